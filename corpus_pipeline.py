"""The corpus pipeline: toxic documents go, one of each group of near copies stays, personal data is masked, the
sources are interleaved by their target weights, and the texts become subword pieces.

Each stage takes (spark, docs, sf_dir) and works on all rows that its predecessor kept. All but the last return the
columns of documents; the mixing stage adds slot and place, which the last stage hands on: the scheduled order of the
result is ORDER BY slot, place. Tests compare the stages with brute-force versions; SQL cannot express them together.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from panelspark.llm import jaccard, mixing, pieces, pii, queries, toxicity
from panelspark.llm.common import settled, table

ORACLE_SQL = None


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Learns from the labelled documents among the given ones and removes those that the model rejects."""
    return toxicity.kept(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Five-word shingles, similarity of 0.8 or more: the smallest doc_id of each group stays."""
    return jaccard.representatives(docs, width=5, top=80, bottom=100)


def mask_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces every span by its kind; DataFrame functions only."""
    return pii.redacted(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, in the order of the schedule, with slot and place."""
    return mixing.scheduled(docs, queries.WEIGHTS, queries.REST_WEIGHT, queries.BLOCK_BYTES)


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_pieces, ids and round_trip of each document, with slot and place where docs have them."""
    return pieces.encode(docs, queries.tokenizer("piece_bpe_32k.model"), keep=tuple(c for c in ("slot", "place") if c in docs.columns))


STAGES = [
    ("toxicity", drop_toxic),
    ("near copies", drop_near_copies),
    ("personal data", mask_personal_data),
    ("source mixing", mix_sources),
    ("subword pieces", encode_pieces),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = settled(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
