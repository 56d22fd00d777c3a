"""One query for each document operator, over whole tables, with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import jaccard, language, media, mixing, neighbours, pieces, pii, repeats, token_counts, toxicity
from .common import table


def tokenizer(name: str) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


WEIGHTS = {"src0": 2, "src1": 3, "src2": 1, "src3": 2}
REST_WEIGHT = 8
BLOCK_BYTES = 1 << 16


def op1_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.without_repeats(table(spark, sf_dir, "documents"), length=50)


def op2_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.encode(table(spark, sf_dir, "documents"), tokenizer("piece_bpe_32k.model"))


def op3_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mixing.mixed(table(spark, sf_dir, "documents"), WEIGHTS, REST_WEIGHT, BLOCK_BYTES)
    return out.select("doc_id", *(F.col(f"_{c}").alias(c) for c in ("stream", "block", "slot", "release", "deadline", "place", "balanced")))


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(table(spark, sf_dir, "documents"), tokenizer("piece_bpe_32k.model"))


def _fold(k: int):
    return F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(k))


def op5_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = language.train(docs.where(_fold(3) != 1))
    return language.predict(docs, model).select("doc_id", (_fold(3) == 1).alias("held_out"), "lang_pred", "score")


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = toxicity.train(docs, labels.where(_fold(4) != 2))
    return toxicity.score(docs, model).select("doc_id", (_fold(4) == 2).alias("held_out"), "score", "predicted")


def op7_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return neighbours.nearest(vectors, vectors.where(F.col("vec_id") % 100 == 0), k=10)


def op8_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(table(spark, sf_dir, "documents"))


def op9_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.similar(table(spark, sf_dir, "documents"), width=3, top=90, bottom=100)


def op10_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.text_media(table(spark, sf_dir, "documents"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_repeats, op2_pieces, op3_source_mixing, op4_token_counts, op5_language, op6_toxicity, op7_neighbours, op8_personal_data, op9_jaccard_join, op10_media)}


def oracle_sql() -> dict[str, str]:
    return {"op3_source_mixing": mixing.oracle(WEIGHTS, REST_WEIGHT, BLOCK_BYTES), "op8_personal_data": pii.oracle()}
