"""Language identification: family first, then one-versus-one linear support vector machines within the family.

Features are hashed byte n-grams (1 to 4) of the lower-cased text, as shares of all n-grams. The family model is a set
of one-versus-one machines between families, the models within a family are one-versus-one between its languages;
the votes decide, margins break ties. All machines are learnt on a bounded sample of labelled rows: the
`per_language` documents of each language with the smallest hash of doc_id (a repeated id counts once; rows without an
id are not learnt from).

Null texts and texts without a letter are `und` with score 0. Ties and repeated rows: the result depends on the
text only. An empty training table gives `und` for all. Languages without a known family form their own.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import U, byte_view, lowered, mix, settled, shipped

BITS = 15
ORDERS = (1, 2, 3, 4)
MANY = 10_000
# Language codes by family.
FAMILIES = {
    "germanic": ["en", "de", "nl", "sv", "da", "no", "is", "af"],
    "romance": ["fr", "es", "it", "pt", "ro", "ca", "gl"],
    "slavic": ["ru", "uk", "pl", "cs", "sk", "bg", "sr", "hr", "sl"],
    "uralic": ["fi", "et", "hu"],
    "sinitic": ["zh", "yue"],
    "semitic": ["ar", "he", "mt"],
    "indic": ["hi", "bn", "mr", "ur", "gu", "pa"],
}
FAMILY = {code: family for family, codes in FAMILIES.items() for code in codes}


def codes(data: np.ndarray, order: int) -> np.ndarray:
    """The hashed n-gram that starts at each byte; those that run over the end of the buffer are left out."""
    n = len(data) - order + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    x = np.zeros(n, np.uint64)
    for k in range(order):
        x = (x << U(8)) | data[k : n + k]
    return (mix(x + U(order << 40)) >> U(64 - BITS)).astype(np.int64)


def gram_shares(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sparse features of one text."""
    counts = np.zeros(1 << BITS, np.int64)
    for order in ORDERS:
        counts += np.bincount(codes(data, order), minlength=1 << BITS)
    where = np.flatnonzero(counts)
    return where, counts[where] / max(1, counts.sum())


def featured(batches):
    for batch in batches:
        data, off = byte_view(batch.column(2))
        data = lowered(data)
        where, shares = [], []
        for i in range(batch.num_rows):
            w, s = gram_shares(data[off[i] : off[i + 1]])
            where.append(w.astype(np.int32))
            shares.append(s.astype(np.float32))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(where, pa.list_(pa.int32())), pa.array(shares, pa.list_(pa.float32()))], ["doc_id", "lang", "at", "share"])


def training_sample(docs: DataFrame, per_language: int) -> DataFrame:
    """(doc_id, lang, text): at most per_language documents of each language, those whose ids have the smallest hashes.

    A hash bound from the number of ids of a language leaves about four times as many as wanted, so no task ever sees all
    rows of a language. The bounds, and the ids to fetch texts with, are broadcast while the languages are at most MANY (a
    counted table); of an id's texts in one language, the smallest counts.
    """
    rows = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull())
    counts = settled(rows.groupBy("lang").agg((4.0 * per_language / F.approx_count_distinct("doc_id") - 0.5).alias("bound")))
    counts = F.broadcast(counts) if counts.count() <= MANY else counts
    hashed = rows.select("doc_id", "lang", F.xxhash64("doc_id").alias("h"))
    near = hashed.join(counts, "lang").where(F.col("h") / float(2**64) < F.col("bound")).distinct()
    order = Window.partitionBy("lang").orderBy("h", "doc_id")
    picked = near.withColumn("r", F.row_number().over(order)).where(F.col("r") <= per_language).select("doc_id", "lang")
    picked = settled(picked)
    picked = F.broadcast(picked) if picked.count() <= MANY * 20 else picked
    return rows.select("doc_id", "lang", "text").join(picked, ["doc_id", "lang"]).groupBy("doc_id", "lang").agg(F.min("text").alias("text"))


def linear_svm(rows: list, sign: np.ndarray, rounds: int = 30, cost: float = 8.0) -> np.ndarray:
    """Dual coordinate descent for the L2-regularised hinge loss; the last weight is the bias."""
    w = np.zeros((1 << BITS) + 1)
    alpha = np.zeros(len(rows))
    norm = [float(v @ v) + 1.0 for _, v in rows]
    order = np.random.default_rng(7)
    for _ in range(rounds):
        moved = 0.0
        for i in order.permutation(len(rows)):
            at, v = rows[i]
            gradient = sign[i] * (w[at] @ v + w[-1]) - 1.0
            new = min(max(alpha[i] - gradient / norm[i], 0.0), cost)
            if new != alpha[i]:
                step = (new - alpha[i]) * sign[i]
                w[at] += step * v
                w[-1] += step
                moved = max(moved, abs(new - alpha[i]))
                alpha[i] = new
        if moved < 1e-3:
            break
    return w


def fit(sample: list) -> dict:
    """sample: (lang, where, share) rows. The weights of all machines side by side, and who plays against whom."""
    scaled = [(lang, np.asarray(at, np.int64), np.asarray(v) / (np.linalg.norm(v) or 1.0)) for lang, at, v in sample]
    langs = sorted({lang for lang, _, _ in scaled})
    families: dict[str, list[str]] = {}
    for lang in langs:
        families.setdefault(FAMILY.get(lang, lang), []).append(lang)
    games = []

    def play(level, a, b, side):
        rows = [(at, v) for lang, at, v in scaled if side(lang)]
        sign = np.array([side(lang) for lang, _, _ in scaled if side(lang)], float)
        games.append((level, a, b, linear_svm(rows, sign)))

    names = sorted(families)
    for a, b in itertools.combinations(names, 2):
        play("", a, b, lambda x, a=a, b=b: (x in families[a]) * 1 - (x in families[b]) * 1)
    for family in names:
        for a, b in itertools.combinations(families[family], 2):
            play(family, a, b, lambda x, a=a, b=b: (x == a) * 1 - (x == b) * 1)
    weights = np.stack([g[3] for g in games], 1).astype(np.float32) if games else np.zeros(((1 << BITS) + 1, 0), np.float32)
    return {"families": families, "games": [g[:3] for g in games], "weights": weights}


def decide(model: dict, margins: np.ndarray) -> tuple[str, float]:
    """The winner and its confidence from the margins of all machines."""

    def winner(level: str, names: list[str]) -> tuple[str, float]:
        votes, sums, least = dict.fromkeys(names, 0), dict.fromkeys(names, 0.0), dict.fromkeys(names, 20.0)
        for (lv, a, b), m in zip(model["games"], margins, strict=True):
            if lv == level:
                for who, x in ((a, m), (b, -m)):
                    votes[who] += x > 0
                    sums[who] += x
                    least[who] = min(least[who], x)
        best = max(names, key=lambda n: (votes[n], sums[n], n))
        return best, float(1.0 / (1.0 + np.exp(-2.0 * max(-15.0, least[best]))))

    family, p = winner("", sorted(model["families"]))
    members = model["families"][family]
    if len(members) == 1:
        return members[0], p
    lang, q = winner(family, members)
    return lang, p * q


def predicted(batches, model: dict):
    weights = model["weights"]
    inner, bias = weights[:-1], weights[-1].astype(float)
    for batch in batches:
        data, off = byte_view(batch.column(1))
        has = batch.column(2).to_pylist()
        data = lowered(data)
        langs, scores = [], []
        for i in range(batch.num_rows):
            if not has[i] or not model["families"]:
                langs.append("und")
                scores.append(0.0)
                continue
            counts = np.zeros(1 << BITS, np.int64)
            for p in range(int(off[i]), int(off[i + 1]), 1 << 20):  # long texts in pieces; n-grams across them included
                for order in ORDERS:
                    counts += np.bincount(codes(data[p : min(p + (1 << 20) + order - 1, int(off[i + 1]))], order), minlength=1 << BITS)
            at = np.flatnonzero(counts)
            v = counts[at].astype(np.float32)
            v /= np.linalg.norm(v) or 1.0
            lang, score = decide(model, v @ inner[at] + bias)
            langs.append(lang)
            scores.append(score)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], ["doc_id", "lang_pred", "score"])


def train(labelled: DataFrame, per_language: int = 400) -> dict:
    """The model from labelled rows (doc_id, lang, text); the driver holds at most per_language rows of each language."""
    rows = training_sample(labelled, per_language).mapInArrow(shipped("panelspark.llm.language", "featured"), "doc_id long, lang string, at array<int>, share array<float>").toArrow().sort_by("doc_id")
    sample = [(l, a, s) for l, a, s in zip(rows.column(1).to_pylist(), (np.asarray(x.values) for x in rows.column(2)), (np.asarray(x.values) for x in rows.column(3)), strict=True)]
    return fit(sample)


def predict(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, lang_pred and score of each row; narrow. The model takes 131 kB a machine, and l languages of one family have
    l (l - 1) / 2 machines; it travels with the function, which PySpark broadcasts once it exceeds a megabyte."""
    rows = docs.select("doc_id", "text", F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False)).alias("has_letter"))
    return rows.mapInArrow(shipped("panelspark.llm.language", "predicted", model), "doc_id long, lang_pred string, score double")
