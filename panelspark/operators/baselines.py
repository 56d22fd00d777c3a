"""Baselines that the methods are compared with, where they are not a mode of a method."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import FOUR_PI


def monopoles(membership: DataFrame, points: DataFrame, charge: str = "charge") -> DataFrame:
    """(node, q, x, y, z): total charge and its mean place, by cluster and all its ancestors."""
    from .clustering import ancestors

    rows = ancestors(membership).join(points, "i")
    w = F.sum(charge)
    return rows.groupBy("node").agg(w.alias("q"), *[F.avg(a).alias(a) for a in "xyz"])


PAIRS = [(a, b) for k, a in enumerate("xyz") for b in "xyz"[k:]]


def multipoles(membership: DataFrame, points: DataFrame, charge: str = "charge") -> DataFrame:
    """(node, q, x, y, z, m_xx .. m_zz): total charge, its mean place, and the second moments about it, by cluster and all
    its ancestors. About the mean place the first moments vanish, so these are the terms up to order 2."""
    from .clustering import ancestors

    rows = ancestors(membership).join(points, "i")
    w = F.col(charge)
    sums = [F.sum(w).alias("q"), *[F.sum(w * F.col(a)).alias(f"s{a}") for a in "xyz"], *[F.sum(w * F.col(a) * F.col(b)).alias(f"s{a}{b}") for a, b in PAIRS]]
    out = rows.groupBy("node").agg(*sums).select("node", "q", *[F.try_divide(F.col(f"s{a}"), F.col("q")).alias(a) for a in "xyz"], *[f"s{a}{b}" for a, b in PAIRS])
    return out.select("node", "q", "x", "y", "z", *[(F.col(f"s{a}{b}") - F.col("q") * F.col(a) * F.col(b)).alias(f"m_{a}{b}") for a, b in PAIRS])


def multipole_potential(blocks: DataFrame, membership: DataFrame, points: DataFrame, moments: DataFrame) -> DataFrame:
    """(i, value): far field up to order 2 plus exact near field of point charges."""
    from .clustering import ancestors

    near = monopole_potential(blocks.where("kind = 'near'"), membership, points, moments.select("node", "q", "x", "y", "z"))
    member = ancestors(membership).select("i", "node").join(points.select("i", "x", "y", "z"), "i").withColumnRenamed("node", "t")
    far = blocks.where("kind = 'far'").join(member, "t").join(moments.select(F.col("node").alias("s"), "q", *[F.col(a).alias(f"c{a}") for a in "xyz"], *[f"m_{a}{b}" for a, b in PAIRS]), "s")
    d = {a: F.col(a) - F.col(f"c{a}") for a in "xyz"}
    r2 = d["x"] * d["x"] + d["y"] * d["y"] + d["z"] * d["z"]
    second = sum((F.col(f"m_{a}{b}") * (3 * d[a] * d[b] - (r2 if a == b else 0.0)) * (1 if a == b else 2) for a, b in PAIRS), F.lit(0.0)) / 2
    # a cluster of one point is far from itself by the rule of boxes; its distance is 0 and it adds nothing
    one = far.select("i", F.try_divide(F.col("q") + F.try_divide(second, r2 * r2), FOUR_PI * F.sqrt(r2)).alias("value"))
    return one.unionByName(near).groupBy("i").agg(F.sum("value").alias("value"))


def monopole_potential(blocks: DataFrame, membership: DataFrame, points: DataFrame, moments: DataFrame) -> DataFrame:
    """(i, value): order-0 far field plus exact near field of point charges."""
    from .clustering import ancestors

    member = ancestors(membership).select("i", "node").join(points.select("i", "x", "y", "z", "charge"), "i")
    far = blocks.where("kind = 'far'").join(member.withColumnRenamed("node", "t"), "t").join(moments.select(F.col("node").alias("s"), "q", *[F.col(a).alias(f"m{a}") for a in "xyz"]), "s")
    near = blocks.where("kind = 'near'").join(member.withColumnRenamed("node", "t"), "t").join(member.select(F.col("node").alias("s"), F.col("i").alias("j"), F.col("charge").alias("q"), *[F.col(a).alias(f"m{a}") for a in "xyz"]), "s").where("i <> j")
    r = F.sqrt(sum(((F.col(a) - F.col(f"m{a}")) ** 2 for a in "xyz"), F.lit(0.0)))
    one = lambda df: df.select("i", F.try_divide(F.col("q"), FOUR_PI * r).alias("value"))
    return one(far).unionByName(one(near)).groupBy("i").agg(F.sum("value").alias("value"))


def direct(blocks: DataFrame, membership: DataFrame, panels: DataFrame, kernel, quad) -> DataFrame:
    """Walks the block leaves and evaluates their entries as expressions: no packages, no Python."""
    from .assembly import one_pass
    from .clustering import ancestors

    m = ancestors(membership).select("node", "i")
    pairs = blocks.join(m.withColumnRenamed("node", "t"), "t").join(m.select(F.col("node").alias("s"), F.col("i").alias("j")), "s").select("i", "j")
    return one_pass(panels, kernel, quad, pairs)
