"""Cost and accuracy measures."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def timed(df: DataFrame) -> float:
    """Seconds to compute all rows without keeping them."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def per_dof(runs: DataFrame) -> DataFrame:
    return runs.withColumn("us_per_dof", F.col("seconds") * 1e6 / F.col("dof"))


def run_stats(runs: DataFrame, keys: list[str], value: str = "seconds") -> DataFrame:
    return runs.groupBy(*keys).agg(F.count("*").alias("runs"), F.min(value).alias("min"), F.avg(value).alias("mean"), F.max(value).alias("max"))


def speedup(runs: DataFrame, base: str, other: str) -> DataFrame:
    a = runs.where(F.col("device") == base).select("workload", "dof", F.col("seconds").alias("base"))
    b = runs.where(F.col("device") == other).select("workload", "dof", F.col("seconds").alias("fast"))
    return a.join(b, ["workload", "dof"]).withColumn("factor", F.col("base") / F.col("fast"))


def scaling(seconds: dict[str, float], rates: dict[str, float]) -> dict[str, tuple[float, float]]:
    """(measured, ideal) factor of all devices together against each one."""
    total = sum(rates.values())
    return {d: (seconds[d] / seconds["all"], total / rates[d]) for d in rates}


def package_stats(packages: DataFrame) -> DataFrame:
    """Number of lists, their sizes, and the bytes of the largest (memory held by an open list)."""
    return packages.groupBy("list").agg(F.sum("bytes").alias("b"), F.count("*").alias("c")).agg(F.count("*").alias("lists"), F.max("b").alias("largest"), F.avg("b").alias("mean_bytes"), F.max("c").alias("most_items"))


def recompute(histogram: DataFrame, regular_points: int) -> DataFrame:
    """Share of pairs that phase 2 evaluates again, and the points spent on them in phase 1."""
    touching = F.sum(F.when(F.col("case") > 0, F.col("pairs")).otherwise(0))
    return histogram.agg(touching.alias("touching"), F.sum("pairs").alias("pairs"), (touching * regular_points).alias("wasted_points"))


def kernel_evals(histogram: DataFrame, quad) -> DataFrame:
    """Kernel evaluations by class."""
    from .quadrature import rule

    points = F.create_map(*[x for c in range(4) for x in (F.lit(c), F.lit(len(rule(c, quad.points(c)))))])
    return histogram.withColumn("points", F.element_at(points, F.col("case"))).withColumn("evaluations", F.col("pairs") * F.col("points"))


def kv_ratio(histogram: DataFrame, quad) -> DataFrame:
    """Kernel evaluations of the double layer (whole matrix, without the identical class, which is 0) against those of the
    single layer (one half and the diagonal)."""
    rows = kernel_evals(histogram, quad)
    identical, all_ = F.col("case") == 3, F.col("evaluations")
    v, k = F.sum(F.when(identical, all_).otherwise(all_ / 2)).cast("long"), F.sum(F.when(identical, 0).otherwise(all_)).cast("long")
    return rows.agg(v.alias("v_evaluations"), k.alias("k_evaluations")).withColumn("ratio", F.col("k_evaluations") / F.col("v_evaluations"))


def tree_stats(clusters: DataFrame, blocks: DataFrame) -> DataFrame:
    return clusters.agg(F.count("*").alias("clusters"), F.sum(F.col("is_leaf").cast("int")).alias("leaves"), F.max("level").alias("depth")).crossJoin(blocks.agg(F.count("*").alias("blocks"), F.sum((F.col("kind") == "far").cast("int")).alias("far")))


def rank_stats(basis: DataFrame, m: int) -> DataFrame:
    """Ranks by level, and against the 2 m columns of the un-pivoted form."""
    ranks = basis.groupBy("level", "node").agg(F.sum((F.col("place") >= 0).cast("int")).alias("rank"))
    return ranks.groupBy("level").agg(F.count("*").alias("clusters"), F.min("rank").alias("min"), F.percentile_approx("rank", 0.5).alias("median"), F.max("rank").alias("max"), (F.max("rank") / F.lit(2.0 * m)).alias("share"))


def block_error(exact: DataFrame, approximate: DataFrame, keys: list[str]) -> DataFrame:
    """Relative Frobenius error by block: both (keys, i, j, re)."""
    both = exact.join(approximate.select(*keys, "i", "j", F.col("re").alias("other")), [*keys, "i", "j"])
    return both.groupBy(*keys).agg(F.sqrt(F.sum((F.col("re") - F.col("other")) ** 2) / F.sum(F.col("re") ** 2)).alias("error"))


def neumann_error(alpha: DataFrame, exact: DataFrame, panels: DataFrame) -> DataFrame:
    """Relative L2 error of piecewise constants against exact values at the centroids."""
    rows = alpha.join(exact.select("i", F.col("value").alias("exact")), "i").join(panels.select(F.col("pid").alias("i"), "area"), "i")
    return rows.agg(F.sqrt(F.sum(F.col("area") * (F.col("value") - F.col("exact")) ** 2) / F.sum(F.col("area") * F.col("exact") ** 2)).alias("error"))


def convergence_order(errors: DataFrame) -> DataFrame:
    """errors(workload, n, error): log2 of the ratio to the next coarser level, scaled by the refinement."""
    w = Window.partitionBy("workload").orderBy("n")
    before, n0 = F.lag("error").over(w), F.lag("n").over(w)
    return errors.withColumn("order", F.log(before / F.col("error")) / F.log(F.col("n") / n0))


def exterior_error(values: DataFrame, exact: DataFrame) -> DataFrame:
    d = F.sqrt((F.col("re") - F.col("e_re")) ** 2 + (F.col("im") - F.col("e_im")) ** 2)
    return values.join(exact, "tid").agg(F.max(d / F.sqrt(F.col("e_re") ** 2 + F.col("e_im") ** 2)).alias("max_relative"), F.count("*").alias("targets"))


def dense_bytes(n: int) -> int:
    return 8 * n * n
