"""Singularity classes of panel pairs: the number of common vertices, found by equi-joins on vertex ids."""

from __future__ import annotations

from itertools import combinations
from math import comb

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def incidence(panels: DataFrame, key: str = "pid", corners=("v0", "v1", "v2")) -> DataFrame:
    return panels.select(F.col(key).alias("pid"), F.explode(F.array(*corners)).alias("vid"))


def touching(panels: DataFrame, other: DataFrame | None = None) -> DataFrame:
    """(i, j, case) of all ordered pairs with a common vertex; linear in the mesh, hub vertices are left to adaptive skew joins."""
    a = incidence(panels).withColumnRenamed("pid", "i")
    b = incidence(other if other is not None else panels).withColumnRenamed("pid", "j")
    return a.join(b, "vid").groupBy("i", "j").agg(F.count("*").cast("int").alias("case"))


def classes(pairs: DataFrame, panels: DataFrame) -> DataFrame:
    """pairs(i, j) with their case; class 0 is the absence of a touching row, so no pair is ever made to find it."""
    return pairs.join(touching(panels), ["i", "j"], "left").withColumn("case", F.coalesce("case", F.lit(0)))


def class_histogram(panels: DataFrame, weight: str | None = None) -> DataFrame:
    """Ordered pairs by class, class 0 as the rest of N^2. weight: the rows that each panel carries, whose pairs are counted."""
    if weight is None:
        near = touching(panels).groupBy("case").agg(F.count("*").alias("pairs"))
        total = panels.agg(F.count("*").alias("n"))
    else:
        held = panels.where(F.col(weight) > 0).select("pid", weight)
        a, b = held.select(F.col("pid").alias("i"), F.col(weight).alias("wa")), held.select(F.col("pid").alias("j"), F.col(weight).alias("wb"))
        near = touching(panels).join(a, "i").join(b, "j").groupBy("case").agg(F.sum(F.col("wa") * F.col("wb")).alias("pairs"))
        total = panels.agg(F.coalesce(F.sum(weight), F.lit(0)).alias("n"))
    rest = near.agg(F.coalesce(F.sum("pairs"), F.lit(0)).alias("near")).crossJoin(total).select(F.lit(0).alias("case"), (F.col("n") * F.col("n") - F.col("near")).alias("pairs"))
    return near.unionByName(rest)


def _corners(side: str) -> Column:
    one = [F.struct(F.col(f"{side}_v{j}").alias("vid"), *[F.col(f"{side}_{p}{x}").alias(x) for x in "xyz"]) for j, p in enumerate("abc")]
    return F.array(*one)


def aligned(pairs: DataFrame) -> DataFrame:
    """Reorders the corners of both panels of each row: the common ones first, by vertex id, the others as they were.

    Columns a_v0.., a_ax.. and b_v0.., b_ax.. are replaced; normals stay those of the panel.
    """
    ids = {s: F.array(*[F.col(f"{s}_v{j}") for j in range(3)]) for s in "ab"}
    rows = pairs.withColumns({"_ca": _corners("a"), "_cb": _corners("b"), "_common": F.array_sort(F.array_intersect(ids["a"], ids["b"]))})

    def order(corners: str) -> Column:
        first = F.transform("_common", lambda v: F.element_at(F.filter(corners, lambda c: c["vid"] == v), 1))
        return F.concat(first, F.filter(corners, lambda c: ~F.array_contains(F.col("_common"), c["vid"])))

    rows = rows.withColumns({"_ca": order("_ca"), "_cb": order("_cb")})
    new = {}
    for s in "ab":
        for j, p in enumerate("abc"):
            c = F.element_at(F.col(f"_c{s}"), j + 1)
            new[f"{s}_v{j}"] = c["vid"]
            for x in "xyz":
                new[f"{s}_{p}{x}"] = c[x]
    return rows.withColumns(new).drop("_ca", "_cb", "_common")


def shared_id_counts(rows: DataFrame, ids: list[str]) -> DataFrame:
    """Ordered pairs of rows by how many of their ids are equal, column by column, without making a pair.

    A group of n rows that agree in a set of columns has n^2 pairs. The sum of these over all sets of k columns counts a pair
    with m equal ids binomial(m, k) times; the pairs of each class follow from the widest set down. Nulls are equal to nothing.
    """
    sums, count = [], {}
    for k in range(len(ids) + 1):
        count[k] = F.lit(0).cast("decimal(38,0)")
        for chosen in combinations(ids, k):
            groups = rows.dropna(subset=list(chosen)) if chosen else rows
            n = groups.groupBy(*chosen).agg(F.count("*").cast("decimal(18,0)").alias("n"))
            sums.append(n.agg(F.coalesce(F.sum(F.col("n") * F.col("n")), F.lit(0)).cast("decimal(38,0)").alias(f"s{len(sums)}")))
            count[k] += F.col(f"s{len(sums) - 1}")
    one = sums[0]
    for s in sums[1:]:
        one = one.crossJoin(F.broadcast(s))
    exact = {}
    for k in range(len(ids), -1, -1):
        exact[k] = count[k] - sum((exact[m] * F.lit(comb(m, k)) for m in range(k + 1, len(ids) + 1)), F.lit(0))
    cases = F.array(*[F.struct(F.lit(k).alias("case"), e.cast("long").alias("pairs")) for k, e in exact.items()])
    return one.select(F.explode(cases).alias("c")).select("c.*").where("pairs > 0 or case = 0")
