"""Triangulated unit spheres and other carriers of panels and points.

A mesh is decoded arithmetically from row numbers: eight octants, n strips in each, 2r + 1 panels in strip r. The
integer lattice point of a vertex is its identity, so shared vertices never depend on floating-point equality.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.scratch import settled

COORDS = ("ax", "ay", "az", "bx", "by", "bz", "cx", "cy", "cz")


def refinement(rows: int) -> int:
    """The finest subdivision whose 8 n^2 panels a table of so many rows can carry."""
    return max(1, int((rows / 8) ** 0.5 + 1e-9))


def decoded_panels(pid: np.ndarray, n: int, project: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Vertex ids (panels, 3) and corners (panels, 3, 3) of panels by number, oriented outward."""
    face, k = pid // (n * n), pid % (n * n)
    r = np.floor(np.sqrt(k.astype(float))).astype(np.int64)
    m, up = (k - r * r) // 2, (k - r * r) % 2 == 0
    sign = np.stack([1 - 2 * (face // d % 2) for d in (1, 2, 4)], 1)
    first = np.stack([r - m, m, n - r], 1)
    second = np.where(up[:, None], np.stack([r + 1 - m, m, n - r - 1], 1), np.stack([r - m, m + 1, n - r - 1], 1))
    third = np.where(up[:, None], np.stack([r - m, m + 1, n - r - 1], 1), np.stack([r - m - 1, m + 1, n - r], 1))
    odd = (sign.prod(1) < 0)[:, None]
    points = np.stack([first, np.where(odd, third, second), np.where(odd, second, third)], 1) * sign[:, None, :]
    side = 2 * n + 1
    ids = ((points[..., 0] + n) * side + points[..., 1] + n) * side + points[..., 2] + n
    d = points.astype(float)
    size = np.sqrt(d[..., 0] * d[..., 0] + d[..., 1] * d[..., 1] + d[..., 2] * d[..., 2])[..., None] if project else float(n)
    return ids, d / size + 0.0


def sphere_panels(spark: SparkSession, n: int, project: bool = True) -> DataFrame:
    """8 n^2 panels: pid, v0..v2 (vertex ids) and the nine coordinates; narrow over a range. Decoded in one step, since the
    same arithmetic as expressions makes plans of which each query spends seconds on optimising and compiling."""

    def run(batches):
        for batch in batches:
            ids, x = decoded_panels(np.asarray(batch.column(0)), n, project)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(np.ascontiguousarray(ids[:, k])) for k in range(3)), *(pa.array(np.ascontiguousarray(x[:, k, a])) for k in range(3) for a in range(3))], names)

    names = ["pid", "v0", "v1", "v2", *COORDS]
    return spark.range(8 * n * n).withColumnRenamed("id", "pid").mapInArrow(run, "pid long, v0 long, v1 long, v2 long, " + ", ".join(f"{c} double" for c in COORDS))


def vertices(panels: DataFrame) -> DataFrame:
    """Distinct vertices: vid, x, y, z."""
    corner = [F.struct(F.col(f"v{j}").alias("vid"), F.col(f"{p}x").alias("x"), F.col(f"{p}y").alias("y"), F.col(f"{p}z").alias("z")) for j, p in enumerate("abc")]
    return panels.select(F.explode(F.array(*corner)).alias("c")).select("c.*").groupBy("vid").agg(*[F.first(x).alias(x) for x in "xyz"])


def sphere_mesh(spark: SparkSession, n: int, project: bool = True) -> tuple[DataFrame, DataFrame]:
    panels = with_metrics(sphere_panels(spark, n, project))
    return vertices(panels), panels


def cross(a, b):
    return (a[1] * b[2] - a[2] * b[1], a[2] * b[0] - a[0] * b[2], a[0] * b[1] - a[1] * b[0])


def with_metrics(panels: DataFrame) -> DataFrame:
    """Adds gram (twice the area), area, the unit normal, the centroid and the box.

    Panels without area get a null normal.
    """
    p = {x: tuple(F.col(f"{x}{axis}") for axis in "xyz") for x in "abc"}
    e1 = tuple(q - r for q, r in zip(p["b"], p["a"], strict=True))
    e2 = tuple(q - r for q, r in zip(p["c"], p["b"], strict=True))
    n = cross([F.col(f"_e1{a}") for a in "xyz"], [F.col(f"_e2{a}") for a in "xyz"])
    out = panels.withColumns({f"_e{k}{a}": c for k, e in ((1, e1), (2, e2)) for a, c in zip("xyz", e, strict=True)})
    out = out.withColumns({"_nx": n[0], "_ny": n[1], "_nz": n[2]})
    out = out.withColumn("gram", F.sqrt(F.col("_nx") * F.col("_nx") + F.col("_ny") * F.col("_ny") + F.col("_nz") * F.col("_nz")))
    new = {"area": F.col("gram") / 2}
    for axis in "xyz":
        corners = [F.col(f"{x}{axis}") for x in "abc"]
        new[f"n{axis}"] = F.try_divide(F.col(f"_n{axis}"), F.col("gram")) + 0.0
        new[f"g{axis}"] = (corners[0] + corners[1] + corners[2]) / 3.0 + 0.0
        new[f"lo{axis}"] = F.least(*corners)
        new[f"hi{axis}"] = F.greatest(*corners)
    return out.withColumns(new).drop("_nx", "_ny", "_nz", *[f"_e{k}{a}" for k in (1, 2) for a in "xyz"])


def carried_panels(spark: SparkSession, table: DataFrame, key: str, value: str, n: int) -> DataFrame:
    """The panels of refinement n, each with the value of the k-th row of the table by key as its density.

    The row numbers come from a range-partitioned prefix count, so no task sorts the whole table.
    """
    panels = with_metrics(sphere_panels(spark, n))
    return panels.join(numbered(table.select(key, value), [key, value]).select(F.col("_row").alias("pid"), F.col(value).cast("double").alias("density")), "pid")


def folded_panels(spark: SparkSession, table: DataFrame, key: str, value: str, n: int) -> DataFrame:
    """The panels of refinement n, with every row of the table on one: row k by key adds its value to panel k mod 8 n^2.

    A panel without a row has the density 0.
    """
    rows = numbered(table.select(key, value), [key, value]).groupBy(F.pmod("_row", F.lit(8 * n * n)).alias("pid")).agg(F.sum(F.col(value).cast("double")).alias("density"))
    return with_metrics(sphere_panels(spark, n)).join(rows, "pid", "left").withColumn("density", F.coalesce("density", F.lit(0.0)))


def parts_for(rows: DataFrame, each: int = 250_000, most: int = 100_000) -> int:
    """So many ranges that each holds about `each` rows (counted here)."""
    return max(1, min(most, -(-rows.count() // each)))


def ranged(rows: DataFrame, order: list[str], parts: int | None = None) -> DataFrame:
    """rows with the number of their range as `_part`, ranges in the given order.

    Several ranges are written once and read again: their bounds are sampled, and each use of the plan would draw its own.
    """
    parts = parts or parts_for(rows)
    spread = rows.repartitionByRange(parts, *order).withColumn("_part", F.spark_partition_id())
    return spread if parts == 1 else settled(spread)


def numbered(rows: DataFrame, order: list[str], parts: int | None = None) -> DataFrame:
    """Adds `_row` (from 0) in the given order, by counting ranges first: two shuffles of the keys, no global sort task."""
    spread = ranged(rows, order, parts)
    counts = spread.groupBy("_part").agg(F.count("*").alias("_n"))
    before = counts.withColumn("_before", F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1))).select("_part", F.coalesce("_before", F.lit(0)).alias("_before"))
    within = spread.withColumn("_r", F.row_number().over(Window.partitionBy("_part").orderBy(*order)))
    return within.join(F.broadcast(before), "_part").withColumn("_row", (F.col("_r") - 1 + F.col("_before")).cast("long")).drop("_part", "_before", "_r")


def unit_points(rows: DataFrame, key: str, vector: str) -> DataFrame:
    """Points on the unit sphere: the first three components of a vector, rescaled. Zero vectors are left out."""
    c = [F.element_at(F.col(vector), j + 1).cast("double") for j in range(3)]
    r = F.sqrt(c[0] * c[0] + c[1] * c[1] + c[2] * c[2])
    return rows.select(F.col(key).cast("long").alias("i"), *[x.alias(a) for x, a in zip(c, "xyz", strict=True)], r.alias("_r")).where("_r > 0").select("i", *[(F.col(a) / F.col("_r")).alias(a) for a in "xyz"])


def scaled_points(rows: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """Three numeric columns scaled by their extremes into the unit cube."""
    ends = rows.agg(*[f(F.col(c).cast("double")).alias(f"{n}{j}") for j, c in enumerate(columns) for n, f in (("lo", F.min), ("hi", F.max))])
    x = [F.coalesce(F.try_divide(F.col(c).cast("double") - F.col(f"lo{j}"), F.col(f"hi{j}") - F.col(f"lo{j}")), F.lit(0.0)) for j, c in enumerate(columns)]
    return rows.crossJoin(F.broadcast(ends)).select(F.col(key).cast("long").alias("i"), *[c.alias(a) for c, a in zip(x, "xyz", strict=True)])


def euler(panels: DataFrame) -> DataFrame:
    """Vertices, edges, panels and V - E + F; edges with other than two panels, and edges passed twice the same way."""
    v = [F.col(f"v{j}") for j in range(3)]
    edge = F.explode(F.array(*[F.struct(F.least(a, b).alias("lo"), F.greatest(a, b).alias("hi"), F.when(a < b, 1).otherwise(-1).alias("way")) for a, b in ((v[0], v[1]), (v[1], v[2]), (v[2], v[0]))])).alias("e")
    edges = panels.select(edge).select("e.*").groupBy("lo", "hi").agg(F.count("*").alias("n"), F.sum("way").alias("w"))
    e = edges.agg(F.count("*").alias("edges"), F.sum(F.when(F.col("n") != 2, 1).otherwise(0)).alias("odd_edges"), F.sum(F.when(F.col("w") != 0, 1).otherwise(0)).alias("twisted_edges"))
    p = panels.agg(F.count("*").alias("panels"))
    q = panels.select(F.explode(F.array(*v)).alias("vid")).agg(F.countDistinct("vid").alias("vertices"))
    return e.crossJoin(p).crossJoin(q).select("vertices", "edges", "panels", (F.col("vertices") - F.col("edges") + F.col("panels")).alias("euler"), "odd_edges", "twisted_edges")
