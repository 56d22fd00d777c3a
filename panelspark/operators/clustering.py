"""Cluster trees in heap numbering: the root is 1, the sons of k are 2k and 2k + 1."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import settled

DEEPEST = 60
FINISH = 1 << 16
POINT = "i long, node long, level int"


def _subtree(table: pa.Table, leaf_size: int) -> pa.Table:
    """(i, node, level) of the points of one node, halved to the end by the rule of geometric_tree."""
    x = np.stack([np.asarray(table.column(a)) for a in "xyz"], 1)
    ids = np.asarray(table.column("i"))
    stack = [(np.arange(len(x)), int(table.column("node")[0].as_py()), int(table.column("level")[0].as_py()))]
    node, level = np.zeros(len(x), np.int64), np.zeros(len(x), np.int32)
    while stack:
        rows, n, k = stack.pop()
        lo, hi = x[rows].min(0), x[rows].max(0)
        wide = hi - lo
        axis = 0 if wide[0] >= wide[1] and wide[0] >= wide[2] else 1 if wide[1] >= wide[2] else 2
        if len(rows) <= leaf_size or wide.max() <= 0 or k >= DEEPEST:
            node[rows], level[rows] = n, k
            continue
        left = x[rows, axis] <= (lo[axis] + hi[axis]) / 2
        stack += [(rows[left], 2 * n, k + 1), (rows[~left], 2 * n + 1, k + 1)]
    return pa.table({"i": pa.array(ids), "node": pa.array(node), "level": pa.array(level)})


def geometric_tree(points: DataFrame, leaf_size: int, finish_rows: int = FINISH) -> DataFrame:
    """(i, node, level) of every point: boxes are halved at the middle of their longest axis while they hold too many.

    Nodes of more than finish_rows points are halved by one grouped aggregate a level; as soon as a node is smaller, one
    bounded task ends its whole subtree. Coordinates are compared after rounding to 12 digits, so symmetric meshes split
    alike everywhere. Points that cannot be told apart, and nodes of level 60, end their branch.
    """
    rounded = [F.round(F.col(a), 12).alias(a) for a in "xyz"]
    now = points.select("i", *rounded, F.lit(1).cast("long").alias("node"), F.lit(0).alias("level"))
    small, done = None, None

    def more(all_, some):
        return some if all_ is None else all_.unionByName(some)

    for level in range(DEEPEST + 1):
        box = now.groupBy("node").agg(F.count("*").alias("n"), *[f(a).alias(f"{m}{a}") for a in "xyz" for m, f in (("lo", F.min), ("hi", F.max))])
        wide = {a: F.col(f"hi{a}") - F.col(f"lo{a}") for a in "xyz"}
        box = settled(box.withColumn("wide", F.greatest(*wide.values())))
        if box.where(F.col("n") > finish_rows).isEmpty():
            small = more(small, now)
            break
        axis = F.when((wide["x"] >= wide["y"]) & (wide["x"] >= wide["z"]), 0).when(wide["y"] >= wide["z"], 1).otherwise(2)
        mid = F.when(F.col("axis") == 0, (F.col("lox") + F.col("hix")) / 2).when(F.col("axis") == 1, (F.col("loy") + F.col("hiy")) / 2).otherwise((F.col("loz") + F.col("hiz")) / 2)
        splits = (F.col("n") > leaf_size) & (F.col("wide") > 0) & F.lit(level < DEEPEST)
        fate = F.when(~splits, "ends").when(F.col("n") <= finish_rows, "small").otherwise("large")
        box = box.withColumn("axis", axis).select("node", "axis", mid.alias("mid"), fate.alias("fate"))
        rows = settled(now.join(box, "node"))
        done = more(done, rows.where("fate = 'ends'").select("i", "node", "level"))
        small = more(small, rows.where("fate = 'small'").select("i", "x", "y", "z", "node", "level"))
        value = F.when(F.col("axis") == 0, F.col("x")).when(F.col("axis") == 1, F.col("y")).otherwise(F.col("z"))
        now = rows.where("fate = 'large'").select("i", "x", "y", "z", (F.col("node") * 2 + F.when(value <= F.col("mid"), 0).otherwise(1)).alias("node"), F.lit(level + 1).alias("level"))
    tree = small.groupBy("node").applyInArrow(lambda t: _subtree(t, leaf_size), POINT)
    return tree if done is None else tree.unionByName(done)


def median_tree(points: DataFrame, depth: int) -> DataFrame:
    """(i, node, level): halves by count along axes x, y, z in turn; ties by id. Ranks come from counted ranges, so no task
    holds a whole node."""
    from .geometry import numbered

    now = points.select("i", "x", "y", "z", F.lit(1).cast("long").alias("node"))
    for level in range(depth):
        axis = "xyz"[level % 3]
        ranked = settled(numbered(now, ["node", axis, "i"]))
        first = ranked.groupBy("node").agg(F.count("*").alias("n"), F.min("_row").alias("first"))
        half = (F.col("_row") - F.col("first") + 1) * 2 <= F.col("n") + 1
        now = ranked.join(first, "node").select("i", "x", "y", "z", (F.col("node") * 2 + F.when(half, 0).otherwise(1)).alias("node"))
    return now.select("i", "node", F.lit(depth).alias("level"))


def morton_tree(points: DataFrame, depth: int) -> DataFrame:
    """(i, node, level) after 3 * depth bits of a fixed grid over [-1, 1]^3: no shuffle at all; ancestors are right shifts."""
    cell = {a: F.least(F.greatest(F.floor((F.col(a) + 1.0) / 2.0 * (1 << depth)), F.lit(0)), F.lit((1 << depth) - 1)).cast("long") for a in "xyz"}
    code = F.lit(1).cast("long")
    for bit in range(depth - 1, -1, -1):
        for a in "xyz":
            code = code * 2 + F.pmod(F.floor(cell[a] / (1 << bit)).cast("long"), F.lit(2))
    return points.select("i", code.alias("node"), F.lit(3 * depth).alias("level"))


def ancestors(membership: DataFrame) -> DataFrame:
    """(i, node, level) for every ancestor of a point's leaf, the leaf included."""
    up = F.transform(F.sequence(F.lit(0), F.col("level")), lambda k: F.struct(F.floor(F.col("node") / F.pow(F.lit(2.0), k)).cast("long").alias("node"), (F.col("level") - k).alias("level")))
    return membership.select("i", F.explode(up).alias("a")).select("i", "a.node", "a.level")


def boxes(membership: DataFrame, extents: DataFrame) -> DataFrame:
    """clusters(node, level, is_leaf, cnt, lox..hiz, diam, diam_max): boxes merged upward from (i, lox..hiz).

    Leaves first, then their ancestors from the (much smaller) leaf table.
    """
    ends = [F.min(f"lo{a}").alias(f"lo{a}") for a in "xyz"] + [F.max(f"hi{a}").alias(f"hi{a}") for a in "xyz"]
    leaf = membership.join(extents, "i").groupBy("node", "level").agg(F.count("*").alias("cnt"), *ends)
    up = leaf.withColumn("k", F.explode(F.sequence(F.lit(0), F.col("level"))))
    rows = up.select(F.floor(F.col("node") / F.pow(F.lit(2.0), F.col("k"))).cast("long").alias("node"), (F.col("level") - F.col("k")).cast("int").alias("level"), (F.col("k") == 0).alias("is_leaf"), "cnt", *[f"{m}{a}" for m in ("lo", "hi") for a in "xyz"])
    out = rows.groupBy("node", "level").agg(F.max("is_leaf").alias("is_leaf"), F.sum("cnt").alias("cnt"), *ends)
    wide = [F.col(f"hi{a}") - F.col(f"lo{a}") for a in "xyz"]
    return out.withColumn("diam", F.sqrt(wide[0] * wide[0] + wide[1] * wide[1] + wide[2] * wide[2])).withColumn("diam_max", F.greatest(*wide))


def point_extents(points: DataFrame) -> DataFrame:
    return points.select("i", *[F.col(a).alias(f"{m}{a}") for m in ("lo", "hi") for a in "xyz"])


def panel_extents(panels: DataFrame) -> DataFrame:
    return panels.select(F.col("pid").alias("i"), *[f"{m}{a}" for m in ("lo", "hi") for a in "xyz"])


def key_tree(region: DataFrame, nation: DataFrame, rows: DataFrame, nation_key: str, value: str) -> DataFrame:
    """Sums of a value up the hierarchy root, region, nation: the sons of a node partition it."""
    base = rows.join(nation, rows[nation_key] == nation.n_nationkey).join(region, nation.n_regionkey == region.r_regionkey)
    return base.rollup("r_regionkey", "n_nationkey").agg(F.count("*").alias("cnt"), F.sum(value).alias("total"), F.grouping_id().alias("gid"))
