"""Block trees: pairs of clusters, split until they are admissible (far) or both are leaves (near)."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import settled

NODE = ["node", "is_leaf", "cnt", "lox", "loy", "loz", "hix", "hiy", "hiz", "diam", "diam_max"]


def _gaps(a: str, b: str) -> list[Column]:
    return [F.greatest(F.lit(0.0), F.col(f"{a}_lo{x}") - F.col(f"{b}_hi{x}"), F.col(f"{b}_lo{x}") - F.col(f"{a}_hi{x}")) for x in "xyz"]


def box_distance(a: str, b: str, norm: str = "max") -> Column:
    g = _gaps(a, b)
    return F.greatest(*g) if norm == "max" else F.sqrt(reduce(lambda p, q: p + q, [x * x for x in g]))


def admissible(a: str, b: str, eta: float, norm: str = "max") -> Column:
    """max of the diameters <= eta * distance of the boxes; columns are prefixed a_, b_."""
    d = "diam_max" if norm == "max" else "diam"
    return F.greatest(F.col(f"{a}_{d}"), F.col(f"{b}_{d}")) <= eta * box_distance(a, b, norm)


def side(clusters: DataFrame, s: str) -> DataFrame:
    return clusters.select(*[F.col(c).alias(f"{s}_{c}") for c in NODE])


BLOCK = "t long, s long, level int, kind string, rows long, cols long"


class _Clusters:
    """Cluster rows as sorted arrays, for a task that expands pairs."""

    def __init__(self, table: pa.Table):
        order = np.argsort(np.asarray(table.column("node")))
        self.node = np.asarray(table.column("node"))[order]
        self.leaf = np.asarray(table.column("is_leaf")).astype(bool)[order]
        self.count = np.asarray(table.column("cnt"))[order]
        self.lo = np.stack([np.asarray(table.column(f"lo{a}"))[order] for a in "xyz"], 1)
        self.hi = np.stack([np.asarray(table.column(f"hi{a}"))[order] for a in "xyz"], 1)
        self.diam, self.diam_max = (np.asarray(table.column(c))[order] for c in ("diam", "diam_max"))

    def at(self, nodes: np.ndarray) -> np.ndarray:
        """Rows of the nodes; -1 where a node has no points."""
        k = np.minimum(np.searchsorted(self.node, nodes), len(self.node) - 1)
        return np.where(self.node[k] == nodes, k, -1)

    def step(self, t: np.ndarray, s: np.ndarray, eta: float, norm: str, symmetric: bool):
        """(kind, rows of t, rows of s) of pairs, and the pairs of sons of those that split (0 far, 1 near, 2 split)."""
        a, b = self.at(t), self.at(s)
        keep = (a >= 0) & (b >= 0)
        t, s, a, b = t[keep], s[keep], a[keep], b[keep]
        gap = np.maximum(np.maximum(self.lo[a] - self.hi[b], self.lo[b] - self.hi[a]), 0.0)
        distance = gap.max(1) if norm == "max" else np.sqrt((gap * gap).sum(1))
        wide = self.diam_max if norm == "max" else self.diam
        kind = np.where(np.maximum(wide[a], wide[b]) <= eta * distance, 0, np.where(self.leaf[a] & self.leaf[b], 1, 2))
        split = kind == 2
        x, y, lx, ly = t[split], s[split], self.leaf[a[split]], self.leaf[b[split]]
        sons = []
        for k in (0, 1):
            for m in (0, 1):
                use = ~((lx & (k == 1)) | (ly & (m == 1)))
                p, q = np.where(lx, x, 2 * x + k)[use], np.where(ly, y, 2 * y + m)[use]
                # of a pair of one cluster with itself, the two mixed pairs of sons are one
                fresh = ~((x[use] == y[use]) & (p < q)) if symmetric else np.ones(len(p), bool)
                sons.append((p[fresh], q[fresh]))
        return (t, s, kind, self.count[a], self.count[b]), tuple(np.concatenate(z) for z in zip(*sons, strict=True))


def _expanded(batches, clusters: _Clusters, eta: float, norm: str, symmetric: bool, most: int = 1 << 18):
    """All leaves below the pairs (t, s, level) of the batches; the frontier is cut into pieces of bounded length."""
    kinds = np.array(["far", "near"], object)
    for batch in batches:
        stack = [(np.asarray(batch.column(0)), np.asarray(batch.column(1)), k) for k in [int(batch.column(2)[0].as_py())]] if batch.num_rows else []
        while stack:
            t, s, level = stack.pop()
            (t, s, kind, rows, cols), (p, q) = clusters.step(t, s, eta, norm, symmetric)
            leaf = np.flatnonzero(kind < 2)
            yield pa.RecordBatch.from_arrays([pa.array(t[leaf]), pa.array(s[leaf]), pa.array(np.full(len(leaf), level, np.int32)), pa.array(kinds[kind[leaf]], pa.string()), pa.array(rows[leaf]), pa.array(cols[leaf])], ["t", "s", "level", "kind", "rows", "cols"])
            stack += [(p[x : x + most], q[x : x + most], level + 1) for x in range(0, len(p), most)]


def block_tree(clusters: DataFrame, eta: float = 1.0, norm: str = "max", symmetric: bool = False, broadcast_rows: int = 1_000_000, max_level: int = 130, seeds: int = 512) -> DataFrame:
    """blocks(t, s, level, kind, rows, cols) of all leaves. symmetric: one of (t, s) and (s, t), which stands for both.

    While the clusters are fewer than broadcast_rows (counted here, at most 90 MB), they go to every task as arrays: the
    driver expands the first levels to some hundred pairs, and tasks expand those to the end. Beyond that, one round of joins
    by node a level, over the frontier only. A leaf cluster against an inner one is its own only son.
    """
    spark = clusters.sparkSession
    if clusters.count() > broadcast_rows:
        return _joined_tree(clusters, eta, norm, symmetric, max_level)
    known = _Clusters(clusters.select("node", "is_leaf", F.col("cnt").cast("long").alias("cnt"), *NODE[3:]).toArrow())
    t, s, level, done = np.ones(1, np.int64), np.ones(1, np.int64), 0, []
    while 0 < len(t) < seeds:
        (a, b, kind, rows, cols), (p, q) = known.step(t, s, eta, norm, symmetric)
        names = np.array(["far", "near"], object)
        done += [(int(x), int(y), level, str(names[k]), int(m), int(n)) for x, y, k, m, n in zip(a, b, kind, rows, cols, strict=True) if k < 2]
        t, s, level = p, q, level + 1
    first = spark.createDataFrame(done, BLOCK)
    if not len(t):
        return first
    seed = spark.createDataFrame(pa.table({"t": t, "s": s, "level": np.full(len(t), level)}).to_pandas()).repartition(min(len(t), max(8, spark.sparkContext.defaultParallelism * 2)))
    return seed.mapInArrow(lambda it: _expanded(it, known, eta, norm, symmetric), BLOCK).unionByName(first)


def _joined_tree(clusters: DataFrame, eta: float, norm: str, symmetric: bool, max_level: int) -> DataFrame:
    """The same by joins, for more clusters than a task should hold."""
    clusters = settled(clusters)
    a, b = side(clusters, "t"), side(clusters, "s")
    frontier = clusters.sparkSession.createDataFrame([(1, 1)], "t long, s long")
    done = None
    for level in range(max_level):
        rows = frontier.join(a, F.col("t") == F.col("t_node")).join(b, F.col("s") == F.col("s_node"))
        far = admissible("t", "s", eta, norm)
        kind = F.when(far, F.lit("far")).when(F.col("t_is_leaf") & F.col("s_is_leaf"), F.lit("near")).otherwise(F.lit("split"))
        rows = settled(rows.select("t", "s", kind.alias("kind"), F.col("t_is_leaf").alias("tl"), F.col("s_is_leaf").alias("sl"), F.col("t_cnt").alias("rows"), F.col("s_cnt").alias("cols")))
        leaves = rows.where("kind <> 'split'").select("t", "s", F.lit(level).alias("level"), "kind", "rows", "cols")
        done = leaves if done is None else done.unionByName(leaves)
        sons = lambda n, leaf: F.when(F.col(leaf), F.array(F.col(n))).otherwise(F.array(F.col(n) * 2, F.col(n) * 2 + 1))
        nxt = rows.where("kind = 'split'").withColumn("same", F.col("t") == F.col("s"))
        nxt = nxt.select(F.explode(sons("t", "tl")).alias("t"), "s", "sl", "same").select("t", F.explode(sons("s", "sl")).alias("s"), "same")
        # a son without points has no cluster row and drops out of the joins; of a pair of one cluster with itself, the two
        # mixed pairs of sons are one
        frontier = (nxt.where(~F.col("same") | (F.col("t") >= F.col("s"))) if symmetric else nxt).select("t", "s")
        if rows.where("kind = 'split'").isEmpty():
            return done
    raise RuntimeError("the block tree is deeper than max_level")


def kind_sql(eta: float) -> str:
    gap = "greatest(" + ", ".join(f"a.lo{x} - b.hi{x}, b.lo{x} - a.hi{x}" for x in "xyz") + ", 0.0)"
    return f"CASE WHEN greatest(a.diam_max, b.diam_max) <= {eta} * {gap} THEN 'far' WHEN a.is_leaf AND b.is_leaf THEN 'near' ELSE 'split' END"


def census(blocks: DataFrame) -> DataFrame:
    """Blocks and entries by level and kind, with subtotals."""
    return blocks.cube("level", "kind").agg(F.count("*").alias("blocks"), F.sum(F.col("rows") * F.col("cols")).alias("entries"), F.grouping_id().alias("gid"))


def coverage(blocks: DataFrame, leaves: DataFrame, symmetric: bool = False) -> DataFrame:
    """Entries covered against N^2, and the number of blocks and of distinct ones. symmetric: (t, s) covers (s, t) too."""
    n = leaves.agg(F.sum("cnt").alias("n"))
    both = F.when(F.col("t") != F.col("s"), 2).otherwise(1) if symmetric else F.lit(1)
    ends = (F.least("t", "s"), F.greatest("t", "s")) if symmetric else (F.col("t"), F.col("s"))
    return blocks.agg(F.sum(F.col("rows") * F.col("cols") * both).alias("covered"), F.count("*").alias("blocks"), F.countDistinct(*ends).alias("distinct_blocks")).crossJoin(n).select("covered", (F.col("n") * F.col("n")).alias("entries"), "blocks", "distinct_blocks")
