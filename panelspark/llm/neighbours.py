"""Nearest neighbours with vantage-point trees, one for each shard of the vectors.

Each shard groups equal vectors, picks a vantage point, splits the others at the median distance to it, and so on
down to small leaves. A block of queries descends at once. First each goes down its near sides to one leaf, whose
distances bound what it can still need; then the tree is walked once, and a node is met by all queries together for
which the triangle inequality, relaxed by `factor` on the far side, still allows a better neighbour. With factor 1 no
possible neighbour is left out; a smaller factor prunes more, and `tuned_factor` finds the smallest one of a grid that
reaches a recall on a bounded sample. How much is pruned depends on the vectors: where all distances are nearly alike
(many dimensions without structure), exact search looks at nearly all of a shard. The k best of all shards are merged
and the distances are those of the original vectors in double precision.

Vectors that are null, zero, or hold null or non-finite components take no part. Equal distances go to the smaller
id. Repeated vec_ids with different vectors are rows of their own; exactly repeated rows count once. Vectors of
another length than a query's are not compared with it. Empty tables give no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


SCHEMA = "query_id long, vec_id long, score double"
LEAF = 48
SPARE = 8
# Distances from products of vectors are off by some 1e-8 of the vectors' lengths where they are small.
OFF = 1e-7


class VantageTree:
    """A tree over distinct vectors; `ids[i]` are the sorted ids of the rows that hold vector i."""

    def __init__(self, vectors: np.ndarray, ids: list[np.ndarray], leaf: int = LEAF):
        self.x, self.ids, self.leaf, self.computed = vectors, ids, leaf, 0
        self.norm = np.einsum("ij,ij->i", vectors, vectors)
        self.nodes: list[tuple] = []
        self.root = self._build(np.arange(len(vectors))) if len(vectors) else -1

    def _distance(self, q: np.ndarray, rows: np.ndarray, square: np.ndarray | None = None) -> np.ndarray:
        square = np.einsum("ij,ij->i", q, q) if square is None else square
        d = square[:, None] + self.norm[rows][None] - 2.0 * (q @ self.x[rows].T)
        return np.sqrt(np.maximum(d, 0.0))

    def _build(self, rows: np.ndarray) -> int:
        at = len(self.nodes)
        self.nodes.append(())
        if len(rows) <= self.leaf:
            self.nodes[at] = (rows,)
            return at
        # the vantage point: of a few candidates, the one whose distances spread most
        tries = rows[:: max(1, len(rows) // 5)][:5]
        probe = rows[:: max(1, len(rows) // 64)]
        point = tries[int(np.argmax(self._distance(self.x[tries], probe).std(1)))]
        rest = rows[rows != point]
        d = self._distance(self.x[point][None], rest)[0]
        mid = np.argsort(d, kind="stable")
        half = len(rest) // 2
        inner, outer = mid[:half], mid[half:]
        edges = (d[inner].min(), d[inner].max(), d[outer].min(), d[outer].max())
        self.nodes[at] = (np.array([point]), self._build(rest[inner]), self._build(rest[outer]), edges)
        return at

    def search(self, queries: np.ndarray, own: np.ndarray, k: int, factor: float):
        """Distances and row indices of distinct vectors: k and some to spare, so that near ties are seen."""
        best_d = np.full((len(queries), k + SPARE), np.inf)
        best_i = np.full((len(queries), k + SPARE), -1)
        if self.root >= 0 and len(queries):
            square = np.einsum("ij,ij->i", queries, queries)
            bound = self._near_leaf(queries, square, k + SPARE)
            self._visit(self.root, queries, square, np.arange(len(queries)), best_d, best_i, bound, factor)
        return best_d, best_i

    def _near_leaf(self, q, square, width):
        """For each query, the largest of the `width` least distances it meets on the way down its near sides."""
        met = np.full((len(q), width), np.inf)
        todo = [(self.root, np.arange(len(q)))]
        while todo:
            at, active = todo.pop()
            node = self.nodes[at]
            d = self._distance(q[active], node[0], square[active])
            self.computed += d.size
            met[active] = np.partition(np.concatenate([met[active], d], 1), width - 1, axis=1)[:, :width]
            if len(node) > 1:
                _, inner, outer, (_, hi1, lo2, _) = node
                near_inner = d[:, 0] < (hi1 + lo2) / 2
                todo += [(child, active[side]) for child, side in ((inner, near_inner), (outer, ~near_inner)) if side.any()]
        return met.max(1)

    def _offer(self, q, square, active, rows, best_d, best_i, bound):
        d = self._distance(q[active], rows, square[active])
        self.computed += d.size
        limit = bound[active] + OFF * (np.sqrt(square[active]) + bound[active])
        hit = np.flatnonzero(d.min(1) <= limit)
        if len(hit):
            at, width = active[hit], best_d.shape[1]
            all_d = np.concatenate([best_d[at], d[hit]], 1)
            all_i = np.concatenate([best_i[at], np.broadcast_to(rows, (len(hit), len(rows)))], 1)
            keep = np.argpartition(all_d, width - 1, axis=1)[:, :width]
            best_d[at] = np.take_along_axis(all_d, keep, 1)
            best_i[at] = np.take_along_axis(all_i, keep, 1)
            bound[at] = np.minimum(bound[at], best_d[at].max(1))
        return d

    def _visit(self, at, q, square, active, best_d, best_i, bound, factor):
        node = self.nodes[at]
        d = self._offer(q, square, active, node[0], best_d, best_i, bound)
        if len(node) == 1:
            return
        d = d[:, 0]
        _, inner, outer, (lo1, hi1, lo2, hi2) = node
        near_inner = d < (hi1 + lo2) / 2
        for near, child, lo, hi in ((near_inner, inner, lo1, hi1), (~near_inner, outer, lo2, hi2)):
            need = bound[active]
            off = OFF * (np.sqrt(square[active]) + d + need)
            reach = np.where(near, need, need * factor) + off
            open_ = (d + reach >= lo) & (d - reach <= hi)
            if open_.any():
                self._visit(child, q, square, active[open_], best_d, best_i, bound, factor)


def matrices(rows: pa.Table) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """The ids and the vectors of the rows, by the length of the vectors."""
    ids, lists = rows.column("vec_id").combine_chunks(), rows.column("embedding").combine_chunks()
    lengths = np.asarray(pc.list_value_length(lists))
    out = {}
    for width in np.unique(lengths).tolist():
        at = pa.array(np.flatnonzero(lengths == width))
        flat = np.asarray(pc.list_flatten(lists.take(at)), np.float64)
        out[width] = np.asarray(ids.take(at), np.int64), flat.reshape(len(at), width) + 0.0  # no -0.0: equal vectors have equal bytes
    return out


def distinct_vectors(ids: np.ndarray, x: np.ndarray, most: int) -> tuple[np.ndarray, list[np.ndarray]]:
    """The distinct vectors, and of each the `most` smallest ids of the rows that hold it."""
    _, first, member = np.unique(np.ascontiguousarray(x).view(f"V{8 * x.shape[1]}").ravel(), return_index=True, return_inverse=True)
    order = np.lexsort((ids, member))
    ids, member = ids[order], member[order]
    new = np.ones(len(ids), bool)
    new[1:] = (np.diff(member) != 0) | (np.diff(ids) != 0)
    ids, member = ids[new], member[new]
    starts = np.append(np.flatnonzero(np.diff(member, prepend=-1)), len(ids))
    return x[first], [ids[a : min(b, a + most)] for a, b in zip(starts[:-1], starts[1:], strict=True)]


def shard_search(key, rows: pa.Table, queries: pa.Table, k: int, factor: float) -> pa.Table:
    """The k best of one shard for each query of one block."""
    if not rows.num_rows or not queries.num_rows:
        return pa.table({"query_id": pa.array([], pa.int64()), "vec_id": pa.array([], pa.int64()), "score": pa.array([], pa.float64())})
    out_q, out_v, out_d = [], [], []
    asked = matrices(queries)
    for width, (ids, x) in matrices(rows).items():
        if width not in asked:
            continue
        own, q = asked[width]
        # a query needs at most k of the rows that hold one vector: those with the smallest ids, its own left out
        distinct, groups = distinct_vectors(ids, x, k + 1)
        tree = VantageTree(distinct, groups)
        _, best_i = tree.search(q, own, k, factor)
        for a in range(len(q)):
            near = best_i[a][best_i[a] >= 0]
            exact = np.sqrt(((distinct[near] - q[a]) ** 2).sum(1))
            cand = sorted((e, i) for e, n in zip(exact, near, strict=True) for i in groups[n] if i != own[a])[:k]
            if len(near) == k + SPARE and cand and cand[-1][0] >= exact.max() - 10 * OFF * (np.sqrt(q[a] @ q[a]) + exact.max()):
                # more vectors tie with the last place than were kept: this query looks at all that are as near
                exact = np.sqrt(((distinct - q[a]) ** 2).sum(1))
                near = np.flatnonzero(exact <= cand[-1][0])
                cand = sorted((e, i) for e, n in zip(exact[near], near, strict=True) for i in groups[n] if i != own[a])[:k]
            for e, i in cand:
                out_q.append(own[a])
                out_v.append(i)
                out_d.append(e)
    return pa.table({"query_id": pa.array(out_q, pa.int64()), "vec_id": pa.array(out_v, pa.int64()), "score": pa.array(out_d, pa.float64())})


def recall_and_work(x: np.ndarray, queries: np.ndarray, k: int, factor: float) -> tuple[float, float]:
    """Of one shard: the share of the true k nearest (by distance) that is found, and of the distances computed."""
    x = np.unique(x, axis=0)
    tree = VantageTree(x, [np.zeros(1, np.int64)] * len(x))
    built = tree.computed
    found = np.sort(tree.search(queries, np.zeros(len(queries)), k, factor)[0], 1)[:, :k]
    true = np.sort(tree._distance(queries, np.arange(len(x))), 1)[:, :k]
    k = true.shape[1]
    return float((found[:, :k] <= true[:, -1:] + 1e-7).mean()), (tree.computed - built) / (len(queries) * len(x))


def tuned_factor(vectors: DataFrame, k: int = 10, recall: float = 0.95, sample_rows: int = 20_000, queries: int = 200, grid: tuple = (0.1, 0.15, 0.2, 0.25, 0.3, 0.4, 0.5, 0.7)) -> float:
    """The smallest factor of the grid with that recall against brute force on at most sample_rows vectors (those of the
    smallest hashes, on the driver), else 1."""
    rows = usable(vectors).orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample_rows).select("embedding").toArrow().column(0).to_pylist()
    width = max(map(len, rows), default=0)
    x = np.array([v for v in rows if len(v) == width], float)
    for factor in grid if len(x) else ():
        if recall_and_work(x, x[:: max(1, len(x) // queries)], k, factor)[0] >= recall:
            return factor
    return 1.0


def usable(vectors: DataFrame) -> DataFrame:
    """The rows whose vectors take part, as doubles; repeated rows once."""
    rows = vectors.select("vec_id", F.col("embedding").cast("array<double>").alias("embedding")).where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull())
    sound = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return rows.where(sound & F.exists("embedding", lambda x: x != 0))


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 10, factor: float = 1.0, shard_rows: int = 20_000, block_rows: int = 20_000) -> DataFrame:
    """query_id, rank, vec_id and score: the k nearest rows of `vectors` to each row of `queries`, its own id left out.

    Shards hold about shard_rows vectors, whatever the size of the table; each meets the query set in blocks. A shard is
    sent once for each block of queries and the queries once for each shard: 20 000 rows each balance the two.
    """
    rows, asked = usable(vectors), usable(queries).dropDuplicates()
    shards = max(1, -(-rows.count() // shard_rows))
    blocks = max(1, -(-asked.count() // block_rows))
    keyed = rows.withColumn("shard", F.pmod(F.xxhash64("vec_id"), F.lit(shards)))
    if blocks > 1:
        keyed = keyed.withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))))
    else:
        keyed = keyed.withColumn("block", F.lit(0).cast("long"))
    sent = asked.withColumn("block", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(blocks))).withColumn("shard", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(shards - 1).cast("long"))))
    found = keyed.groupBy("shard", "block").cogroup(sent.groupBy("shard", "block")).applyInArrow(_searcher(k, factor), SCHEMA)
    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _searcher(k: int, factor: float):
    from .common import ROOT

    root = ROOT

    def run(left, right):
        import sys

        if root not in sys.path:
            sys.path.insert(0, root)
        from panelspark.llm.neighbours import shard_search

        return shard_search(None, left, right, k, factor)

    return run
