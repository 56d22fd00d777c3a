"""Blocks into packages, packages into entries.

A block is a pair of clusters; its rows carry the members of both as arrays, so the pairs are made inside the task and never
shuffled. Blocks larger than a package are cut along their members. Size-bounded lists of blocks (prefix or greedy rule)
become one Arrow table each: the merged buffer that one kernel call works on. Within it the work is in two phases, regular
rule first and touching pairs again by the rule of their class, or in one pass over classified pairs.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import EngineConfig
from ..plans.scratch import settled
from . import packages
from .assembly import batch_values
from .kernels import FOUR_PI, KernelSpec, waves
from .quadrature import triangle_rule

VALUE_BYTES = 16
MEMBER = "array<struct<i: long, geo: array<double>, v: array<long>>>"
FILLED = "list long, t long, s long, i long, j long, re double, im double"


def members(rows: DataFrame, node: str = "node") -> DataFrame:
    """(node, members): rows (node, i, geo, v) of each cluster as one array, by i. Clusters are bounded: leaves by the leaf
    size, pivots by the rank."""
    return rows.groupBy(F.col(node).alias("node")).agg(F.sort_array(F.collect_list(F.struct("i", "geo", "v"))).cast(MEMBER).alias("members"))


def cut(blocks: DataFrame, limit: int) -> DataFrame:
    """blocks(t, s, m, n) cut into pieces below the limit: (t, s, r0, m, c0, n, bytes). Rows are cut first, then columns."""
    limit = max(int(limit), 2 * VALUE_BYTES)
    per = F.greatest(F.floor(F.lit((limit - 1) // VALUE_BYTES) / F.col("n")), F.lit(1)).cast("long")  # rows of a piece
    rows = blocks.withColumn("per", F.least("per0", "m") if "per0" in blocks.columns else F.least(per, "m"))
    rows = rows.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("m") - 1, F.col("per"))).alias("r0"))
    rows = rows.withColumn("wide", F.least(F.col("n"), F.greatest(F.floor(F.lit((limit - 1) // VALUE_BYTES) / F.col("per")), F.lit(1))).cast("long"))
    rows = rows.select("t", "s", "r0", F.least("per", F.col("m") - F.col("r0")).alias("m"), "n", "wide", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1, F.col("wide"))).alias("c0"))
    return rows.select("t", "s", "r0", "m", "c0", F.least("wide", F.col("n") - F.col("c0")).alias("n")).withColumn("bytes", F.col("m") * F.col("n") * VALUE_BYTES)


def lists(blocks: DataFrame, limit: int, rule: str = "prefix") -> DataFrame:
    """The pieces of blocks(t, s, m, n) with the number of their list. rule: 'prefix' at any size, 'greedy' is exact and
    sequential, for one producer a leading cluster."""
    pieces = cut(blocks, limit)
    order = ["t", "s", "r0", "c0"]
    if rule == "prefix":
        return packages.prefix(pieces, limit, order)
    one = packages.greedy(pieces.withColumn("producer", F.floor(F.col("t") / 256)), limit, order)
    return one.withColumn("list", F.col("list") + F.col("producer") * (1 << 32)).drop("producer", "piece")


def with_members(pieces: DataFrame, rows: DataFrame, cols: DataFrame) -> DataFrame:
    """(list, t, s, a, b): the members of both sides of each piece."""
    a, b = rows.select(F.col("node").alias("t"), F.col("members").alias("a")), cols.select(F.col("node").alias("s"), F.col("members").alias("b"))
    cutting = lambda c, lo, n: F.slice(c, (F.col(lo) + 1).cast("int"), F.col(n).cast("int"))
    return pieces.join(a, "t").join(b, "s").select("list", "t", "s", cutting("a", "r0", "m").alias("a"), cutting("b", "c0", "n").alias("b"))


def _side(column) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray | None]:
    """Sizes, ids, geometry and vertex ids of a column of member arrays."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    size = np.diff(np.asarray(column.offsets))
    flat = column.flatten()
    ids, geo, v = (flat.field(k) for k in range(3))
    return size, np.asarray(ids), np.asarray(geo.flatten()).reshape(len(ids), -1), None if v.null_count else np.asarray(v.flatten()).reshape(len(ids), 3)


def _aligned(va: np.ndarray, vb: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Number of common vertices of pairs, and the order of corners of both: common ones by id, the others as they were."""
    same = va[:, :, None] == vb[:, None, :]
    last = np.iinfo(np.int64).max - 3 + np.arange(3)
    ka, kb = np.where(same.any(2), va, last), np.where(same.any(1), vb, last)
    return same.any(2).sum(1), np.argsort(ka, 1, kind="stable"), np.argsort(kb, 1, kind="stable")


def integrate(ga, va, gb, vb, kernel: KernelSpec, quad, phases: str = "two") -> np.ndarray:
    """Values of pairs of panels (13 numbers and 3 vertex ids each) or of points (3 numbers each; a point with itself: 0)."""
    if ga.shape[1] == 3:
        d = ga - gb
        out = kernel.values(d)
        return np.where(np.einsum("ik,ik->i", d, d) == 0, 0.0, out)
    ca, cb, scale, normal = ga[:, :9].reshape(-1, 3, 3), gb[:, :9].reshape(-1, 3, 3), ga[:, 9] * gb[:, 9], gb[:, 10:13]
    case = np.zeros(len(ga), np.int64)
    near = np.flatnonzero((va[:, :, None] == vb[:, None, :]).any((1, 2)))
    case[near], pa_, pb_ = _aligned(va[near], vb[near])
    out = np.zeros(len(ga), complex if kernel.complex else float)
    first = np.arange(len(ga)) if phases == "two" else np.flatnonzero(case == 0)
    with np.errstate(invalid="ignore"):
        out[first] = batch_values(ca[first], cb[first], normal[first], scale[first], 0, quad.points(0), kernel)
    for c in (1, 2, 3):
        at = np.flatnonzero(case[near] == c)
        rows = near[at]
        out[rows] = batch_values(np.take_along_axis(ca[rows], pa_[at][:, :, None], 1), np.take_along_axis(cb[rows], pb_[at][:, :, None], 1), normal[rows], scale[rows], c, quad.points(c), kernel)
    return out


def run_list(table: pa.Table, kernel: KernelSpec, quad, phases: str, lower: bool) -> pa.Table:
    """The entries of one list. lower: a symmetric kernel is evaluated with the larger id first."""
    na, ia, ga, va = _side(table.column("a"))
    nb, ib, gb, vb = _side(table.column("b"))
    sa, sb = np.cumsum(na) - na, np.cumsum(nb) - nb
    pairs = na * nb
    block = np.repeat(np.arange(len(pairs)), pairs)
    k = np.arange(len(block)) - np.repeat(np.cumsum(pairs) - pairs, pairs)
    p, q = sa[block] + k // nb[block], sb[block] + k % nb[block]
    i, j = ia[p], ib[q]
    panels = va is not None
    x, y = (ga[p], gb[q])
    vx, vy = (va[p], vb[q]) if panels else (None, None)
    if lower and panels:
        turn = i < j
        x, y = np.where(turn[:, None], y, x), np.where(turn[:, None], x, y)
        vx, vy = np.where(turn[:, None], vy, vx), np.where(turn[:, None], vx, vy)
    value = integrate(x, vx, y, vy, kernel, quad, phases)
    number = np.full(len(i), table.column("list")[0].as_py())
    t, s = np.asarray(table.column("t"))[block], np.asarray(table.column("s"))[block]
    return pa.table({"list": pa.array(number, pa.int64()), "t": pa.array(t), "s": pa.array(s), "i": pa.array(i), "j": pa.array(j), "re": pa.array(np.real(value).astype(float)), "im": pa.array(np.imag(value).astype(float) if np.iscomplexobj(value) else np.zeros(len(i)))})


def fill(blocks: DataFrame, rows: DataFrame, cols: DataFrame, kernel: KernelSpec, cfg: EngineConfig, phases: str = "two", rule: str = "prefix", lower: bool = False) -> DataFrame:
    """(list, t, s, i, j, re, im) of blocks(t, s) between the members (node, members) of both sides, list by list."""
    sized = blocks.join(rows.select(F.col("node").alias("t"), F.size("members").cast("long").alias("m")), "t").join(cols.select(F.col("node").alias("s"), F.size("members").cast("long").alias("n")), "s").where("m > 0 and n > 0")
    work = with_members(lists(sized.select("t", "s", "m", "n"), cfg.limit_bytes, rule), rows, cols)
    quad = cfg.quad
    return work.groupBy("list").applyInArrow(lambda table: run_list(table, kernel, quad, phases, lower), FILLED)


def touching_blocks(blocks: DataFrame, membership: DataFrame, panels: DataFrame) -> DataFrame:
    """The blocks (t, s, ..) of leaves that hold a touching pair: those that a second phase looks at."""
    from .classify import incidence

    leaf = incidence(panels).join(membership.select(F.col("i").alias("pid"), "node"), "pid").select("vid", "node").distinct()
    near = leaf.withColumnRenamed("node", "t").join(leaf.withColumnRenamed("node", "s"), "vid").select("t", "s").distinct()
    return blocks.join(near, ["t", "s"], "left_semi")


APPLIED = "node long, i long, re double, im double"
GROUPS = 512  # of lists that share what they read of clusters, where there are so many lists


def apply(blocks: DataFrame, rows: DataFrame, cols: DataFrame, kernel: KernelSpec, cfg: EngineConfig, phases: str = "two", symmetric: bool = False) -> DataFrame:
    """(node, i, re, im): the product of the entries of blocks(t, s) with a vector, without storing an entry.

    rows and cols are (node, members, x): x holds a pair (re, im) for each member. symmetric: a block with t <> s stands for
    (s, t) too. A task gets some lists that follow each other, and each cluster of them once, however many blocks it is in."""
    sized = blocks.join(rows.select(F.col("node").alias("t"), F.size("members").cast("long").alias("m")), "t").join(cols.select(F.col("node").alias("s"), F.size("members").cast("long").alias("n")), "s").where("m > 0 and n > 0")
    pieces = settled(lists(sized.select("t", "s", "m", "n"), cfg.limit_bytes))
    count = (pieces.agg(F.max("list")).first()[0] or 0) + 1
    each, cuts = max(1, min(64, count // GROUPS)), max(1, 64 // count)
    tasks = -(-count // each) * cuts  # given, since short lists hold much work; few lists are dealt by row cluster
    work = pieces.withColumn("part", F.floor(F.col("list") / F.lit(each)).cast("long") * cuts + F.pmod("t", F.lit(cuts)))
    one = rows is cols
    held = [f.select(F.lit(k).alias("side"), "node", "members", "x") for k, f in enumerate([rows] if one else [rows, cols])]
    used = work.select("part", F.lit(0).alias("side"), F.col("t").alias("node")).union(work.select("part", F.lit(0 if one else 1), "s")).distinct()
    known = used.join(held[0] if one else held[0].unionByName(held[1]), ["side", "node"]).select(F.col("part").alias("part"), F.col("side").alias("side"), F.col("node").alias("node"), "members", "x")
    quad, parts = cfg.quad, min(tasks, 10_000)
    run = lambda a, b: apply_lists(a, b, kernel, quad, phases, symmetric)
    made = work.repartition(parts, "part").groupBy("part").cogroup(known.repartition(parts, "part").groupBy("part")).applyInArrow(run, APPLIED)
    return made.groupBy("node", "i").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))


def _vector(column) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    x = np.asarray(flat.flatten().flatten()).reshape(-1, 2)
    return x[:, 0] + 1j * x[:, 1]


def apply_lists(pieces: pa.Table, known: pa.Table, kernel: KernelSpec, quad, phases: str, symmetric: bool) -> pa.Table:
    """The product of pieces (list, t, s, r0, m, c0, n) of blocks with the vector of the clusters known (side, node, members, x)."""
    size, ids, geo, v = _side(known.column("members"))
    x, start = _vector(known.column("x")), np.cumsum(size) - size
    side, node = (np.asarray(known.column(c)) for c in ("side", "node"))
    at = {(int(k), int(n)): int(o) for k, n, o in zip(side, node, start, strict=True)}
    other = int(side.max()) if len(side) else 0
    col = {c: np.asarray(pieces.column(c)) for c in ("list", "t", "s", "r0", "m", "c0", "n")}
    order = np.lexsort((col["c0"], col["s"], col["r0"], col["t"], col["list"]))
    edges = np.flatnonzero(np.any([np.diff(col[c][order]) != 0 for c in ("list", "t", "r0")], axis=0)) + 1
    y, written = np.zeros(len(ids), complex), np.zeros(len(ids), bool)
    for rows in np.split(order, edges) if len(order) else []:  # one strip of a row cluster against all its columns in a list
        t, m = int(col["t"][rows[0]]), int(col["m"][rows[0]])
        first = at[0, t] + int(col["r0"][rows[0]])
        i = np.arange(first, first + m)
        j = np.concatenate([at[other, s] + c0 + np.arange(n) for s, c0, n in zip(*(col[c][rows].tolist() for c in ("s", "c0", "n")), strict=True)])
        both = np.repeat(col["s"][rows] != t, col["n"][rows]) if symmetric else None
        one = (geo[i], ids[i], x[i], None if v is None else v[i])
        two = (geo[j], ids[j], x[j], None if v is None else v[j])
        mine, theirs = (_apply_points if v is None else _apply_panels)(one, two, both, kernel, quad, phases)
        y[i] += mine
        written[i] = True
        if symmetric:
            y[j] += theirs
            written[j] = True
    out, y = np.flatnonzero(written), y[written]
    return pa.table({"node": pa.array(np.repeat(node, size)[out], pa.int64()), "i": pa.array(ids[out], pa.int64()), "re": pa.array(y.real.copy()), "im": pa.array(y.imag.copy())})


def _apply_points(one, two, both, kernel: KernelSpec, quad, phases: str):
    (ga, _, xa, _), (gb, _, xb, _) = one, two
    p, q = np.repeat(np.arange(len(ga)), len(gb)), np.tile(np.arange(len(gb)), len(ga))
    value = integrate(ga[p], None, gb[q], None, kernel, quad, phases).reshape(len(ga), len(gb))
    return value @ xb, None if both is None else np.where(both, xa @ value, 0.0)


def _apply_panels(one, two, both, kernel: KernelSpec, quad, phases: str):
    """The regular rule for all pairs without a common vertex, from the points of both sides; touching pairs by the rule of their
    class. Each pair is evaluated once, in either number of phases."""
    (ga, ia, xa, va), (gb, ib, xb, vb) = one, two
    p, q = touching(va, vb)
    mine, theirs = regular_product(ga, gb, xa if both is not None else None, xb, kernel, quad.points(0), (p, q))
    if len(p):
        x, y, vx, vy = ga[p], gb[q], va[p], vb[q]
        if both is not None:  # a symmetric kernel is evaluated with the larger id first
            turn = (ia[p] < ib[q])[:, None]
            x, y = np.where(turn, y, x), np.where(turn, x, y)
            vx, vy = np.where(turn, vy, vx), np.where(turn, vx, vy)
        value = integrate(x, vx, y, vy, kernel, quad, "one")
        np.add.at(mine, p, value * xb[q])
        if both is not None:
            np.add.at(theirs, q, value * xa[p])
    return mine, None if both is None else np.where(both, theirs, 0.0)


def touching(va: np.ndarray, vb: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (row of va, row of vb) with a common vertex."""
    q = np.flatnonzero(np.isin(vb, va).any(1))
    p = np.flatnonzero(np.isin(va, vb[q]).any(1))
    a, b = np.nonzero((va[p][:, None, :, None] == vb[q][None, :, None, :]).any((2, 3)))
    return p[a], q[b]


def regular_product(ga, gb, xa, xb, kernel: KernelSpec, n: int, without, most: int = 1 << 14):
    """(G xb, xa G) for the entries G of all panels ga against all gb by the rule without common vertices, 0 for the pairs `without`.

    Distances of all quadrature points come from one matrix product over coordinates around the middle of ga, strip by strip of
    about `most` points; weights go to the vectors, so an entry is never formed. xa None: only the first."""
    middle = ga[:, :9].reshape(-1, 3).mean(0)
    rule = triangle_rule(n)
    size = len(rule)

    def points(g):
        a, b, c = (g[:, k : k + 3] - middle for k in (0, 3, 6))
        z = a[:, None] + rule[None, :, 0, None] * (b - a)[:, None] + rule[None, :, 1, None] * (c - b)[:, None]
        return z.reshape(-1, 3), (g[:, 9:10] * rule[None, :, 2]).ravel(), a

    (p, wp, _), (q, wq, corner) = points(ga), points(gb)
    wp /= FOUR_PI
    left = np.concatenate([-2 * p, (p * p).sum(1)[:, None], np.ones((len(p), 1))], 1)
    right = np.concatenate([q, np.ones((len(q), 1)), (q * q).sum(1)[:, None]], 1).T.copy()
    if kernel.layer == "dlp":  # (x - y) n is the same for all y of a panel
        along = np.concatenate([p, np.ones((len(p), 1))], 1)
        turned = np.repeat(np.concatenate([gb[:, 10:13], -np.einsum("ik,ik->i", corner, gb[:, 10:13])[:, None]], 1), size, 0).T.copy()

    def split(x, w):
        x = np.repeat(x, size) * w
        return [x.real.copy()] + ([x.imag.copy()] if x.imag.any() else [])

    into, back = split(xb, wq), [] if xa is None else split(xa, wp)
    kind = complex if kernel.complex or len(into) + len(back) > 2 - (xa is None) else float
    mine, theirs = np.zeros(len(p), kind), np.zeros(len(q), kind)
    high = max(1, min(len(ga), 144 // size))
    wide = max(1, most // (high * size * size))
    rooms = [np.empty(high * wide * size * size) for _ in range(3 if kernel.complex else 2)]
    for r in range(0, len(ga), high):
        rows = slice(r * size, min(r + high, len(ga)) * size)
        for c in range(0, len(gb), wide):
            cols = slice(c * size, min(c + wide, len(gb)) * size)
            shape = (rows.stop - rows.start, cols.stop - cols.start)
            value, r2, *spare = (z[: shape[0] * shape[1]].reshape(shape) for z in rooms)
            np.matmul(left[rows], right[:, cols], out=r2)
            skip = None
            if len(without[0]):
                at = np.flatnonzero((without[0] >= r) & (without[0] < r + high) & (without[1] >= c) & (without[1] < c + wide))
                skip = (without[0][at] - r, slice(None), without[1][at] - c, slice(None)) if len(at) else None
            if skip:  # any distance of this strip, lest the others are taken for wider spread
                r2.reshape(shape[0] // size, size, shape[1] // size, size)[skip] = r2.max() if r2.max() > 0 else 1.0
            dist = np.sqrt(r2, out=spare[0] if spare else value)
            if kernel.layer == "dlp":
                r2 *= dist
                np.matmul(along[rows], turned[:, cols], out=value)
                value /= r2
            else:
                np.reciprocal(dist, out=value)
            if skip:
                value.reshape(shape[0] // size, size, shape[1] // size, size)[skip] = 0.0
            for z, factor in waves(kernel, value, dist, r2) if kernel.complex else [(value, 1.0)]:
                for unit, x in zip((factor, factor * 1j), into, strict=False):
                    y = z @ x[cols]
                    mine[rows] += y if kind is float else y * unit
                for unit, x in zip((factor, factor * 1j), back, strict=False):
                    y = x[rows] @ z
                    theirs[cols] += y if kind is float else y * unit
    fold = lambda y, w: (y * w).reshape(-1, size).sum(1)
    return fold(mine, wp) + 0j, None if xa is None else fold(theirs, wq) + 0j
