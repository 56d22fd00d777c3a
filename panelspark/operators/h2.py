"""Compression with nested bases: pivots by cluster, couplings between pivots, a near field, and the product with a vector.

The tree is cut into bands of `band` levels. The part of a band below one cluster is a task of bounded size: its leaves have at
most the leaf size of members, its inner clusters the pivots of their sons. So bases, and both sweeps of a product, take one
step for each band, not one for each level.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import EngineConfig
from ..plans.scratch import discard, settled
from . import cross, fill, green, packages
from .kernels import KernelSpec

BASIS = "top long, node long, level int, son long, i long, place int, coef array<double>, geo array<double>, v array<long>"
MEMBER_BYTES = 160  # of a panel with its geometry, vertices and id
BOX = [f"{m}{a}" for m in ("lo", "hi") for a in "xyz"]


@dataclass
class H2:
    """basis rows (top, node, level, son, i, place, coef): place is the pivot number or -1; far and near entries by block.

    symmetric: a block (t, s) with t <> s stands for (s, t) as well. seconds: of the steps of the set-up."""

    row_basis: DataFrame
    col_basis: DataFrame
    coupling: DataFrame
    nearfield: DataFrame
    blocks: DataFrame
    depth: int
    band: int = 6
    top: int = 0
    symmetric: bool = False
    seconds: dict[str, float] = field(default_factory=dict)


def geometry_rows(panels: DataFrame) -> DataFrame:
    return panels.select(F.col("pid").alias("i"), F.array(*green.GEOMETRY).alias("geo"), F.array("v0", "v1", "v2").alias("v"))


def point_rows(points: DataFrame) -> DataFrame:
    return points.select("i", F.array("x", "y", "z").alias("geo"), F.lit(None).cast("array<long>").alias("v"))


def pivots(geo: np.ndarray, box: np.ndarray, kernel: KernelSpec, cfg: EngineConfig, side: str) -> tuple[list[int], np.ndarray]:
    """Pivot members of one cluster and the coefficients that interpolate all members from them."""
    surface = green.surface(box[:3], box[3:], cfg.green_q, cfg.box_scale, cfg.norm)
    if surface[3] == 0:  # one point, or all alike: the first stands for all
        return [0], np.ones((len(geo), 1))
    a = green.row_factor(geo, surface, kernel, side)
    if np.iscomplexobj(a):  # real interpolation of both parts
        a = np.concatenate([a.real, a.imag], 1)
    rows, cols = cross.pivots(a, cfg.aca_eps, cfg.kmax, cfg.pivot)
    return rows, cross.interpolation(a, rows, cols)


def _edge(level: int, band: int, top: int) -> int:
    """The upper level of the band of a level; bands begin at level `top`."""
    return level - (level - top) % band


def _tasks(edge: int) -> int:
    """Tasks for the groups of a band, given, since few bytes hold much work: some for each cluster of its upper level."""
    return min(64, 4 << min(edge, 10))


def _top(band: int, top: int):
    """The cluster at the upper edge of the band of a cluster (node, level)."""
    return F.floor(F.col("node") / F.pow(F.lit(2.0), (F.col("level") - top) % band)).cast("long")


def top_level(blocks: DataFrame) -> int:
    """The smallest level of a cluster with a far block: no cluster above it needs a basis."""
    far = blocks.where("kind = 'far'")
    lowest = far.agg(F.min(F.least("t", "s"))).first()[0]
    return int(lowest).bit_length() - 1 if lowest else 0


def _lists(column) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return np.asarray(flat.flatten()).reshape(len(flat), -1) if len(flat) else np.zeros((0, 0))


def _band_basis(members: pa.Table, frame: pa.Table, kernel: KernelSpec, cfg: EngineConfig, side: str, flat: bool, above: int = 0) -> pa.Table:
    """Basis rows of all clusters below one top, lowest level first."""
    schema = pa.schema([("top", pa.int64()), ("node", pa.int64()), ("level", pa.int32()), ("son", pa.int64()), ("i", pa.int64()), ("place", pa.int32()), ("coef", pa.list_(pa.float64())), ("geo", pa.list_(pa.float64())), ("v", pa.list_(pa.int64()))])
    if not members.num_rows:
        return schema.empty_table()
    boxes = dict(zip(frame.column("node").to_pylist(), np.stack([np.asarray(frame.column(c)) for c in BOX], 1), strict=True))
    node, level, son, ids = (np.asarray(members.column(c)) for c in ("node", "level", "son", "i"))
    geo = _lists(members.column("geo"))
    v = _lists(members.column("v")).astype(np.int64) if members.column("v").null_count == 0 else None
    top = members.column("top")[0].as_py()
    edge = int(level.min()) if flat else _edge(int(level.min()), cfg.band, above)
    at: dict[tuple[int, int], list] = {}
    for r in range(len(node)):
        at.setdefault((int(level[r]), int(node[r])), []).append((int(son[r]), r))
    out: list[tuple] = []
    for k in range(int(level.max()), edge - 1, -1):
        for n in sorted(x for lv, x in at if lv == k):
            rows = sorted(at[k, n], key=lambda m: ids[m[1]])
            pick = np.array([r for _, r in rows])
            chosen, coef = pivots(geo[pick], boxes[n], kernel, cfg, side)
            place = np.full(len(pick), -1)
            place[chosen] = np.arange(len(chosen))
            out += [(n, k, s, r, int(p), c) for (s, r), p, c in zip(rows, place, coef, strict=True)]
            if k > edge and not flat:
                at.setdefault((k - 1, n // 2), []).extend((n, pick[c]) for c in chosen)
    pick = np.array([r for _, _, _, r, _, _ in out])
    sizes = np.cumsum([0] + [len(c) for *_, c in out]).astype(np.int32)
    lists = lambda x, kind: pa.FixedSizeListArray.from_arrays(pa.array(x[pick].ravel(), kind), x.shape[1]).cast(pa.list_(kind))
    return pa.Table.from_arrays(
        [pa.array(np.full(len(out), top), pa.int64()), pa.array([x[0] for x in out], pa.int64()), pa.array([x[1] for x in out], pa.int32()), pa.array([x[2] for x in out], pa.int64()), pa.array(ids[pick], pa.int64()), pa.array([x[4] for x in out], pa.int32()),
         pa.ListArray.from_arrays(pa.array(sizes), pa.array(np.concatenate([c for *_, c in out]))), lists(geo, pa.float64()), pa.nulls(len(out), pa.list_(pa.int64())) if v is None else lists(v, pa.int64())], schema=schema)


def nested_basis(membership: DataFrame, clusters: DataFrame, geometry: DataFrame, kernel: KernelSpec, cfg: EngineConfig, side: str = "row", above: int = 0) -> DataFrame:
    """Basis rows of all clusters of level `above` and below, band by band from below: a leaf works on its members, an inner
    cluster on the pivots of its sons."""
    band = cfg.band
    clusters = clusters.where(F.col("level") >= above)
    frame = clusters.select(_top(band, above).alias("top"), "node", "level", *BOX)
    depth = max(above, clusters.agg(F.max("level")).first()[0] or 0)
    leaves = membership.select("i", "node", "level").join(geometry, "i").withColumn("son", F.lit(0).cast("long"))
    done, risen = None, None
    for edge in range(_edge(depth, band, above), above - 1, -band):
        inside = (F.col("level") >= edge) & (F.col("level") < edge + band)
        rows = leaves.where(inside).select(_top(band, above).alias("top"), "node", "level", "son", "i", "geo", "v")
        if risen is not None:
            rows = rows.unionByName(risen)
        tasks = _tasks(edge)
        made = settled(rows.repartition(tasks, "top").groupBy("top").cogroup(_fresh(frame.where(inside)).repartition(tasks, "top").groupBy("top")).applyInArrow(lambda a, b: _band_basis(a, b, kernel, cfg, side, False, above), BASIS))
        done = made if done is None else done.unionByName(made)
        up = made.where((F.col("place") >= 0) & (F.col("level") == edge))
        risen = up.select(F.floor(F.col("node") / 2).cast("long").alias("node"), (F.col("level") - 1).cast("int").alias("level"), F.col("node").alias("son"), "i", "geo", "v").withColumn("top", _top(band, above))
    return done


def flat_basis(membership: DataFrame, clusters: DataFrame, geometry: DataFrame, kernel: KernelSpec, cfg: EngineConfig, side: str = "row", blocks: DataFrame | None = None) -> DataFrame:
    """Basis rows of clusters over all their members; the storage that nesting avoids. blocks: only the clusters of its far
    blocks need one, which leaves out the root and its like."""
    from .clustering import ancestors

    rows = ancestors(membership).withColumn("level", F.col("level").cast("int"))
    if blocks is not None:
        far = blocks.where("kind = 'far'")
        rows = rows.join(far.select(F.col("t").alias("node")).union(far.select("s")).distinct(), "node", "left_semi")
    rows = rows.join(geometry, "i").select(F.col("node").alias("top"), "node", "level", F.lit(0).cast("long").alias("son"), "i", "geo", "v")
    frame = clusters.select(F.col("node").alias("top"), "node", "level", *BOX)
    return rows.groupBy("top").cogroup(frame.groupBy("top")).applyInArrow(lambda a, b: _band_basis(a, b, kernel, cfg, side, True), BASIS)


def pivot_members(basis: DataFrame) -> DataFrame:
    return fill.members(basis.where("place >= 0").select("node", "i", "geo", "v"))


def build(membership: DataFrame, clusters: DataFrame, blocks: DataFrame, geometry: DataFrame, kernel: KernelSpec, cfg: EngineConfig, phases: str = "two", rule: str = "prefix", symmetric: bool | None = None) -> H2:
    """The four tables. Trees, bases and blocks adapt to the data; the entries are packages of one uniform kernel call.

    symmetric: blocks hold one of (t, s) and (s, t), and the layer is the single one."""
    symmetric = False if symmetric is None else symmetric
    if symmetric and kernel.layer != "slp":
        raise ValueError("only the single layer is symmetric")
    began, seconds = time.perf_counter(), {}

    def lap(name):
        nonlocal began
        seconds[name], began = time.perf_counter() - began, time.perf_counter()

    above = top_level(blocks)
    row_basis = nested_basis(membership, clusters, geometry, kernel, cfg, "row", above)
    col_basis = nested_basis(membership, clusters, geometry, kernel, cfg, "col", above) if kernel.layer == "dlp" else row_basis
    depth = clusters.agg(F.max("level")).first()[0] or 0
    lap("interpolation")
    far, near = blocks.where("kind = 'far'").select("t", "s"), blocks.where("kind = 'near'").select("t", "s")
    coupling = settled(fill.fill(far, pivot_members(row_basis), pivot_members(col_basis), kernel, cfg, "one", rule, symmetric))
    lap("coupling")
    leaf = fill.members(membership.select("node", "i").join(geometry, "i"))
    nearfield = settled(fill.fill(near, leaf, leaf, kernel, cfg, phases, rule, symmetric))
    lap("near field")
    return H2(row_basis, col_basis, coupling, nearfield, blocks, max(above, depth), cfg.band, above, symmetric, seconds)


# ---- the product: vectors are rows (i, re, im)


def _table(node, i, re, im, top=None) -> pa.Table:
    out = {"node": pa.array(node, pa.int64()), "i": pa.array(i, pa.int64()), "re": pa.array(re, pa.float64()), "im": pa.array(im, pa.float64())}
    return pa.table(out)


VECTOR = "node long, i long, re double, im double"


def _coefficients(basis: pa.Table):
    """By (level, node): the rows of each cluster, its sons, ids, coefficient matrix and pivots."""
    node, level, son, ids, place = (np.asarray(basis.column(c)) for c in ("node", "level", "son", "i", "place"))
    column = basis.column("coef").combine_chunks()
    off, flat = np.asarray(column.offsets), np.asarray(column.values)
    order = np.lexsort((ids, node, level))
    edges = np.concatenate([[0], np.flatnonzero(np.diff(node[order])) + 1, [len(order)]]) if len(order) else [0]
    out = []
    for x, y in zip(edges[:-1], edges[1:], strict=True):
        rows = order[x:y]
        c = np.stack([flat[off[r] : off[r + 1]] for r in rows])
        pivot = np.empty(c.shape[1], np.int64)
        at = place[rows] >= 0
        pivot[place[rows][at]] = ids[rows][at]
        out.append((int(level[rows[0]]), int(node[rows[0]]), son[rows], ids[rows], c, pivot))
    return out


def _collect_up(basis: pa.Table, given: pa.Table) -> pa.Table:
    """Forward sweep of one band: given values of members (node 0) and of pivots of sons of the band below."""
    value = {(n, i): complex(re, im) for n, i, re, im in zip(*(given.column(c).to_pylist() for c in ("node", "i", "re", "im")), strict=True)}
    out = []
    for _, n, son, ids, c, pivot in sorted(_coefficients(basis), key=lambda r: -r[0]):
        x = c.T @ np.array([value.get((int(s), int(i)), 0.0) for s, i in zip(son, ids, strict=True)])
        for p, y in zip(pivot.tolist(), x.tolist(), strict=True):
            value[n, p] = y
            out.append((n, p, y.real, y.imag))
    return _table(*zip(*out, strict=True)) if out else _table([], [], [], [])


def _hand_down(basis: pa.Table, given: pa.Table) -> pa.Table:
    """Backward sweep of one band: given values of pivots of its clusters; (node 0, i) are members' values, others go to
    the band below."""
    value: dict[tuple[int, int], complex] = {}
    for n, i, re, im in zip(*(given.column(c).to_pylist() for c in ("node", "i", "re", "im")), strict=True):
        value[n, i] = value.get((n, i), 0.0) + complex(re, im)
    made = sorted(_coefficients(basis), key=lambda r: r[0])
    inside = {n for _, n, *_ in made}
    out = []
    for _, n, son, ids, c, pivot in made:
        y = c @ np.array([value.get((n, int(p)), 0.0) for p in pivot])
        for s, i, z in zip(son.tolist(), ids.tolist(), y.tolist(), strict=True):
            if s in inside:
                value[s, i] = value.get((s, i), 0.0) + z
            else:
                out.append((s, i, complex(z).real, complex(z).imag))
    return _table(*zip(*out, strict=True)) if out else _table([], [], [], [])


def _edges(h: H2) -> range:
    return range(_edge(h.depth, h.band, h.top), h.top - 1, -h.band)


def _fresh(df: DataFrame) -> DataFrame:
    """The same columns under new identities: a cogroup of frames of one origin would take them for each other."""
    return df.select(*[F.col(c).alias(c) for c in df.columns])


def _of_band(basis: DataFrame, edge: int, band: int) -> DataFrame:
    return basis.where((F.col("level") >= edge) & (F.col("level") < edge + band)).select("top", "node", "level", "son", "i", "place", "coef")


def forward(h: H2, x: DataFrame, steps: list | None = None) -> DataFrame:
    """(node, i, re, im): the coefficients of all clusters, from the leaves up. x(i, re, im). steps takes what was written."""
    up, below = None, None
    for edge in _edges(h):
        basis = _of_band(h.col_basis, edge, h.band)
        given = basis.where("son = 0").select("top", "i").join(x, "i").select("top", F.lit(0).cast("long").alias("node"), "i", "re", "im")
        if below is not None:  # values of the clusters just below the band go to the band of their parents
            parents = below.where((F.col("node") >= 2 ** (edge + h.band)) & (F.col("node") < 2 ** (edge + h.band + 1)))
            given = given.unionByName(parents.select(F.floor(F.col("node") / 2**h.band).cast("long").alias("top"), "node", "i", "re", "im"))
        below = settled(basis.groupBy("top").cogroup(_fresh(given).groupBy("top")).applyInArrow(_collect_up, VECTOR))
        up = below if up is None else up.unionByName(below)
        if steps is not None:
            steps.append(below)
    return up


def couple(h: H2, xhat: DataFrame) -> DataFrame:
    """(node, i, re, im): far blocks between pivots, summed by row cluster."""
    c = h.coupling.select("t", "s", "i", "j", F.col("re").alias("kr"), F.col("im").alias("ki"))
    if h.symmetric:
        c = c.unionByName(c.where("t <> s").select(F.col("s").alias("t"), F.col("t").alias("s"), F.col("j").alias("i"), F.col("i").alias("j"), "kr", "ki"))
    rows = c.join(xhat.select(F.col("node").alias("s"), F.col("i").alias("j"), "re", "im"), ["s", "j"])
    return rows.groupBy(F.col("t").alias("node"), "i").agg(*_product())


def _product():
    return (F.sum(F.col("kr") * F.col("re") - F.col("ki") * F.col("im")).alias("re"), F.sum(F.col("kr") * F.col("im") + F.col("ki") * F.col("re")).alias("im"))


def backward(h: H2, yhat: DataFrame, steps: list | None = None) -> DataFrame:
    """(i, re, im): coefficients of the row clusters carried down to the members."""
    yhat = settled(yhat)
    leaf, down = None, None
    for edge in reversed(_edges(h)):
        inside = (F.col("node") >= 2**edge) & (F.col("node") < 2 ** (edge + h.band))
        level = F.floor(F.log2(F.col("node").cast("double"))).cast("int")
        given = yhat.where(inside)
        if down is not None:
            given = given.unionByName(down.where("node > 0"))
        given = given.withColumn("top", F.floor(F.col("node") / F.pow(F.lit(2.0), level - F.lit(edge))).cast("long"))
        basis = _of_band(h.row_basis, edge, h.band)
        down = settled(basis.groupBy("top").cogroup(_fresh(given).groupBy("top")).applyInArrow(_hand_down, VECTOR))
        ends = down.where("node = 0").select("i", "re", "im")
        leaf = ends if leaf is None else leaf.unionByName(ends)
        if steps is not None:
            steps += [down, *([yhat] if edge == h.top else [])]
    return leaf


def near(h: H2, x: DataFrame) -> DataFrame:
    n = h.nearfield.select("t", "s", "i", "j", F.col("re").alias("kr"), F.col("im").alias("ki"))
    if h.symmetric:
        n = n.unionByName(n.where("t <> s").select(F.col("s").alias("t"), F.col("t").alias("s"), F.col("j").alias("i"), F.col("i").alias("j"), "kr", "ki"))
    return n.join(x.withColumnRenamed("i", "j"), "j").groupBy("i").agg(*_product())


def complex_matvec(h: H2, x: DataFrame) -> DataFrame:
    """(i, re, im) = H x: two sweeps over the bands, one coupling join and the near field. x(i, re, im)."""
    steps: list[DataFrame] = []
    total = backward(h, couple(h, forward(h, x, steps)), steps).unionByName(near(h, x))
    out = settled(total.groupBy("i").agg(F.sum("re").alias("re"), F.sum("im").alias("im")))
    discard(*steps)
    return out


def with_vector(rows: DataFrame, x: DataFrame) -> DataFrame:
    """(node, members, x): rows(node, i, geo, v) with the values of x(node, i, re, im) beside the members, 0 where there is none."""
    held = rows.join(x, ["node", "i"], "left").select("node", F.struct("i", "geo", "v").alias("m"), F.array(F.coalesce("re", F.lit(0.0)), F.coalesce("im", F.lit(0.0))).alias("x"))
    both = held.groupBy("node").agg(F.sort_array(F.collect_list(F.struct("m", "x"))).alias("b"))
    return settled(both.select("node", F.col("b.m").cast(fill.MEMBER).alias("members"), F.col("b.x").alias("x")))


def product(membership: DataFrame, clusters: DataFrame, blocks: DataFrame, geometry: DataFrame, kernel: KernelSpec, cfg: EngineConfig, x: DataFrame, symmetric: bool = False) -> DataFrame:
    """(i, re, im) = H x for one vector: couplings and near field are applied where they are made and not stored."""
    above = top_level(blocks)
    row_basis = nested_basis(membership, clusters, geometry, kernel, cfg, "row", above)
    col_basis = nested_basis(membership, clusters, geometry, kernel, cfg, "col", above) if kernel.layer == "dlp" else row_basis
    depth = clusters.agg(F.max("level")).first()[0] or 0
    h = H2(row_basis, col_basis, None, None, blocks, max(above, depth), cfg.band, above, symmetric)
    pivot = lambda basis: basis.where("place >= 0").select("node", "i", "geo", "v")
    cols = with_vector(pivot(col_basis), forward(h, x))
    rows = cols if kernel.layer == "slp" else with_vector(pivot(row_basis), x.select(F.lit(-1).cast("long").alias("node"), "i", "re", "im"))
    far, near_ = (blocks.where(F.col("kind") == k).select("t", "s") for k in ("far", "near"))
    carried = backward(h, fill.apply(far, rows, cols, kernel, cfg, "one", symmetric))
    leaf = membership.select("node", "i").join(geometry, "i")
    leaves = with_vector(leaf, membership.select("node", "i").join(x, "i"))
    direct = fill.apply(near_, leaves, leaves, kernel, cfg, "two", symmetric).select("i", "re", "im")
    return carried.unionByName(direct).groupBy("i").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))


def matvec(h: H2, x: DataFrame) -> DataFrame:
    """(i, value) = H x for real kernels."""
    return complex_matvec(h, x.select("i", F.col("value").alias("re"), F.lit(0.0).alias("im"))).select("i", F.col("re").alias("value"))


def _pivot_names(basis: DataFrame) -> DataFrame:
    return basis.where("place >= 0").select("node", F.col("place").alias("k"), F.col("i").alias("pivot"))


def _coefs(basis: DataFrame) -> DataFrame:
    """(node, level, son, i, pivot, c): the interpolation coefficients in entry form."""
    return basis.select("node", "level", "son", "i", F.posexplode("coef").alias("k", "c")).join(_pivot_names(basis), ["node", "k"]).select("node", "level", "son", "i", "pivot", "c")


def one_sided(blocks: DataFrame, row_flat: DataFrame, members: DataFrame, kernel: KernelSpec, cfg: EngineConfig) -> DataFrame:
    """(t, s, i, j, re): V_t G(pivots, s) for far blocks with a flat row basis. members: (node, i, geo, v) of all clusters."""
    g = fill.fill(blocks.select("t", "s"), pivot_members(row_flat), fill.members(members), kernel, cfg, "one").withColumnRenamed("i", "pivot")
    c = _coefs(row_flat).select(F.col("node").alias("t"), "i", "pivot", "c")
    return g.join(c, ["t", "pivot"]).groupBy("t", "s", "i", "j").agg(F.sum(F.col("re") * F.col("c")).alias("re"))


def two_sided(blocks: DataFrame, row_flat: DataFrame, col_flat: DataFrame, kernel: KernelSpec, cfg: EngineConfig) -> DataFrame:
    """(t, s, i, j, re): V_t G(pivots, pivots) V_s^T for far blocks with flat bases (transpose, not adjoint)."""
    g = fill.fill(blocks.select("t", "s"), pivot_members(row_flat), pivot_members(col_flat), kernel, cfg, "one").select("t", "s", F.col("i").alias("p"), F.col("j").alias("q"), "re")
    ct = _coefs(row_flat).select(F.col("node").alias("t"), "i", F.col("pivot").alias("p"), F.col("c").alias("c1"))
    cs = _coefs(col_flat).select(F.col("node").alias("s"), F.col("i").alias("j"), F.col("pivot").alias("q"), F.col("c").alias("c2"))
    half = g.join(ct, ["t", "p"]).groupBy("t", "s", "i", "q").agg(F.sum(F.col("re") * F.col("c1")).alias("x"))
    return half.join(cs, ["s", "q"]).groupBy("t", "s", "i", "j").agg(F.sum(F.col("x") * F.col("c2")).alias("re"))


def unpivoted(blocks: DataFrame, clusters: DataFrame, members: DataFrame, kernel: KernelSpec, cfg: EngineConfig) -> DataFrame:
    """(t, s, i, j, re): the rank-2m form A_t B_ts^T of far blocks, without pivots: the largest factors of all. members as in
    one_sided."""
    m = fill.members(members)
    rows = blocks.select("t", "s").join(m.select(F.col("node").alias("t"), F.col("members").alias("a")), "t").join(m.select(F.col("node").alias("s"), F.col("members").alias("b")), "s").join(clusters.select(F.col("node").alias("t"), *BOX), "t")

    def run(batches):
        for batch in batches:
            na, ia, ga, _ = fill._side(batch.column(2))
            nb, ib, gb, _ = fill._side(batch.column(3))
            box = np.stack([np.asarray(batch.column(4 + k)) for k in range(6)], 1)
            sa, sb, out = np.cumsum(na) - na, np.cumsum(nb) - nb, []
            for r, (t, s) in enumerate(zip(batch.column(1).to_pylist(), batch.column(0).to_pylist(), strict=True)):
                p, q = slice(sa[r], sa[r] + na[r]), slice(sb[r], sb[r] + nb[r])
                surface = green.surface(box[r, :3], box[r, 3:], cfg.green_q, cfg.box_scale, cfg.norm)
                low = np.real(green.row_factor(ga[p], surface, kernel) @ green.column_factor(gb[q], surface, kernel).T)
                out.append(pa.table({"t": pa.array([t] * low.size, pa.int64()), "s": pa.array([s] * low.size, pa.int64()), "i": pa.array(np.repeat(ia[p], nb[r])), "j": pa.array(np.tile(ib[q], na[r])), "re": pa.array(low.ravel())}))
            yield from pa.concat_tables(out).combine_chunks().to_batches() if out else []

    return rows.select("s", "t", "a", "b", *BOX).mapInArrow(run, "t long, s long, i long, j long, re double")


def aca_blocks(blocks: DataFrame, members: DataFrame, kernel: KernelSpec, cfg: EngineConfig, check: bool = False) -> DataFrame:
    """Cross approximation of each far block itself, entries on demand: (t, s, rank, evaluated, error). The baseline: adapts by
    block, only the asked rows and columns are evaluated. check: the error against the whole block, evaluated for that only.

    A task gets lists of blocks whose members stay below the limit plus one block, and evaluates strips of a block, so its
    memory follows the members of one block and not their product."""
    far = blocks.where("kind = 'far'").select("t", "s")
    used = far.select(F.col("t").alias("node")).union(far.select("s")).distinct()
    m = settled(fill.members(members.join(used, "node", "left_semi")))
    size = lambda side: m.select(F.col("node").alias(side), F.size("members").alias(f"n_{side}"))
    sized = far.join(size("t"), "t").join(size("s"), "s").select("t", "s", ((F.col("n_t") + F.col("n_s")) * MEMBER_BYTES).cast("long").alias("bytes"))
    limit = min(cfg.limit_bytes, 1 << 20)
    tasks = int(min(10_000, (sized.agg(F.sum("bytes")).first()[0] or 0) // limit + 1))  # given, since short lists hold much work
    rows = packages.prefix(sized, limit, ["t", "s"]).join(m.select(F.col("node").alias("t"), F.col("members").alias("a")), "t").join(m.select(F.col("node").alias("s"), F.col("members").alias("b")), "s")
    run = lambda table: _aca_list(table, kernel, cfg, check)
    return rows.select("list", "s", "t", "a", "b").repartition(tasks, "list").groupBy("list").applyInArrow(run, "t long, s long, rank long, evaluated long, error double")


def _aca_list(table: pa.Table, kernel: KernelSpec, cfg: EngineConfig, check: bool, most: int = 1 << 17) -> pa.Table:
    na, _, ga, va = fill._side(table.column("a"))
    nb, _, gb, vb = fill._side(table.column("b"))
    sa, sb, out = np.cumsum(na) - na, np.cumsum(nb) - nb, []
    for r, (s, t) in enumerate(zip(table.column("s").to_pylist(), table.column("t").to_pylist(), strict=True)):
        a, b = np.arange(sa[r], sa[r] + na[r]), np.arange(sb[r], sb[r] + nb[r])

        def values(p, q):
            return fill.integrate(ga[p], None if va is None else va[p], gb[q], None if vb is None else vb[q], kernel, cfg.quad, "one")

        row = lambda i: values(np.full(len(b), a[i]), b)  # noqa: E731, B023
        col = lambda j: values(a, np.full(len(a), b[j]))  # noqa: E731, B023
        found, cols, u, v = cross.partial(row, col, (len(a), len(b)), cfg.aca_eps, cfg.kmax)
        error = None
        if check:
            off, whole = 0.0, 0.0
            step = max(1, most // len(b))
            for k in range(0, len(a), step):
                part = a[k : k + step]
                g = values(np.repeat(part, len(b)), np.tile(b, len(part))).reshape(len(part), len(b))
                whole += np.linalg.norm(g) ** 2
                off += np.linalg.norm(g - u[k : k + step] @ v.T) ** 2
            error = float(np.sqrt(off) / max(np.sqrt(whole), 1e-300))
        out.append((t, s, len(found), len(found) * len(b) + len(cols) * len(a), error))
    columns = list(zip(*out, strict=True)) if out else [[]] * 5
    return pa.table({n: pa.array(c, k) for n, c, k in zip(("t", "s", "rank", "evaluated", "error"), columns, (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.float64()), strict=True)})


def storage(h: H2) -> DataFrame:
    """Bytes of leaf bases, transfers, couplings and near field."""
    size = F.size("coef") * 8
    leaf = h.row_basis.where("son = 0").agg(F.coalesce(F.sum(size), F.lit(0)).cast("long").alias("bytes")).withColumn("part", F.lit("leaf basis"))
    up = h.row_basis.where("son > 0").agg(F.coalesce(F.sum(size), F.lit(0)).cast("long").alias("bytes")).withColumn("part", F.lit("transfer"))
    c = h.coupling.agg((F.count("*") * 8).alias("bytes")).withColumn("part", F.lit("coupling"))
    n = h.nearfield.agg((F.count("*") * 8).alias("bytes")).withColumn("part", F.lit("nearfield"))
    return leaf.unionByName(up).unionByName(c).unionByName(n).select("part", "bytes")


def save(h: H2, folder: str) -> None:
    """The four tables as Parquet, couplings and near field partitioned for pruning by kind."""
    h.row_basis.write.mode("overwrite").partitionBy("level").parquet(f"{folder}/row_basis")
    h.col_basis.write.mode("overwrite").partitionBy("level").parquet(f"{folder}/col_basis")
    h.coupling.write.mode("overwrite").parquet(f"{folder}/coupling")
    h.nearfield.write.mode("overwrite").parquet(f"{folder}/nearfield")
