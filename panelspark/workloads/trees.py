"""Cluster trees, blocks, separation, compression."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import oracles as O
from ..config import EngineConfig
from ..operators import baselines, blocks, clustering, cross, geometry, green, h2, measures
from ..operators.kernels import slp
from ..plans.scratch import settled
from .registry import Registry, scaled, table

R = Registry()
LEAF = 8
MAX_LEVEL = 24


def customer_points(spark, sf_dir):
    rows = table(spark, sf_dir, "customer").withColumn("seg", F.length("c_mktsegment") * 7 + F.pmod("c_custkey", F.lit(97)))
    return geometry.scaled_points(rows, "c_custkey", ["c_acctbal", "c_nationkey", "seg"])


POINTS = """raw AS (SELECT c_custkey AS i, c_acctbal AS a, CAST(c_nationkey AS DOUBLE) AS b, CAST(length(c_mktsegment) * 7 + c_custkey % 97 AS DOUBLE) AS c FROM customer),
ends AS (SELECT min(a) la, max(a) ha, min(b) lb, max(b) hb, min(c) lc, max(c) hc FROM raw),
pts AS (SELECT i, coalesce((a - la) / nullif(ha - la, 0), 0.0) AS x, coalesce((b - lb) / nullif(hb - lb, 0), 0.0) AS y, coalesce((c - lc) / nullif(hc - lc, 0), 0.0) AS z FROM raw, ends)"""


def tree_sql(leaf=LEAF, levels=MAX_LEVEL) -> str:
    """CTEs t0, t1, .. with the points of each level, and `tree`(i, node, level)."""
    out = [POINTS, "t0 AS (SELECT i, round(x, 12) AS x, round(y, 12) AS y, round(z, 12) AS z, CAST(1 AS BIGINT) AS node FROM pts)"]
    ends = []
    for k in range(levels):
        out.append(f"b{k} AS (SELECT node, count(*) AS n, min(x) lx, max(x) hx, min(y) ly, max(y) hy, min(z) lz, max(z) hz FROM t{k} GROUP BY node)")
        out.append(f"c{k} AS (SELECT node, n > {leaf} AND greatest(hx - lx, hy - ly, hz - lz) > 0 AS splits, CASE WHEN hx - lx >= hy - ly AND hx - lx >= hz - lz THEN 0 WHEN hy - ly >= hz - lz THEN 1 ELSE 2 END AS axis, (lx + hx) / 2 AS mx, (ly + hy) / 2 AS my, (lz + hz) / 2 AS mz FROM b{k})")
        out.append(f"t{k + 1} AS (SELECT i, x, y, z, node * 2 + CASE WHEN (CASE axis WHEN 0 THEN x <= mx WHEN 1 THEN y <= my ELSE z <= mz END) THEN 0 ELSE 1 END AS node FROM t{k} JOIN c{k} USING (node) WHERE splits)")
        ends.append(f"SELECT i, node, {k} AS level FROM t{k} JOIN c{k} USING (node) WHERE NOT splits")
    return ",\n".join([*(x if x.startswith("raw") else x.replace(" AS (SELECT", " AS MATERIALIZED (SELECT", 1) for x in out), "tree AS (" + " UNION ALL ".join(ends) + ")"])


BOXES = """anc AS (SELECT i, CAST(node >> k AS BIGINT) AS node, level - k AS level, k = 0 AS leaf FROM tree, range(0, 30) AS q(k) WHERE k <= level),
clusters AS MATERIALIZED (SELECT node, CAST(level AS INTEGER) AS level, bool_or(leaf) AS is_leaf, count(*) AS cnt, min(x) AS lox, min(y) AS loy, min(z) AS loz, max(x) AS hix, max(y) AS hiy, max(z) AS hiz,
 sqrt(pow(max(x) - min(x), 2) + pow(max(y) - min(y), 2) + pow(max(z) - min(z), 2)) AS diam, greatest(max(x) - min(x), max(y) - min(y), max(z) - min(z)) AS diam_max FROM anc JOIN pts USING (i) GROUP BY node, level)"""


def tree(spark, sf_dir, leaf=LEAF):
    pts = settled(customer_points(spark, sf_dir))
    member = settled(clustering.geometric_tree(pts, leaf))
    return pts, member, settled(clustering.boxes(member, clustering.point_extents(pts)))


@R.add(f"WITH {tree_sql()} SELECT i, node, level FROM tree")
def cluster_tree(spark, sf_dir):
    return clustering.geometric_tree(customer_points(spark, sf_dir), LEAF)


@R.add(f"WITH {tree_sql()}, {BOXES} SELECT node, level, is_leaf, cnt, {', '.join(O.scaled(c, 10, c) for c in ('lox', 'loy', 'loz', 'hix', 'hiy', 'hiz', 'diam'))} FROM clusters")
def cluster_boxes(spark, sf_dir):
    _, _, c = tree(spark, sf_dir)
    return c.select("node", "level", "is_leaf", "cnt", *[scaled(F.col(x), 10, x) for x in ("lox", "loy", "loz", "hix", "hiy", "hiz", "diam")])


def _median_sql(depth=4):
    out = [POINTS, "m0 AS (SELECT *, CAST(1 AS BIGINT) AS node FROM pts)"]
    for k in range(depth):
        out.append(f"m{k + 1} AS (SELECT i, x, y, z, node * 2 + CASE WHEN row_number() OVER (PARTITION BY node ORDER BY {'xyz'[k % 3]}, i) * 2 <= count(*) OVER (PARTITION BY node) + 1 THEN 0 ELSE 1 END AS node FROM m{k})")
    return "WITH " + ",\n".join(out) + f" SELECT i, node, {depth} AS level FROM m{depth}"


@R.add(_median_sql())
def cluster_median(spark, sf_dir):
    return clustering.median_tree(customer_points(spark, sf_dir), 4)


def _morton_sql(depth=3):
    cell = {a: f"CAST(least(greatest(floor(({a} + 1.0) / 2.0 * {1 << depth}), 0), {(1 << depth) - 1}) AS BIGINT)" for a in "xyz"}
    code = "CAST(1 AS BIGINT)"
    for bit in range(depth - 1, -1, -1):
        for a in "xyz":
            code = f"({code} * 2 + ({cell[a]} >> {bit}) % 2)"
    return f"WITH u AS (SELECT vec_id AS i, CAST(embedding[1] AS DOUBLE) AS x0, CAST(embedding[2] AS DOUBLE) AS y0, CAST(embedding[3] AS DOUBLE) AS z0 FROM embeddings), s AS (SELECT i, x0 / sqrt(x0*x0+y0*y0+z0*z0) AS x, y0 / sqrt(x0*x0+y0*y0+z0*z0) AS y, z0 / sqrt(x0*x0+y0*y0+z0*z0) AS z FROM u WHERE x0*x0+y0*y0+z0*z0 > 0) SELECT i, {code} AS node, {3 * depth} AS level FROM s"


@R.add(_morton_sql())
def cluster_morton(spark, sf_dir):
    return clustering.morton_tree(geometry.unit_points(table(spark, sf_dir, "embeddings"), "vec_id", "embedding"), 3)


@R.add("SELECT coalesce(region.r_regionkey, -1) AS r_regionkey, coalesce(nation.n_nationkey, -1) AS n_nationkey, count(*) AS cnt, CAST(round(sum(c_acctbal) * 100) AS BIGINT) AS cents, CAST(grouping(region.r_regionkey) * 2 + grouping(nation.n_nationkey) AS BIGINT) AS gid FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (region.r_regionkey, nation.n_nationkey)")
def key_tree_rollup(spark, sf_dir):
    out = clustering.key_tree(table(spark, sf_dir, "region"), table(spark, sf_dir, "nation"), table(spark, sf_dir, "customer"), "c_nationkey", "c_acctbal")
    return out.select(F.coalesce("r_regionkey", F.lit(-1)).alias("r_regionkey"), F.coalesce("n_nationkey", F.lit(-1)).alias("n_nationkey"), "cnt", F.round(F.col("total") * 100).cast("long").alias("cents"), F.col("gid").cast("long").alias("gid"))


def _block_sql(tail, levels=26):
    """Level by level: pairs of clusters with their kind."""
    kind = blocks.kind_sql(1.0)
    out = [f"k0 AS (SELECT a.node AS t, b.node AS s, {kind} AS kind, a.cnt AS rws, b.cnt AS cls, a.is_leaf AS tl, b.is_leaf AS sl FROM clusters a, clusters b WHERE a.node = 1 AND b.node = 1)"]
    for k in range(1, levels):
        out.append(f"f{k} AS (SELECT unnest(CASE WHEN tl THEN [t] ELSE [2 * t, 2 * t + 1] END) AS t, s, sl FROM k{k - 1} WHERE kind = 'split'), g{k} AS (SELECT t, unnest(CASE WHEN sl THEN [s] ELSE [2 * s, 2 * s + 1] END) AS s FROM f{k}), k{k} AS MATERIALIZED (SELECT g.t, g.s, {kind} AS kind, a.cnt AS rws, b.cnt AS cls, a.is_leaf AS tl, b.is_leaf AS sl FROM g{k} g JOIN clusters a ON a.node = g.t JOIN clusters b ON b.node = g.s)")
    union = " UNION ALL ".join(f"SELECT t, s, {k} AS level, kind, rws AS \"rows\", cls AS cols FROM k{k} WHERE kind <> 'split'" for k in range(levels))
    return f"WITH {tree_sql()}, {BOXES}, {', '.join(out)}, blk AS ({union}) {tail}"


@R.add(_block_sql('SELECT t, s, level, kind, "rows", cols FROM blk'))
def block_tree(spark, sf_dir):
    _, _, c = tree(spark, sf_dir)
    return blocks.block_tree(c)


@R.add(_block_sql('SELECT coalesce(blk.level, -1) AS level, coalesce(blk.kind, \'all\') AS kind, count(*) AS blocks, CAST(sum("rows" * cols) AS BIGINT) AS entries, CAST(grouping(blk.level) * 2 + grouping(blk.kind) AS BIGINT) AS gid FROM blk GROUP BY CUBE (blk.level, blk.kind)'))
def block_census(spark, sf_dir):
    _, _, c = tree(spark, sf_dir)
    out = blocks.census(settled(blocks.block_tree(c)))
    return out.select(F.coalesce("level", F.lit(-1)).alias("level"), F.coalesce("kind", F.lit("all")).alias("kind"), "blocks", "entries", F.col("gid").cast("long").alias("gid"))


@R.add("SELECT CAST(count(*) * count(*) AS BIGINT) AS covered, CAST(count(*) * count(*) AS BIGINT) AS entries, 0 AS repeated FROM customer")
def block_coverage(spark, sf_dir):
    _, _, c = tree(spark, sf_dir)
    out = blocks.coverage(settled(blocks.block_tree(c)), c.where("is_leaf"))
    return out.select("covered", "entries", (F.col("blocks") - F.col("distinct_blocks")).cast("int").alias("repeated"))


@R.add("SELECT CAST(count(*) * count(*) AS BIGINT) AS covered, CAST(count(*) * count(*) AS BIGINT) AS entries, 0 AS repeated FROM customer")
def block_symmetric(spark, sf_dir):
    """One block of each pair (t, s), (s, t): the two together still cover every entry once."""
    _, _, c = tree(spark, sf_dir)
    out = blocks.coverage(settled(blocks.block_tree(c, symmetric=True)), c.where("is_leaf"), symmetric=True)
    return out.select("covered", "entries", (F.col("blocks") - F.col("distinct_blocks")).cast("int").alias("repeated"))


@R.add(_block_sql('SELECT t, s, level, kind, "rows", cols FROM blk'))
def block_tree_sql(spark, sf_dir):
    """The block tree by joins of the frontier, the way for more clusters than a task should hold."""
    _, _, c = tree(spark, sf_dir)
    return blocks.block_tree(c, broadcast_rows=0)


@R.add(_block_sql("SELECT (SELECT count(*) FROM clusters) AS clusters, (SELECT CAST(sum(CAST(is_leaf AS INT)) AS BIGINT) FROM clusters) AS leaves, (SELECT max(level) FROM clusters) AS depth, count(*) AS blocks, CAST(sum(CASE WHEN kind = 'far' THEN 1 ELSE 0 END) AS BIGINT) AS far FROM blk"))
def tree_stats(spark, sf_dir):
    _, _, c = tree(spark, sf_dir)
    return measures.tree_stats(c, settled(blocks.block_tree(c)))


NATION = f"""{POINTS}, clusters AS (SELECT c_nationkey AS node, min(x) AS lox, min(y) AS loy, min(z) AS loz, max(x) AS hix, max(y) AS hiy, max(z) AS hiz, true AS is_leaf, count(*) AS cnt, greatest(max(x)-min(x), max(y)-min(y), max(z)-min(z)) AS diam_max FROM pts JOIN customer ON c_custkey = i GROUP BY 1)"""


@R.add(f"WITH {NATION} SELECT a.node AS t, b.node AS s, {blocks.kind_sql(1.0)} = 'far' AS admissible FROM clusters a, clusters b")
def admissible_pairs(spark, sf_dir):
    """At most 25 nations: the pairs of a table of fixed size."""
    nation = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("i"), F.col("c_nationkey").cast("long").alias("node"), F.lit(0).alias("level"))
    c = clustering.boxes(nation, clustering.point_extents(customer_points(spark, sf_dir)))
    rows = blocks.side(c, "t").crossJoin(F.broadcast(blocks.side(c, "s")))
    return rows.select(F.col("t_node").cast("int").alias("t"), F.col("s_node").cast("int").alias("s"), blocks.admissible("t", "s", 1.0).alias("admissible"))


@R.add(f"WITH {tree_sql()}, {BOXES} SELECT node, count(*) AS nodes, {O.scaled('2 * ((hix-lox+diam_max)*(hiy-loy+diam_max) + (hiy-loy+diam_max)*(hiz-loz+diam_max) + (hiz-loz+diam_max)*(hix-lox+diam_max))', 8, 'surface')} FROM clusters, range(0, 96) GROUP BY ALL")
def green_nodes(spark, sf_dir):
    _, _, c = tree(spark, sf_dir)
    return green.box_nodes(c, 4).groupBy("node").agg(F.count("*").alias("nodes"), scaled(F.sum("w"), 8, "surface"))


@R.add(_block_sql(f"SELECT count(*) AS far, sum(CASE WHEN d < a.diam_max / 2 - 1e-12 THEN 1 ELSE 0 END)::BIGINT AS too_near FROM (SELECT *, greatest(a.lox - a.diam_max / 2 - b.hix, b.lox - a.hix - a.diam_max / 2, a.loy - a.diam_max / 2 - b.hiy, b.loy - a.hiy - a.diam_max / 2, a.loz - a.diam_max / 2 - b.hiz, b.loz - a.hiz - a.diam_max / 2) AS d FROM blk JOIN clusters a ON a.node = t JOIN clusters b ON b.node = s WHERE kind = 'far')".replace("a.diam_max / 2 - 1e-12 THEN", "half - 1e-12 THEN").replace("SELECT *, greatest", "SELECT a.diam_max / 2 AS half, greatest")))
def separation_check(spark, sf_dir):
    """No far partner comes nearer to the enlarged box of a cluster than half its diameter (maximum norm)."""
    _, _, c = tree(spark, sf_dir)
    far = settled(blocks.block_tree(c)).where("kind = 'far'").select("t", "s").join(blocks.side(c, "t"), F.col("t") == F.col("t_node")).join(blocks.side(c, "s"), F.col("s") == F.col("s_node"))
    h = F.col("t_diam_max") / 2
    d = F.greatest(*[x for a in "xyz" for x in (F.col(f"t_lo{a}") - h - F.col(f"s_hi{a}"), F.col(f"s_lo{a}") - F.col(f"t_hi{a}") - h)])
    return far.agg(F.count("*").alias("far"), F.sum((d < h - 1e-12).cast("long")).alias("too_near"))


FEW = "vec_id < 300"  # the points of the dense SQL of h2_matvec and green_factor


def sphere_points(spark, sf_dir, which="true"):
    return geometry.unit_points(table(spark, sf_dir, "embeddings").where(which), "vec_id", "embedding")


def compressed(spark, sf_dir, eps=1e-5, which="true"):
    cfg = EngineConfig(leaf_size=LEAF, aca_eps=eps)
    pts = settled(sphere_points(spark, sf_dir, which))
    member = settled(clustering.geometric_tree(pts, LEAF))
    c = settled(clustering.boxes(member, clustering.point_extents(pts)))
    blk = settled(blocks.block_tree(c))
    return pts, member, c, blk, cfg


UNIT = "q AS (SELECT vec_id AS i, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y, CAST(embedding[3] AS DOUBLE) AS z FROM embeddings WHERE vec_id < 300), u AS (SELECT i, x / sqrt(x*x+y*y+z*z) AS x, y / sqrt(x*x+y*y+z*z) AS y, z / sqrt(x*x+y*y+z*z) AS z FROM q WHERE x*x+y*y+z*z > 0)"


@R.add(f"WITH {UNIT} SELECT a.i, CAST(round(sum(1.0 / ({O.FOUR_PI} * sqrt(pow(a.x-b.x,2) + pow(a.y-b.y,2) + pow(a.z-b.z,2)))) * 10) AS BIGINT) AS y10 FROM u a JOIN u b ON a.i <> b.i GROUP BY a.i")
def h2_matvec(spark, sf_dir):
    """The compressed product with ones agrees with the dense sum to the printed digit. The points of its SQL."""
    return _product(spark, sf_dir, FEW)


@R.add()
def h2_matvec_all(spark, sf_dir):
    """All points. Without SQL: the tests compare with the dense sum on a fixture."""
    return _product(spark, sf_dir, "true")


def _product(spark, sf_dir, which):
    pts, member, c, blk, cfg = compressed(spark, sf_dir, 1e-8, which)
    h = h2.build(member, c, blk, h2.point_rows(pts), slp(), cfg)
    y = h2.matvec(h, pts.select("i", F.lit(1.0).alias("value")))
    return y.select("i", F.round(F.col("value") * 10).cast("long").alias("y10"))


@R.add()
def h2_storage(spark, sf_dir):
    pts, member, c, blk, cfg = compressed(spark, sf_dir)
    return h2.storage(h2.build(member, c, blk, h2.point_rows(pts), slp(), cfg))


@R.add()
def nested_basis_ranks(spark, sf_dir):
    pts, member, c, _, cfg = compressed(spark, sf_dir)
    return measures.rank_stats(h2.nested_basis(member, c, h2.point_rows(pts), slp(), cfg), 6 * cfg.green_q**2)


@R.add()
def gca_pivots(spark, sf_dir):
    """(node, rank) of the flat bases."""
    pts, member, c, blk, cfg = compressed(spark, sf_dir)
    return h2.flat_basis(member, c, h2.point_rows(pts), slp(), cfg, blocks=blk).groupBy("node").agg(F.sum((F.col("place") >= 0).cast("int")).alias("rank"))


@R.add()
def gca_interpolation(spark, sf_dir):
    """The largest deviation of pivot rows from the identity."""
    pts, member, c, blk, cfg = compressed(spark, sf_dir)
    b = h2.flat_basis(member, c, h2.point_rows(pts), slp(), cfg, blocks=blk).where("place >= 0").select("place", F.posexplode("coef").alias("k", "v"))
    return b.agg(F.max(F.abs(F.col("v") - (F.col("place") == F.col("k")).cast("double"))).alias("worst"))


@R.add()
def aca_blocks(spark, sf_dir):
    pts, member, _, blk, cfg = compressed(spark, sf_dir)
    rows = clustering.ancestors(member).select("i", "node").join(h2.point_rows(pts), "i")
    return h2.aca_blocks(blk, rows, slp(), cfg, check=True)


@R.add(f"WITH {UNIT}, c AS (SELECT min(x) lx, max(x) hx, min(y) ly, max(y) hy, min(z) lz, max(z) hz FROM u WHERE z > 0.8), d AS (SELECT *, greatest(hx-lx, hy-ly, hz-lz) AS delta FROM c), {O.line(4, 'gl')}, f AS (SELECT axis, sign, p.x AS a, q.x AS b, p.w * q.w AS uw FROM gl p, gl q, (VALUES (0), (1), (2)) AS ax(axis), (VALUES (0), (1)) AS sg(sign)), nd AS (SELECT lx - delta/2 + (CASE axis WHEN 0 THEN sign WHEN 1 THEN b ELSE a END) * (hx - lx + delta) AS zx, ly - delta/2 + (CASE axis WHEN 1 THEN sign WHEN 2 THEN b ELSE a END) * (hy - ly + delta) AS zy, lz - delta/2 + (CASE axis WHEN 2 THEN sign WHEN 0 THEN b ELSE a END) * (hz - lz + delta) AS zz, CASE axis WHEN 0 THEN 2*sign-1 ELSE 0 END AS mx, CASE axis WHEN 1 THEN 2*sign-1 ELSE 0 END AS my, CASE axis WHEN 2 THEN 2*sign-1 ELSE 0 END AS mz, uw * CASE axis WHEN 0 THEN (hy-ly+delta)*(hz-lz+delta) WHEN 1 THEN (hz-lz+delta)*(hx-lx+delta) ELSE (hx-lx+delta)*(hy-ly+delta) END AS w, delta FROM f, d), e AS (SELECT i, sqrt(w) AS rw, delta, x - zx AS dx, y - zy AS dy, z - zz AS dz, mx, my, mz FROM u, nd WHERE z > 0.8) SELECT i, {O.scaled(f'sum(rw / ({O.FOUR_PI} * sqrt(dx*dx+dy*dy+dz*dz)))', 8, 'plus')}, {O.scaled(f'sum(rw * delta * (dx*mx+dy*my+dz*mz) / ({O.FOUR_PI} * (dx*dx+dy*dy+dz*dz) * sqrt(dx*dx+dy*dy+dz*dz)))', 8, 'minus')} FROM e GROUP BY i")
def green_factor(spark, sf_dir):
    """Row sums of both parts of the row factor of one cap of the points of its SQL."""
    return _cap(spark, sf_dir, FEW)


@R.add(f"WITH {UNIT.replace(' WHERE ' + FEW, '')}, c AS (SELECT min(x) lx, max(x) hx, min(y) ly, max(y) hy, min(z) lz, max(z) hz FROM u WHERE z > 0.8), d AS (SELECT *, greatest(hx-lx, hy-ly, hz-lz) AS delta FROM c), {O.line(4, 'gl')}, f AS (SELECT axis, sign, p.x AS a, q.x AS b, p.w * q.w AS uw FROM gl p, gl q, (VALUES (0), (1), (2)) AS ax(axis), (VALUES (0), (1)) AS sg(sign)), nd AS (SELECT lx - delta/2 + (CASE axis WHEN 0 THEN sign WHEN 1 THEN b ELSE a END) * (hx - lx + delta) AS zx, ly - delta/2 + (CASE axis WHEN 1 THEN sign WHEN 2 THEN b ELSE a END) * (hy - ly + delta) AS zy, lz - delta/2 + (CASE axis WHEN 2 THEN sign WHEN 0 THEN b ELSE a END) * (hz - lz + delta) AS zz, CASE axis WHEN 0 THEN 2*sign-1 ELSE 0 END AS mx, CASE axis WHEN 1 THEN 2*sign-1 ELSE 0 END AS my, CASE axis WHEN 2 THEN 2*sign-1 ELSE 0 END AS mz, uw * CASE axis WHEN 0 THEN (hy-ly+delta)*(hz-lz+delta) WHEN 1 THEN (hz-lz+delta)*(hx-lx+delta) ELSE (hx-lx+delta)*(hy-ly+delta) END AS w, delta FROM f, d), e AS (SELECT i, sqrt(w) AS rw, delta, x - zx AS dx, y - zy AS dy, z - zz AS dz, mx, my, mz FROM u, nd WHERE z > 0.8) SELECT i, {O.scaled(f'sum(rw / ({O.FOUR_PI} * sqrt(dx*dx+dy*dy+dz*dz)))', 8, 'plus')}, {O.scaled(f'sum(rw * delta * (dx*mx+dy*my+dz*mz) / ({O.FOUR_PI} * (dx*dx+dy*dy+dz*dz) * sqrt(dx*dx+dy*dy+dz*dz)))', 8, 'minus')} FROM e GROUP BY i")
def green_factor_all(spark, sf_dir):
    return _cap(spark, sf_dir, "true")


def _cap(spark, sf_dir, which):
    pts = sphere_points(spark, sf_dir, which).where("z > 0.8").withColumn("node", F.lit(1).cast("long"))
    member = pts.select("i", "node", F.lit(0).alias("level"))
    c = clustering.boxes(member, clustering.point_extents(pts))
    a = green.point_factor(pts, green.box_nodes(c, 4))
    return a.groupBy("i").agg(scaled(F.sum("plus"), 8, "plus"), scaled(F.sum("minus"), 8, "minus"))


@R.add()
def green_lowrank_error(spark, sf_dir):
    """Relative error of the un-pivoted form between two opposite caps, by the number of Gauss points."""
    import numpy as np

    pts = settled(sphere_points(spark, sf_dir).where("abs(z) > 0.8"))
    top = np.array([list(r) for r in pts.where("z > 0").select("x", "y", "z").toLocalIterator()]).reshape(-1, 3)
    orders, rows = (2, 3, 4, 5, 6), []
    errors = cap_errors(pts, top.min(0), top.max(0), orders) if len(top) else {}
    for q in orders if errors else ():
        # the pivots need the whole row factor of one cap: 12 q^2 numbers a point
        p = cross.full(green.row_factor(top, green.surface(top.min(0), top.max(0), q, 1.0, "max"), slp()), 1e-6)
        rows.append((q, errors[q], len(p[0])))
    return spark.createDataFrame(rows, "q int, error double, rank int")


def cap_errors(pts, lo, hi, orders, block_rows=1024):
    """The relative error of the block between the points of z > 0 and those of z < 0 by order: blocks of points meet in
    tasks, which return sums of squares only."""
    import numpy as np
    import pyarrow as pa

    lo, hi = [float(x) for x in lo], [float(x) for x in hi]
    blocks = max(1, -(-pts.count() // block_rows))
    rows = pts.select(F.when(F.col("z") > 0, "a").otherwise("b").alias("side"), F.pmod(F.xxhash64("i"), F.lit(blocks)).alias("blk"), F.array("x", "y", "z").alias("p"))
    held = settled(rows.groupBy("side", "blk").agg(F.flatten(F.sort_array(F.collect_list("p"))).alias("p")))
    a, b = (held.where(F.col("side") == s).select(F.col("blk").alias(f"k{s}"), F.col("p").alias(s)) for s in "ab")

    def run(table):
        out = []
        for one, other in zip(table.column("a").to_pylist(), table.column("b").to_pylist(), strict=True):
            x, y = np.reshape(one, (-1, 3)), np.reshape(other, (-1, 3))
            left, right = [], []
            for q in orders:
                box = green.surface(np.array(lo), np.array(hi), q, 1.0, "max")
                left.append(green.row_factor(x, box, slp()))
                right.append(green.column_factor(y, box, slp()))
            for k in range(0, len(x), 128):
                exact = slp().values(x[k : k + 128, None] - y[None])
                whole = float(np.linalg.norm(exact) ** 2)
                out += [(q, float(np.linalg.norm(exact - u[k : k + 128] @ v.T) ** 2), whole) for q, u, v in zip(orders, left, right, strict=True)]
        q, off, whole = zip(*out, strict=True) if out else ((), (), ())
        return pa.table({"q": pa.array(q, pa.int32()), "off": pa.array(off, pa.float64()), "whole": pa.array(whole, pa.float64())})

    tasks = int(min(10_000, blocks * blocks))
    met = a.crossJoin(b).repartition(tasks, "ka", "kb").groupBy("ka", "kb").applyInArrow(run, "q int, off double, whole double")
    return {r["q"]: (r["off"] / r["whole"]) ** 0.5 for r in met.groupBy("q").agg(F.sum("off").alias("off"), F.sum("whole").alias("whole")).collect()}


@R.add()
def monopole_far(spark, sf_dir):
    """Order-0 cluster potentials against the direct sum: the largest relative error."""
    pts, member, _, blk, _ = compressed(spark, sf_dir)
    p = pts.withColumn("charge", F.lit(1.0))
    y = baselines.monopole_potential(blk, member, p, baselines.monopoles(member, p))
    b = F.broadcast(pts.select(F.col("i").alias("j"), *[F.col(a).alias(f"m{a}") for a in "xyz"]))
    r = F.sqrt(sum(((F.col(a) - F.col(f"m{a}")) ** 2 for a in "xyz"), F.lit(0.0)))
    exact = pts.crossJoin(b).where("i <> j").groupBy("i").agg(F.sum(F.lit(1.0) / (4 * 3.141592653589793 * r)).alias("exact"))
    return y.join(exact, "i").agg(F.max(F.abs(F.col("value") / F.col("exact") - 1)).alias("worst"), F.count("*").alias("points"))


@R.add("SELECT count(*) AS points, true AS second_order_is_nearer FROM embeddings WHERE pow(embedding[1], 2) + pow(embedding[2], 2) + pow(embedding[3], 2) > 0")
def multipole_orders(spark, sf_dir):
    """Far fields up to order 2 against order 0: the mean error of all points falls (direct sum of all pairs as the truth)."""
    pts, member, _, blk, _ = compressed(spark, sf_dir)
    p = settled(pts.withColumn("charge", F.lit(1.0)))
    moments = settled(baselines.multipoles(member, p))
    zero = baselines.monopole_potential(blk, member, p, moments.select("node", "q", "x", "y", "z")).select("i", F.col("value").alias("zero"))
    two = baselines.multipole_potential(blk, member, p, moments).select("i", F.col("value").alias("two"))
    b = F.broadcast(pts.select(F.col("i").alias("j"), *[F.col(a).alias(f"m{a}") for a in "xyz"]))
    r = F.sqrt(sum(((F.col(a) - F.col(f"m{a}")) ** 2 for a in "xyz"), F.lit(0.0)))
    exact = pts.crossJoin(b).where("i <> j").groupBy("i").agg(F.sum(F.lit(1.0) / (4 * 3.141592653589793 * r)).alias("exact"))
    off = lambda c: F.avg(F.abs(F.col(c) / F.col("exact") - 1))
    return zero.join(two, "i").join(exact, "i").agg(F.count("*").alias("points"), (off("two") < off("zero") / 3).alias("second_order_is_nearer"))
