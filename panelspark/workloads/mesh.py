"""Meshes, classes, rules and entries."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import oracles as O
from ..config import BASIC, HIGHER
from ..operators import assembly, classify, geometry, measures, quadrature
from ..operators.kernels import dlp, slp
from .registry import Registry, scaled, table

R = Registry()
N = 4
KAPPA = 3.0


def part_mesh(spark, sf_dir, project=True):
    n = geometry.refinement(table(spark, sf_dir, "part").count())
    return geometry.with_metrics(geometry.sphere_panels(spark, n, project))


def part_density(spark, sf_dir, n):
    """(pid, parts, density): how many parts are on each of the 8 n^2 panels, part k on panel k mod 8 n^2, and their mean price.
    Prices are summed as cents, so that no sum depends on its order."""
    cents = F.sum(F.round(F.col("p_retailprice") * 100).cast("long"))
    rows = table(spark, sf_dir, "part").where("p_partkey is not null").groupBy(F.pmod("p_partkey", F.lit(8 * n * n)).alias("pid"))
    return rows.agg(F.count("*").alias("parts"), cents.alias("cents")).select("pid", "parts", (F.col("cents").cast("double") / (F.col("parts") * 100.0)).alias("density"))


def on_parts(spark, sf_dir):
    """The mesh sized by the parts, with what they put on each panel; 0 where no part is."""
    n = geometry.refinement(table(spark, sf_dir, "part").count())
    panels = geometry.with_metrics(geometry.sphere_panels(spark, n)).join(part_density(spark, sf_dir, n), "pid", "left")
    return panels.withColumns({c: F.coalesce(c, F.lit(z)) for c, z in (("parts", 0), ("density", 0.0))})


PART_DENSITY = "dp AS (SELECT (p_partkey % m + m) % m AS pid, count(*) AS parts, CAST(sum(CAST(round(p_retailprice * 100) AS BIGINT)) AS DOUBLE) / (1e2 * count(*)) AS density FROM part, (SELECT 8 * n * n AS m FROM n0) WHERE p_partkey IS NOT NULL GROUP BY 1)"


def small_mesh(spark, n=N):
    return geometry.with_metrics(geometry.sphere_panels(spark, n))


CORNER_SQL = " UNION ALL ".join(f"SELECT v{k} AS vid, {p}x AS x, {p}y AS y, {p}z AS z FROM p" for k, p in enumerate("akc"))


@R.add(f"WITH {O.panels(O.PART_N)} SELECT vid, {O.scaled('any_value(x)', 12, 'x')}, {O.scaled('any_value(y)', 12, 'y')}, {O.scaled('any_value(z)', 12, 'z')} FROM ({CORNER_SQL}) GROUP BY vid")
def mesh_vertices(spark, sf_dir):
    return geometry.vertices(part_mesh(spark, sf_dir)).select("vid", *[scaled(F.col(a), 12, a) for a in "xyz"])


@R.add(f"WITH {O.panels(O.PART_N)} SELECT pid, v0, v1, v2 FROM p")
def mesh_panels(spark, sf_dir):
    return part_mesh(spark, sf_dir).select("pid", "v0", "v1", "v2")


@R.add(f"WITH {O.panels(O.PART_N, project=False)} SELECT pid, {', '.join(O.scaled(c.replace('b', 'k'), 12, chr(34) + c + chr(34)) for c in geometry.COORDS)} FROM p")
def mesh_pyramid(spark, sf_dir):
    return part_mesh(spark, sf_dir, project=False).select("pid", *[scaled(F.col(c), 12, c) for c in geometry.COORDS])


METRIC = ["gram", "area", "nx", "ny", "nz", "gx", "gy", "gz", "lox", "loy", "loz", "hix", "hiy", "hiz"]


@R.add(f"WITH {O.panels(O.PART_N)} SELECT pid, {', '.join(O.scaled(c, 10, c) for c in METRIC)} FROM p")
def mesh_metrics(spark, sf_dir):
    return part_mesh(spark, sf_dir).select("pid", *[scaled(F.col(c), 10, c) for c in METRIC])


EULER = f"""WITH {O.panels(O.PART_N)}, e0 AS (SELECT v0 AS s, v1 AS t FROM p UNION ALL SELECT v1, v2 FROM p UNION ALL SELECT v2, v0 FROM p),
e1 AS (SELECT least(s, t) AS lo, greatest(s, t) AS hi, count(*) AS c, sum(CASE WHEN s < t THEN 1 ELSE -1 END) AS w FROM e0 GROUP BY ALL),
e AS (SELECT count(*) AS edges, sum(CASE WHEN c <> 2 THEN 1 ELSE 0 END) AS odd, sum(CASE WHEN w <> 0 THEN 1 ELSE 0 END) AS twisted FROM e1),
v AS (SELECT count(DISTINCT s) AS vertices FROM e0), q AS (SELECT count(*) AS panels FROM p)
SELECT vertices, edges, panels, vertices - edges + panels AS euler, CAST(odd AS BIGINT) AS odd_edges, CAST(twisted AS BIGINT) AS twisted_edges FROM e, v, q"""


@R.add(EULER)
def mesh_euler(spark, sf_dir):
    return geometry.euler(part_mesh(spark, sf_dir))


RULE_SQL = " UNION ALL ".join(f"SELECT * FROM (WITH {O.rules(r, s)} SELECT {k} AS spec, cls AS case_, count(*) AS points, {O.scaled('sum(w)', 10, 'w')}, {O.scaled('sum(w * s)', 10, 'ws')}, {O.scaled('sum(w * u * v)', 10, 'wuv')} FROM rules GROUP BY cls)" for k, (r, s) in enumerate(((3, 5), (4, 6))))


@R.add(RULE_SQL)
def quadrature_rule(spark, sf_dir):
    out = None
    for k, q in enumerate((BASIC, HIGHER)):
        one = quadrature.rule_frame(spark, q).groupBy(F.col("case").alias("case_")).agg(F.count("*").alias("points"), scaled(F.sum("w"), 10, "w"), scaled(F.sum(F.col("w") * F.col("s")), 10, "ws"), scaled(F.sum(F.col("w") * F.col("u") * F.col("v")), 10, "wuv")).withColumn("spec", F.lit(k))
        out = one if out is None else out.unionByName(one)
    return out.select("spec", "case_", "points", "w", "ws", "wuv")


@R.add(f"""WITH {O.panels(O.PART_N)}, {O.touching()}
SELECT i, j, cls AS common, array_to_string(list_concat(sh, list_filter(va, lambda x: NOT list_contains(sh, x))), ',') AS first_, array_to_string(list_concat(sh, list_filter(vb, lambda x: NOT list_contains(sh, x))), ',') AS second_
FROM (SELECT q.*, [a.v0, a.v1, a.v2] AS va, [b.v0, b.v1, b.v2] AS vb, list_sort(list_filter([a.v0, a.v1, a.v2], lambda x: list_contains([b.v0, b.v1, b.v2], x))) AS sh FROM near q JOIN p a ON a.pid = i JOIN p b ON b.pid = j)""")
def pair_classes(spark, sf_dir):
    panels = part_mesh(spark, sf_dir)
    rows = classify.aligned(assembly.with_geometry(classify.touching(panels), panels))
    return rows.select("i", "j", F.col("case").alias("common"), *[F.concat_ws(",", *[F.col(f"{s}_v{k}").cast("string") for k in range(3)]).alias(n) for s, n in (("a", "first_"), ("b", "second_"))])


HISTOGRAM = f"""{O.touching()}, h AS (SELECT cls, count(*) AS pairs FROM near GROUP BY cls UNION ALL SELECT 0, (SELECT count(*) * count(*) FROM p) - (SELECT count(*) FROM near))"""
# ordered pairs of parts by the common vertices of their panels
PART_HISTOGRAM = f"""{O.touching()}, {PART_DENSITY}, h1 AS (SELECT cls, CAST(sum(a.parts * b.parts) AS BIGINT) AS pairs FROM near q JOIN dp a ON a.pid = q.i JOIN dp b ON b.pid = q.j GROUP BY cls),
h AS (SELECT * FROM h1 UNION ALL SELECT 0, CAST((SELECT sum(parts) * sum(parts) FROM dp) - (SELECT coalesce(sum(pairs), 0) FROM h1) AS BIGINT))"""
POINTS = "CASE cls WHEN 0 THEN {0} WHEN 1 THEN {1} WHEN 2 THEN {2} ELSE {3} END"


@R.add(f"WITH {O.panels(O.PART_N)}, {PART_HISTOGRAM} SELECT cls AS common, pairs, {POINTS.format(81, 1250, 3125, 3750)} AS points, pairs * {POINTS.format(81, 1250, 3125, 3750)} AS evaluations FROM h")
def class_histogram(spark, sf_dir):
    out = measures.kernel_evals(classify.class_histogram(on_parts(spark, sf_dir), "parts"), BASIC)
    return out.select(F.col("case").alias("common"), "pairs", "points", "evaluations")


@R.add(f"WITH {O.panels(O.PART_N)}, {PART_HISTOGRAM} SELECT 0 AS spec, cls AS common, pairs * {POINTS.format(81, 1250, 3125, 3750)} AS evaluations FROM h UNION ALL SELECT 1, cls, pairs * {POINTS.format(256, 2592, 6480, 7776)} FROM h")
def kernel_eval_counts(spark, sf_dir):
    h = classify.class_histogram(on_parts(spark, sf_dir), "parts")
    out = [measures.kernel_evals(h, q).select(F.lit(k).alias("spec"), F.col("case").alias("common"), "evaluations") for k, q in enumerate((BASIC, HIGHER))]
    return out[0].unionByName(out[1])


@R.add(f"WITH {O.panels(O.PART_N)}, {HISTOGRAM} SELECT CAST(sum(CASE WHEN cls > 0 THEN pairs ELSE 0 END) AS BIGINT) AS touching, CAST(sum(pairs) AS BIGINT) AS pairs, CAST(sum(CASE WHEN cls > 0 THEN pairs ELSE 0 END) * 81 AS BIGINT) AS wasted_points FROM h")
def recompute_overhead(spark, sf_dir):
    return measures.recompute(classify.class_histogram(part_mesh(spark, sf_dir)), 81)


@R.add("""WITH r AS (SELECT row_number() OVER (ORDER BY l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice) AS r, l_orderkey, l_partkey, l_suppkey FROM lineitem WHERE l_orderkey < 200),
c AS (SELECT CAST((a.l_orderkey = b.l_orderkey) AS INT) + CAST((a.l_partkey = b.l_partkey) AS INT) + CAST((a.l_suppkey = b.l_suppkey) AS INT) AS common FROM r a, r b)
SELECT common, count(*) AS pairs FROM c GROUP BY common""")
def lineitem_shared_ids(spark, sf_dir):
    """The orders that its SQL has; lineitem_shared_ids_all takes every row."""
    return _shared_ids(table(spark, sf_dir, "lineitem").where("l_orderkey < 200"))


def _shared_ids(rows):
    rows = rows.select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice")
    return classify.shared_id_counts(rows, ["l_orderkey", "l_partkey", "l_suppkey"]).select(F.col("case").alias("common"), "pairs")


@R.add()
def lineitem_shared_ids_all(spark, sf_dir):
    """Every row of the table. Without SQL: the tests compare with brute force."""
    return _shared_ids(table(spark, sf_dir, "lineitem"))


def _pairs(spark, case, n=N):
    panels = small_mesh(spark, n)
    if case:
        return panels, classify.touching(panels).where(F.col("case") == case)
    every = assembly.all_pairs(panels, 10**6)
    return panels, classify.classes(every, panels).where("case = 0")


def _entry_query(name, kernel, case, quad=BASIC):
    pairs = "SELECT i, j, cls FROM near WHERE cls = %d" % case if case else "SELECT a.pid AS i, b.pid AS j, 0 AS cls FROM p a, p b WHERE NOT EXISTS (SELECT 1 FROM near q WHERE q.i = a.pid AND q.j = b.pid)"
    sql = f"WITH {O.panels(N)}, {O.touching()}, {O.rules(quad.regular, quad.singular, (case,))}, pairs AS ({pairs}), {O.entries('pairs', kernel.layer, kernel.kappa)} SELECT i, j, {O.scaled('re', 9, 're')}, {O.scaled('im', 9, 'im')} FROM e"

    def run(spark, sf_dir):
        panels, rows = _pairs(spark, case)
        return assembly.entries(rows, panels, kernel, quad).select("i", "j", scaled(F.col("re"), 9, "re"), scaled(F.col("im"), 9, "im"))

    R.add(sql, name)(run)


def _charged_query(name, kernel, case):
    """Entries times the mean price of the parts on the panel of their column."""
    pairs = "SELECT i, j, cls FROM near WHERE cls = %d" % case if case else "SELECT a.pid AS i, b.pid AS j, 0 AS cls FROM p a, p b WHERE NOT EXISTS (SELECT 1 FROM near q WHERE q.i = a.pid AND q.j = b.pid)"
    sql = f"WITH {O.panels(N)}, {O.touching()}, {O.rules(BASIC.regular, BASIC.singular, (case,))}, {PART_DENSITY}, pairs AS ({pairs}), {O.entries('pairs', kernel.layer, kernel.kappa)} SELECT i, j, {O.scaled('re * density', 6, 're')}, {O.scaled('im * density', 6, 'im')} FROM e JOIN dp ON dp.pid = j"

    def run(spark, sf_dir):
        panels, rows = _pairs(spark, case)
        held = part_density(spark, sf_dir, N).select(F.col("pid").alias("j"), "density")
        return assembly.entries(rows, panels, kernel).join(held, "j").select("i", "j", *[scaled(F.col(c) * F.col("density"), 6, c) for c in ("re", "im")])

    R.add(sql, name)(run)


for _name, _kernel, _case in (("dlp_regular", dlp(), 0), ("dlp_vertex", dlp(), 1), ("dlp_edge", dlp(), 2)):
    _charged_query(_name, _kernel, _case)

for _name, _kernel, _case in (
    ("slp_regular", slp(), 0), ("slp_vertex", slp(), 1), ("slp_edge", slp(), 2), ("slp_identical", slp(), 3),
    ("wave_slp_regular", slp(KAPPA), 0), ("wave_dlp_regular", dlp(KAPPA), 0), ("wave_slp_edge", slp(KAPPA), 2), ("wave_dlp_vertex", dlp(KAPPA), 1),
):
    _entry_query(_name, _kernel, _case)


ALL = "SELECT a.pid AS i, b.pid AS j, coalesce(q.cls, 0) AS cls FROM p a CROSS JOIN p b LEFT JOIN near q ON q.i = a.pid AND q.j = b.pid"


def matrix_sql(kernel, n=N, quad=BASIC, tail=""):
    return f"WITH {O.panels(n)}, {O.touching()}, {O.rules(quad.regular, quad.singular)}, pairs AS ({ALL}), {O.entries('pairs', kernel.layer, kernel.kappa)} {tail}"


ROW_SUM = f"SELECT i, {O.scaled('sum(re)', 8, 'total')} FROM e GROUP BY i"


def _sums(values):
    return assembly.row_sums(values).select("i", scaled(F.col("re"), 8, "total"))


@R.add(matrix_sql(slp(), tail=ROW_SUM))
def slp_one_pass(spark, sf_dir):
    return _sums(assembly.one_pass(small_mesh(spark), slp()))


@R.add(matrix_sql(slp(), tail=ROW_SUM))
def slp_two_phase(spark, sf_dir):
    return _sums(assembly.two_phase(small_mesh(spark), slp()))


@R.add(matrix_sql(slp(), tail=ROW_SUM))
def slp_dense_rowsum(spark, sf_dir):
    return _sums(assembly.dense(small_mesh(spark), slp()))


@R.add(matrix_sql(dlp(), tail=f", {PART_DENSITY} SELECT i, {O.scaled('sum(re * density)', 5, 'total')} FROM e JOIN dp ON dp.pid = j GROUP BY i"))
def dlp_dense_rowsum(spark, sf_dir):
    """Row sums with the mean price of the parts of each column's panel."""
    sums = assembly.row_sums(assembly.dense(small_mesh(spark), dlp()), part_density(spark, sf_dir, N))
    return sums.select("i", scaled(F.col("re"), 5, "total"))


@R.add(matrix_sql(slp(), tail=ROW_SUM))
def slp_direct(spark, sf_dir):
    from ..config import EngineConfig
    from ..session import Session

    s = Session(spark, EngineConfig(leaf_size=8))
    s.mesh(N)
    return _sums(s.assemble(slp(), "direct"))


@R.add(matrix_sql(slp(), tail=ROW_SUM))
def slp_packages_mixed(spark, sf_dir):
    """The Arrow path without grouping by class: batches of mixed cases, the same values."""
    panels = small_mesh(spark)
    return _sums(assembly.package_entries(classify.classes(assembly.all_pairs(panels, 10**6), panels), panels, slp(), by_case=False))


@R.add(matrix_sql(slp(), tail=f"SELECT i, j, {O.scaled('re', 9, 're')} FROM e WHERE i >= j UNION ALL SELECT j, i, {O.scaled('re', 9, 're')} FROM e WHERE i > j"))
def slp_symmetric(spark, sf_dir):
    """The lower half only, mirrored at use. The other half differs by quadrature errors only."""
    panels = small_mesh(spark)
    half = assembly.symmetric_half(assembly.all_pairs(panels, 10**6))
    return assembly.mirrored(assembly.one_pass(panels, slp(), pairs=half)).select("i", "j", scaled(F.col("re"), 9, "re"))


@R.add(matrix_sql(dlp(), tail=f", {PART_DENSITY} SELECT {O.scaled('max(abs(k / area + 0.5))', 7, 'worst')}, {O.scaled('sum(parts * abs(k / area + 0.5)) / sum(parts)', 7, 'mean')}, count(*) AS panels FROM (SELECT i, sum(re) AS k FROM e GROUP BY i) JOIN p ON pid = i JOIN dp USING (pid)"))
def dlp_rowsum_identity(spark, sf_dir):
    """The largest deviation of the panels that hold parts, and the mean over the parts."""
    panels = small_mesh(spark)
    held = panels.join(part_density(spark, sf_dir, N), "pid").select(F.col("pid").alias("i"), "area", "parts")
    rows = assembly.row_sums(assembly.one_pass(panels, dlp(), skip_coplanar=True)).join(held, "i")
    off = F.abs(F.col("re") / F.col("area") + 0.5)
    return rows.agg(scaled(F.max(off), 7, "worst"), scaled(F.sum(F.col("parts") * off) / F.sum("parts"), 7, "mean"), F.count("*").alias("panels"))


@R.add(matrix_sql(slp(), tail=f", f AS (SELECT i, j, cls, re FROM e), pr AS (SELECT i, j, 0 AS cls FROM f), {O.entries('pr', 'slp', 0.0, 'w')} SELECT f.cls AS common, count(*) AS pairs, count(w.re) AS finite, {O.scaled('coalesce(sqrt(sum((f.re - w.re) * (f.re - w.re)) / sum(CASE WHEN w.re IS NULL THEN NULL ELSE f.re * f.re END)), 0.0)', 7, 'error')} FROM f JOIN w USING (i, j) GROUP BY f.cls"))
def regular_only_error(spark, sf_dir):
    panels = small_mesh(spark)
    good = classify.classes(assembly.all_pairs(panels, 10**6), panels)
    a = assembly.entries(good, panels, slp()).join(good, ["i", "j"])
    b = assembly.regular_only(panels, slp()).select("i", "j", F.col("re").alias("w"))
    rows = a.join(b, ["i", "j"])
    error = F.sqrt(F.sum((F.col("re") - F.col("w")) ** 2) / F.sum(F.when(F.col("w").isNotNull(), F.col("re") ** 2)))
    return rows.groupBy(F.col("case").alias("common")).agg(F.count("*").alias("pairs"), F.count("w").alias("finite"), scaled(F.coalesce(error, F.lit(0.0)), 7, "error"))


@R.add("WITH " + ", ".join(f"q{k} AS ({matrix_sql(slp(), 3, q, f'SELECT cls AS common, sum(re) AS total FROM e GROUP BY cls')})" for k, q in enumerate((BASIC, HIGHER))) + f" SELECT common, {O.scaled('q0.total', 8, 'basic')}, {O.scaled('q1.total', 8, 'higher')} FROM q0 JOIN q1 USING (common)")
def quad_order_compare(spark, sf_dir):
    panels = small_mesh(spark, 3)
    pairs = classify.classes(assembly.all_pairs(panels, 10**6), panels)
    a, b = (assembly.package_entries(pairs, panels, slp(), q).join(pairs, ["i", "j"]).groupBy(F.col("case").alias("common")).agg(F.sum("re").alias(n)) for q, n in ((BASIC, "basic"), (HIGHER, "higher")))
    return a.join(b, "common").select("common", scaled(F.col("basic"), 8, "basic"), scaled(F.col("higher"), 8, "higher"))


@R.add(f"WITH {O.panels(O.PART_N)}, c AS (" + " UNION ALL ".join(f"SELECT v{a} AS vi, v{b} AS vj, area / {6.0 if a == b else 12.0} AS m FROM p" for a in range(3) for b in range(3)) + f") SELECT vi, vj, {O.scaled('sum(m)', 10, 'mass')} FROM c GROUP BY vi, vj")
def p1_mass(spark, sf_dir):
    return assembly.p1_mass(part_mesh(spark, sf_dir)).select("vi", "vj", scaled(F.col("mass"), 10, "mass"))


_HAT = {"a": ("1 - s", "s - t", "t"), "b": ("1 - u", "u - v", "v")}
P1_SQL = f"""WITH {O.panels(2)}, {O.touching()}, {O.rules(3, 5, (0,))}, pairs AS (SELECT a.pid AS i, b.pid AS j, 0 AS cls FROM p a, p b WHERE NOT EXISTS (SELECT 1 FROM near q WHERE q.i = a.pid AND q.j = b.pid)),
f AS (SELECT a.v0 AS a0, a.v1 AS a1, a.v2 AS a2, b.v0 AS b0, b.v1 AS b1, b.v2 AS b2, s, t, u, v, w * a.gram * b.gram / ({O.FOUR_PI} * sqrt({' + '.join(f'pow(a.a{x} + s * (a.k{x} - a.a{x}) + t * (a.c{x} - a.k{x}) - b.a{x} - u * (b.k{x} - b.a{x}) - v * (b.c{x} - b.k{x}), 2)' for x in 'xyz')})) AS g FROM pairs JOIN p a ON a.pid = i JOIN p b ON b.pid = j CROSS JOIN rules),
l AS ({' UNION ALL '.join(f'SELECT a{k} AS vi, b{m} AS vj, g * ({_HAT["a"][k]}) * ({_HAT["b"][m]}) AS re FROM f' for k in range(3) for m in range(3))})
SELECT vi, vj, {O.scaled('sum(re)', 9, 're')} FROM l GROUP BY vi, vj"""


@R.add(P1_SQL)
def p1_slp_local(spark, sf_dir):
    panels, pairs = _pairs(spark, 0, 2)
    return assembly.p1_scatter(pairs, panels, slp()).select("vi", "vj", scaled(F.col("re"), 9, "re"))


@R.add(f"WITH {O.panels(O.PART_N)}, {PART_DENSITY} SELECT pid AS i, {O.scaled('area', 10, 'mass')}, {O.scaled('area * coalesce(density, 0)', 6, 'load')} FROM p LEFT JOIN dp USING (pid)")
def mass_matrix(spark, sf_dir):
    """The mass of each panel, and its product with the mean price of the panel's parts."""
    panels = on_parts(spark, sf_dir)
    rows = assembly.mass_matrix(panels).join(panels.select(F.col("pid").alias("i"), "density"), "i")
    return rows.select("i", scaled(F.col("mass"), 10, "mass"), scaled(F.col("mass") * F.col("density"), 6, "load"))


def _density(table_name, key, value):
    return f"d AS (SELECT row_number() OVER (ORDER BY {key}, {value}) - 1 AS pid, CAST({value} AS DOUBLE) AS density FROM {table_name})"


def folded_density(table_name, key, value, n=N):
    return f"d AS (SELECT k % {8 * n * n} AS pid, sum(density) AS density FROM (SELECT row_number() OVER (ORDER BY {key}, {value}) - 1 AS k, CAST({value} AS DOUBLE) AS density FROM {table_name}) GROUP BY 1)"


def _potential(name, table_name, key, value):
    """`name` has one row on each panel, as its SQL, `name`_all every row of the table."""
    for query, density, carried, digits in ((name, _density, geometry.carried_panels, 5), (f"{name}_all", folded_density, geometry.folded_panels, 4)):
        sql = matrix_sql(slp(), tail=f", {density(table_name, key, value)} SELECT i, {O.scaled('sum(re * density)', digits, 'potential')} FROM e JOIN d ON d.pid = j GROUP BY i")

        def run(spark, sf_dir, carried=carried, digits=digits):
            panels = carried(spark, table(spark, sf_dir, table_name), key, value, N)
            return assembly.row_sums(assembly.one_pass(panels, slp()), panels).select("i", scaled(F.col("re"), digits, "potential"))

        R.add(sql, query)(run)


_potential("potential_of_price", "part", "p_partkey", "p_retailprice")
_potential("potential_of_balance", "customer", "c_custkey", "c_acctbal")


@R.add(matrix_sql(slp(), tail=f", d AS (SELECT user_id % 128 AS pid, sum(value) AS density FROM events GROUP BY 1) SELECT i, {O.scaled('sum(re * density)', 4, 'potential')} FROM e JOIN d ON d.pid = j GROUP BY i"))
def potential_of_events(spark, sf_dir):
    panels = small_mesh(spark)
    density = table(spark, sf_dir, "events").groupBy(F.pmod("user_id", F.lit(128)).alias("pid")).agg(F.sum("value").alias("density"))
    return assembly.row_sums(assembly.one_pass(panels, slp()), density).select("i", scaled(F.col("re"), 4, "potential"))


@R.add(f"""WITH q AS (SELECT vec_id AS i, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y, CAST(embedding[3] AS DOUBLE) AS z, 1.0 + label AS c FROM embeddings WHERE vec_id < 300),
u AS (SELECT i, x / sqrt(x*x+y*y+z*z) AS x, y / sqrt(x*x+y*y+z*z) AS y, z / sqrt(x*x+y*y+z*z) AS z, c FROM q WHERE x*x+y*y+z*z > 0)
SELECT a.i, {O.scaled(f'sum(b.c / ({O.FOUR_PI} * sqrt((a.x-b.x)*(a.x-b.x) + (a.y-b.y)*(a.y-b.y) + (a.z-b.z)*(a.z-b.z))))', 6, 'potential')} FROM u a JOIN u b ON a.i <> b.i GROUP BY a.i""")
def point_potential(spark, sf_dir):
    """Direct sum over the point charges of its SQL (the dense form that compression replaces)."""
    return _charges(table(spark, sf_dir, "embeddings").where("vec_id < 300"))


@R.add(f"""WITH q AS (SELECT vec_id AS i, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y, CAST(embedding[3] AS DOUBLE) AS z, 1.0 + label AS c FROM embeddings),
u AS (SELECT i, x / sqrt(x*x+y*y+z*z) AS x, y / sqrt(x*x+y*y+z*z) AS y, z / sqrt(x*x+y*y+z*z) AS z, c FROM q WHERE x*x+y*y+z*z > 0)
SELECT a.i, {O.scaled(f'sum(b.c / ({O.FOUR_PI} * sqrt((a.x-b.x)*(a.x-b.x) + (a.y-b.y)*(a.y-b.y) + (a.z-b.z)*(a.z-b.z))))', 6, 'potential')} FROM u a JOIN u b ON a.i <> b.i GROUP BY a.i""")
def point_potential_all(spark, sf_dir):
    """All points; the square of their number by nature."""
    return _charges(table(spark, sf_dir, "embeddings"))


def _charges(e):
    """Direct sums over point charges. Each term is split into a multiple of 2^-20 and a rest: the multiples add up without
    rounding below 2^33 and the rests are small, so the sum of many terms has no error of its order."""
    c = [F.get("embedding", j).cast("double") for j in range(3)]
    pts = e.select(F.col("vec_id").alias("i"), *[x.alias(a) for x, a in zip(c, "xyz", strict=True)], (F.lit(1.0) + F.col("label")).alias("c"))
    r2 = F.col("x") * F.col("x") + F.col("y") * F.col("y") + F.col("z") * F.col("z")
    pts = pts.withColumn("r", F.sqrt(r2)).where("r > 0").select("i", *[(F.col(a) / F.col("r")).alias(a) for a in "xyz"], "c")
    b = pts.select(F.col("i").alias("j"), *[F.col(a).alias(f"{a}2") for a in "xyz"], "c")
    d = [F.col(a) - F.col(f"{a}2") for a in "xyz"]
    rows = pts.drop("c").crossJoin(F.broadcast(b)).where("i <> j")
    rows = rows.select("i", (F.col("c") / (4 * 3.141592653589793 * F.sqrt(d[0] * d[0] + d[1] * d[1] + d[2] * d[2]))).alias("t"))
    rows = rows.withColumn("whole", F.rint(F.col("t") * 2.0**20) / 2.0**20)
    return rows.groupBy("i").agg(scaled(F.sum("whole") + F.sum(F.col("t") - F.col("whole")), 6, "potential"))
