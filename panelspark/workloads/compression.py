"""Compressed matrices of panels, packages of integrated entries, and the problems solved with them."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import oracles as O
from ..config import BASIC, EngineConfig
from ..operators import assembly, classify, clustering, fields, fill, geometry, h2, measures, schedule, solve
from ..operators.kernels import dlp, slp
from ..plans.scratch import settled
from ..session import Session
from .mesh import PART_HISTOGRAM, ROW_SUM, matrix_sql, on_parts, small_mesh
from .registry import Registry, scaled, table

R = Registry()
KAPPA = 3.0
N = "(SELECT floor(sqrt(count(*) / 8.0)) FROM customer)"
SHARP = EngineConfig(leaf_size=16, green_q=6, aca_eps=1e-10)

DENSITY = "d AS (SELECT k % (SELECT 8 * n * n FROM n0) AS pid, sum(density) AS density FROM (SELECT row_number() OVER (ORDER BY c_custkey, c_acctbal) - 1 AS k, CAST(c_acctbal AS DOUBLE) AS density FROM customer) GROUP BY 1)"
FULL = "SELECT a.pid AS i, b.pid AS j, coalesce(q.cls, 0) AS cls FROM p a CROSS JOIN p b LEFT JOIN near q ON q.i = a.pid AND q.j = b.pid"
LOWER = "SELECT a.pid AS i, b.pid AS j, coalesce(q.cls, 0) AS cls FROM p a JOIN p b ON a.pid >= b.pid LEFT JOIN near q ON q.i = a.pid AND q.j = b.pid"


def _product_sql(kernel, lower: bool) -> str:
    """The dense product with the customers' balances, as a potential per area. lower: the other half is mirrored."""
    every = "e" if not lower else "(SELECT i, j, re, im FROM e UNION ALL SELECT j, i, re, im FROM e WHERE i > j)"
    parts = ", ".join(O.scaled(f"sum({x} * density) / any_value(area)", 3, x) for x in ("re", "im"))
    return f"WITH {O.panels(N)}, {O.touching()}, {O.rules(3, 5)}, pairs AS ({LOWER if lower else FULL}), {O.entries('pairs', kernel.layer, kernel.kappa)}, {DENSITY} SELECT q.i, {parts} FROM {every} q JOIN d ON d.pid = q.j JOIN p ON p.pid = q.i GROUP BY q.i"


def _carried(spark, sf_dir):
    rows = table(spark, sf_dir, "customer")
    return geometry.folded_panels(spark, rows, "c_custkey", "c_acctbal", geometry.refinement(rows.count()))


def _compressed_product(name, kernel):
    def run(spark, sf_dir):
        s = Session(spark, SHARP)
        s.panels = settled(_carried(spark, sf_dir))
        x = s.panels.select(F.col("pid").alias("i"), F.col("density").alias("re"), F.lit(0.0).alias("im"))
        half = kernel.layer == "slp"
        s.tree(half)
        made = h2.product(s.membership, s.clusters, s.blocks, h2.geometry_rows(s.panels), kernel, s.cfg, x, half)
        y = made.join(s.panels.select(F.col("pid").alias("i"), "area"), "i")
        return y.select("i", scaled(F.col("re") / F.col("area"), 3, "re"), scaled(F.col("im") / F.col("area"), 3, "im"))

    R.add(_product_sql(kernel, kernel.layer == "slp"), name)(run)


_compressed_product("h2_slp_panels", slp())
_compressed_product("h2_dlp_panels", dlp())
_compressed_product("h2_wave_slp_panels", slp(KAPPA))
_compressed_product("h2_wave_dlp_panels", dlp(KAPPA))


def _forms(spark):
    s = Session(spark, EngineConfig(leaf_size=16, green_q=5, aca_eps=1e-7, symmetric=False))
    s.mesh(6)
    s.panels = settled(s.panels)
    s.tree()
    member = settled(clustering.ancestors(s.membership).select("node", "i").join(h2.geometry_rows(s.panels), "i"))
    return s, member, s.blocks.where("kind = 'far'")


@R.add("SELECT * FROM (VALUES ('aca', true), ('one_sided', true), ('two_sided', true), ('unpivoted', true)) AS t(form, within)")
def compression_forms(spark, sf_dir):
    """The largest relative error of a far block stays below the tolerance of each form (288 panels): 1e-4, and 1e-2 for the
    un-pivoted one, whose error is that of the quadrature of the separation, without algebraic correction."""
    s, member, far = _forms(spark)
    all_members = fill.members(member)
    exact = settled(fill.fill(far, all_members, all_members, slp(), s.cfg, "one"))
    errors = h2.aca_blocks(far, member, slp(), s.cfg, check=True).select(F.lit("aca").alias("form"), "error")
    row, col = (h2.flat_basis(s.membership, s.clusters, h2.geometry_rows(s.panels), slp(), s.cfg, side, s.blocks) for side in ("row", "col"))
    row, col = settled(row), settled(col)
    for name, made in (("one_sided", h2.one_sided(far, row, member, slp(), s.cfg)), ("two_sided", h2.two_sided(far, row, col, slp(), s.cfg)), ("unpivoted", h2.unpivoted(far, s.clusters, member, slp(), s.cfg))):
        errors = errors.unionByName(measures.block_error(exact, made, ["t", "s"]).select(F.lit(name).alias("form"), "error"))
    return errors.groupBy("form").agg((F.max("error") < F.when(F.col("form") == "unpivoted", 1e-2).otherwise(1e-4)).alias("within"))


@R.add("SELECT true AS nested_below_flat, true AS ranks_below_unpivoted, true AS compressed_below_dense")
def compression_storage(spark, sf_dir):
    """Which form stores least: transfer matrices against flat bases, ranks against the 2 m columns of the un-pivoted form,
    and a larger mesh (4608 panels) against the dense matrix."""
    s = Session(spark, EngineConfig(leaf_size=32, green_q=4, aca_eps=1e-3))
    s.mesh(24)
    s.panels = settled(s.panels)
    nested = s.compress(slp())
    used = {r["part"]: r["bytes"] for r in h2.storage(nested).collect()}
    flat = h2.flat_basis(s.membership, s.clusters, h2.geometry_rows(s.panels), slp(), s.cfg, "row", s.blocks).agg(F.sum(F.size("coef") * 8)).first()[0]
    far = s.blocks.where("kind = 'far'")
    used_by = nested.row_basis.join(far.select(F.col("t").alias("node")).union(far.select("s")).distinct(), "node", "left_semi")
    share = measures.rank_stats(used_by, 6 * s.cfg.green_q**2).agg(F.max("share")).first()[0]
    dense = measures.dense_bytes(s.panels.count()) / 2
    return spark.createDataFrame([(used["leaf basis"] + used["transfer"] < flat, share < 1, sum(used.values()) < dense)], "nested_below_flat boolean, ranks_below_unpivoted boolean, compressed_below_dense boolean")


# ---- packages of integrated entries


def _leaves(spark, n=4, leaf=8):
    """All entries of a small mesh as blocks of its leaf clusters."""
    s = Session(spark, EngineConfig(leaf_size=leaf, symmetric=False))
    s.mesh(n)
    s.panels = settled(s.panels)
    s.tree()
    every = s.clusters.where("is_leaf").select("node")
    return s, fill.members(s.membership.select("node", "i").join(h2.geometry_rows(s.panels), "i")), every.select(F.col("node").alias("t")).crossJoin(F.broadcast(every.select(F.col("node").alias("s"))))


def _sums(values):
    return assembly.row_sums(values).select("i", scaled(F.col("re"), 8, "total"))


def _listed(name, rule, phases, limit):
    def run(spark, sf_dir):
        from dataclasses import replace

        s, member, every = _leaves(spark)
        return _sums(fill.fill(every, member, member, slp(), replace(s.cfg, limit_bytes=limit), phases, rule))

    R.add(matrix_sql(slp(), tail=ROW_SUM), name)(run)


_listed("slp_lists_prefix", "prefix", "two", 1 << 14)
_listed("slp_lists_greedy", "greedy", "two", 1 << 14)
_listed("slp_lists_one_pass", "prefix", "one", 1 << 16)
_listed("slp_lists_unbatched", "prefix", "two", 32)

SWEEP = (1 << 10, 1 << 13, 1 << 16)


@R.add(matrix_sql(slp(), tail=f"SELECT CAST(l AS BIGINT) AS \"limit\", true AS bounded, true AS fewer, {O.scaled('total', 6, 'total')} FROM (SELECT sum(re) AS total FROM e), (VALUES {', '.join(f'({x})' for x in SWEEP)}) AS q(l)"))
def slp_list_sweep(spark, sf_dir):
    """Lists of integrated entries by size limit: the sum of all entries, whether lists stay below the limit plus one block, and
    whether their number falls as the limit grows."""
    from dataclasses import replace

    s, member, every = _leaves(spark)
    rows, before = [], None
    for x in SWEEP:
        got = fill.fill(every, member, member, slp(), replace(s.cfg, limit_bytes=x)).groupBy("list").agg(F.count("*").alias("n"), F.sum("re").alias("re"))
        count, most, total = got.agg(F.count("*"), F.max("n"), F.sum("re")).first()
        rows.append((x, most * fill.VALUE_BYTES < 2 * x, before is None or count < before, round(total * 1e6)))
        before = count
    return spark.createDataFrame(rows, "limit long, bounded boolean, fewer boolean, total long")


@R.add(matrix_sql(slp(), tail=ROW_SUM))
def slp_dispatch(spark, sf_dir):
    """Pairs with an affinity for the accelerator run as Arrow packages, the others as generated code; one matrix."""
    panels = settled(small_mesh(spark))
    pairs = classify.classes(assembly.all_pairs(panels, 10**6), panels)
    return _sums(schedule.dispatch(pairs, F.col("case") > 0, lambda df: assembly.package_entries(df.drop("route"), panels, slp()), lambda df: assembly.entries(df.drop("route"), panels, slp())))


@R.add(matrix_sql(slp(), tail=ROW_SUM))
def slp_hybrid(spark, sf_dir):
    """About a share of 0.6 of the rows of pairs on the accelerator, the rest beside it on the host."""
    panels = settled(small_mesh(spark))
    pairs = schedule.hybrid_split(classify.classes(assembly.all_pairs(panels, 10**6), panels), 0.6, "i")
    fast, host = (pairs.where(F.col("route") == r).drop("route") for r in ("accelerator", "host"))
    return _sums(assembly.package_entries(fast, panels, slp()).unionByName(assembly.entries(host, panels, slp())))


@R.add(f"WITH {O.panels(O.PART_N)}, {PART_HISTOGRAM}, c AS (SELECT cls, pairs, CASE cls WHEN 0 THEN 81 WHEN 1 THEN 1250 WHEN 2 THEN 3125 ELSE 3750 END AS pts FROM h), s AS (SELECT CAST(sum(CASE WHEN cls < 3 THEN pairs * pts / 2 ELSE pairs * pts END) AS BIGINT) AS v_evaluations, CAST(sum(CASE WHEN cls < 3 THEN pairs * pts ELSE 0 END) AS BIGINT) AS k_evaluations FROM c) SELECT *, {O.scaled('k_evaluations / CAST(v_evaluations AS DOUBLE)', 6, 'ratio')} FROM s")
def kv_ratio(spark, sf_dir):
    out = measures.kv_ratio(classify.class_histogram(on_parts(spark, sf_dir), "parts"), BASIC)
    return out.select("v_evaluations", "k_evaluations", scaled(F.col("ratio"), 6, "ratio"))


# ---- problems


def _dense_problem(panels, field, precond=False, **options):
    v, k = (settled(assembly.dense(panels, x)) for x in (slp(), dlp()))
    diag = v.where("i = j").select("i", F.col("re").alias("d")) if precond else None
    beta = fields.project(panels, fields.FIELDS[field], "mean")
    alpha, report = solve.dirichlet(solve.entry_apply(v), solve.entry_apply(k), assembly.mass_matrix(panels), beta, precond=diag, **options)
    g = [F.col(c) for c in ("gx", "gy", "gz", "nx", "ny", "nz")]
    exact = panels.select(F.col("pid").alias("i"), fields.normal_derivative(field, *g).alias("value"))
    return report, measures.neumann_error(alpha, exact, panels).first()[0]


@R.add("SELECT 'f1' AS field, 4 AS coarse, 8 AS fine, true AS falls, true AS about_first_order")
def dirichlet_order(spark, sf_dir):
    """Errors of the Neumann data on 128 and 512 panels, data by mean values: the order is near one or above."""
    errors = [_dense_problem(settled(small_mesh(spark, n)), "f1", precond=True, tol=1e-6)[1] for n in (4, 8)]
    rows = measures.convergence_order(spark.createDataFrame([("f1", n, e) for n, e in zip((4, 8), errors, strict=True)], "workload string, n int, error double"))
    order = rows.where("n = 8").first()["order"]
    return spark.createDataFrame([("f1", 4, 8, errors[1] < errors[0], 0.8 <= order <= 2.2)], "field string, coarse int, fine int, falls boolean, about_first_order boolean")


@R.add("SELECT count(*) AS targets, true AS below_2_percent FROM supplier")
def wave_exterior_field(spark, sf_dir):
    """The exterior wave field of 512 panels against the known source, at targets made from suppliers."""
    panels = settled(small_mesh(spark, 8))
    v, k = (settled(assembly.dense(panels, x)) for x in (slp(KAPPA), dlp(KAPPA)))
    re, im = fields.f_wave(F.col("gx"), F.col("gy"), F.col("gz"), KAPPA)
    rhs = panels.select(F.col("pid").alias("i"), (re * F.col("area")).alias("re"), (im * F.col("area")).alias("im"))
    w, _ = solve.wave_exterior(v, k, assembly.mass_matrix(panels), rhs, tol=1e-5)
    t = settled(fields.targets_from(table(spark, sf_dir, "supplier"), "s_suppkey", "s_acctbal"))
    u = fields.combined_field(t, panels, settled(w), KAPPA)
    er, ei = fields.f_wave(F.col("x"), F.col("y"), F.col("z"), KAPPA)
    out = measures.exterior_error(u, t.select("tid", er.alias("e_re"), ei.alias("e_im")))
    return out.select("targets", (F.col("max_relative") < 0.02).alias("below_2_percent"))


@R.add("SELECT CAST(count(*) * count(*) AS BIGINT) AS covered, CAST(count(*) * count(*) AS BIGINT) AS entries, true AS some_touch FROM supplier")
def block_touching(spark, sf_dir):
    """Blocks of a mesh sized by the suppliers that a second phase looks at: fewer than all near blocks, and none outside them."""
    n = geometry.refinement(table(spark, sf_dir, "supplier").count())
    s = Session(spark, EngineConfig(leaf_size=4, symmetric=False))
    s.panels = settled(geometry.with_metrics(geometry.sphere_panels(spark, n)))
    s.tree()
    near = s.blocks.where("kind = 'near'")
    touched = fill.touching_blocks(s.blocks.select("t", "s", "kind"), s.membership, s.panels).groupBy("kind").agg(F.count("*").alias("c")).collect()
    count = table(spark, sf_dir, "supplier").agg((F.count("*") * F.count("*")).alias("covered"), (F.count("*") * F.count("*")).alias("entries"))
    return count.select("covered", "entries", F.lit([r["kind"] for r in touched] == ["near"] and 0 < touched[0]["c"] <= near.count()).alias("some_touch"))
