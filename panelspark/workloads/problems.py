"""Boundary values, right-hand sides, solvers and potentials."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import oracles as O
from ..operators import assembly, fields, geometry, measures, solve
from ..operators.kernels import dlp, slp
from ..plans.scratch import settled
from .mesh import PART_DENSITY, folded_density, matrix_sql, on_parts, part_density, part_mesh, small_mesh
from .registry import Registry, scaled, table

R = Registry()
KAPPA = 3.0


def _source_sql(s, at=("gx", "gy", "gz")):
    return " + ".join(f"({a} - {v}) * ({a} - {v})" for a, v in zip(at, s, strict=True))


FIELD_SQL = {"f1": "gx * gx - gz * gz", "f2": f"1.0 / ({O.FOUR_PI} * sqrt({_source_sql(fields.SOURCE2)}))", "f3": f"1.0 / ({O.FOUR_PI} * sqrt({_source_sql(fields.SOURCE3)}))"}


def _normal_sql(s):
    d = _source_sql(s)
    turn = " + ".join(f"(g{a} - {v}) * n{a}" for a, v in zip("xyz", s, strict=True))
    return f"-({turn}) / ({O.FOUR_PI} * ({d}) * sqrt({d}))"


NORMAL_SQL = {"f1": "2 * gx * nx - 2 * gz * nz", "f2": _normal_sql(fields.SOURCE2), "f3": _normal_sql(fields.SOURCE3)}


@R.add(f"WITH {O.panels(O.PART_N)}, {PART_DENSITY} SELECT pid AS i, {', '.join(O.scaled(f'({e}) * coalesce(density, 0)', 6, n) for n, e in FIELD_SQL.items())} FROM p LEFT JOIN dp USING (pid)")
def boundary_values(spark, sf_dir):
    """The fields with the mean price of the parts of each panel as their strength."""
    g = [F.col(c) for c in ("gx", "gy", "gz")]
    return on_parts(spark, sf_dir).select(F.col("pid").alias("i"), *[scaled(f(*g) * F.col("density"), 6, n) for n, f in fields.FIELDS.items()])


@R.add(f"WITH {O.panels(O.PART_N)} SELECT pid AS i, {', '.join(O.scaled(e, 9, n) for n, e in NORMAL_SQL.items())} FROM p")
def neumann_exact(spark, sf_dir):
    g = [F.col(c) for c in ("gx", "gy", "gz", "nx", "ny", "nz")]
    return part_mesh(spark, sf_dir).select(F.col("pid").alias("i"), *[scaled(fields.normal_derivative(n, *g), 9, n) for n in fields.FIELDS])


@R.add(matrix_sql(dlp(), 3, tail=f", {PART_DENSITY}, b AS (SELECT pid, area, (gx * gx - gz * gz) * coalesce(density, 0) AS beta FROM p LEFT JOIN dp USING (pid)), k AS (SELECT i, sum(re * beta) AS k FROM e JOIN b ON pid = j GROUP BY i) SELECT i, {O.scaled('area * beta / 2 + k', 5, 'rhs')} FROM k JOIN b ON pid = i"))
def dirichlet_rhs(spark, sf_dir):
    panels = small_mesh(spark, 3)
    k = solve.entry_apply(assembly.dense(panels, dlp()))
    strength = part_density(spark, sf_dir, 3).select(F.col("pid").alias("i"), "density")
    beta = fields.project(panels, fields.f1).join(strength, "i", "left").select("i", (F.col("value") * F.coalesce("density", F.lit(0.0))).alias("value"))
    out = solve.dirichlet_rhs(k, assembly.mass_matrix(panels), beta)
    return out.select("i", scaled(F.col("value"), 5, "rhs"))


def solved(spark, field, n=3):
    panels = settled(small_mesh(spark, n))
    v, k = (solve.entry_apply(settled(assembly.dense(panels, x))) for x in (slp(), dlp()))
    alpha, report = solve.dirichlet(v, k, assembly.mass_matrix(panels), fields.project(panels, fields.FIELDS[field]))
    g = [F.col(c) for c in ("gx", "gy", "gz", "nx", "ny", "nz")]
    exact = panels.select(F.col("pid").alias("i"), fields.normal_derivative(field, *g).alias("value"))
    return alpha, report, measures.neumann_error(alpha, exact, panels)


def _dirichlet(field):
    def run(spark, sf_dir):
        alpha, report, error = solved(spark, field)
        return error.select("error", F.lit(report.steps).alias("steps"), F.lit(report.residuals[-1]).alias("residual"))

    R.add(None, f"dirichlet_{field}")(run)


for _f in fields.FIELDS:
    _dirichlet(_f)


@R.add()
def neumann_error(spark, sf_dir):
    """Errors of f1 on two levels and the observed order."""
    rows = [("f1", n, solved(spark, "f1", n)[2].first()[0]) for n in (2, 3)]
    return measures.convergence_order(spark.createDataFrame(rows, "workload string, n int, error double"))


@R.add()
def cg_steps(spark, sf_dir):
    """Steps and extreme eigenvalues with and without the diagonal preconditioner."""
    panels = settled(small_mesh(spark, 2))
    v = settled(assembly.dense(panels, slp()))
    b = fields.project(panels, fields.f2)
    diag = v.where("i = j").select("i", F.col("re").alias("d"))
    rows = []
    for name, pre in (("none", None), ("diagonal", diag)):
        _, r = solve.cg(solve.entry_apply(v), b, precond=pre)
        rows.append((name, r.steps, r.residuals[-1], *r.eigenvalues()))
    return spark.createDataFrame(rows, "precond string, steps int, residual double, lowest double, highest double")


@R.add()
def wave_exterior(spark, sf_dir):
    """Exterior wave field from a combined-layer density against the known source, at targets made from suppliers."""
    panels = settled(small_mesh(spark, 2))
    v, k = (settled(assembly.dense(panels, x)) for x in (slp(KAPPA), dlp(KAPPA)))
    re, im = fields.f_wave(F.col("gx"), F.col("gy"), F.col("gz"), KAPPA)
    rhs = panels.select(F.col("pid").alias("i"), (re * F.col("area")).alias("re"), (im * F.col("area")).alias("im"))
    w, report = solve.wave_exterior(v, k, assembly.mass_matrix(panels), rhs, tol=1e-6)
    w = settled(w)
    t = settled(fields.targets_from(table(spark, sf_dir, "supplier"), "s_suppkey", "s_acctbal"))
    u = fields.combined_field(t, panels, w, KAPPA)
    er, ei = fields.f_wave(F.col("x"), F.col("y"), F.col("z"), KAPPA)
    return measures.exterior_error(u, t.select("tid", er.alias("e_re"), ei.alias("e_im"))).withColumn("steps", F.lit(report.steps))


TARGETS = "tg AS (SELECT s_suppkey AS tid, a / r * f AS x, b / r * f AS y, c / r * f AS z FROM (SELECT *, sqrt(a*a+b*b+c*c) AS r FROM (SELECT s_suppkey, ((s_suppkey * 3) % 15) - 7 + 0.5 AS a, ((s_suppkey * 5) % 15) - 7 + 0.5 AS b, ((s_suppkey * 11) % 15) - 7 + 0.5 AS c, 2.0 + ((CAST(floor(s_acctbal) AS BIGINT) % 1000 + 1000) % 1000) / 1000.0 AS f FROM (SELECT s_suppkey, s_acctbal FROM supplier))))"


@R.add(f"""WITH {O.panels(4)}, {TARGETS}, {O.line(3, 'gl')}, tr AS (SELECT a.x AS s, a.x * b.x AS t, a.w * b.w * a.x AS w FROM gl a, gl b),
d AS (SELECT row_number() OVER (ORDER BY p_partkey, p_retailprice) - 1 AS pid, p_retailprice AS density FROM part),
y AS (SELECT ax + s * (kx - ax) + t * (cx - kx) AS yx, ay + s * (ky - ay) + t * (cy - ky) AS yy, az + s * (kz - az) + t * (cz - kz) AS yz, w * gram * density AS w FROM p JOIN d USING (pid), tr)
SELECT tid, {O.scaled(f'sum(w / ({O.FOUR_PI} * sqrt(pow(x - yx, 2) + pow(y - yy, 2) + pow(z - yz, 2))))', 4, 'potential')} FROM tg, y GROUP BY tid""")
def representation_eval(spark, sf_dir):
    """One part on each panel, as its SQL; representation_eval_all has every part."""
    return _representation(spark, sf_dir, geometry.carried_panels)


@R.add(f"""WITH {O.panels(4)}, {TARGETS}, {O.line(3, 'gl')}, tr AS (SELECT a.x AS s, a.x * b.x AS t, a.w * b.w * a.x AS w FROM gl a, gl b),
{folded_density("part", "p_partkey", "p_retailprice")},
y AS (SELECT ax + s * (kx - ax) + t * (cx - kx) AS yx, ay + s * (ky - ay) + t * (cy - ky) AS yy, az + s * (kz - az) + t * (cz - kz) AS yz, w * gram * density AS w FROM p JOIN d USING (pid), tr)
SELECT tid, {O.scaled(f'sum(w / ({O.FOUR_PI} * sqrt(pow(x - yx, 2) + pow(y - yy, 2) + pow(z - yz, 2))))', 4, 'potential')} FROM tg, y GROUP BY tid""")
def representation_eval_all(spark, sf_dir):
    return _representation(spark, sf_dir, geometry.folded_panels)


def _representation(spark, sf_dir, carried):
    panels = carried(spark, table(spark, sf_dir, "part"), "p_partkey", "p_retailprice", 4)
    t = fields.targets_from(table(spark, sf_dir, "supplier"), "s_suppkey", "s_acctbal")
    density = panels.select(F.col("pid").alias("i"), F.col("density").alias("re"), F.lit(0.0).alias("im"))
    return fields.evaluate(t, panels.drop("density"), density, slp()).select("tid", scaled(F.col("re"), 4, "potential"))
