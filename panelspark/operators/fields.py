"""Test fields on the unit sphere, their projections, and potentials off the surface."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .kernels import FOUR_PI, KernelSpec
from .quadrature import triangle_rule

# Where the point sources of the test fields stand.
SOURCE2, SOURCE3, SOURCE_WAVE = (1.2, 1.2, 1.2), (1.0, 0.25, 1.0), (0.0, 0.0, 0.2)


def f1(x: Column, y: Column, z: Column) -> Column:
    return x * x - z * z


def _source(x, y, z, s) -> Column:
    d = [c - v for c, v in zip((x, y, z), s, strict=True)]
    return F.lit(1.0) / (FOUR_PI * F.sqrt(d[0] * d[0] + d[1] * d[1] + d[2] * d[2]))


def f2(x, y, z):
    return _source(x, y, z, SOURCE2)


def f3(x, y, z):
    return _source(x, y, z, SOURCE3)


def f_wave(x, y, z, kappa: float) -> tuple[Column, Column]:
    d = [c - v for c, v in zip((x, y, z), SOURCE_WAVE, strict=True)]
    r = F.sqrt(d[0] * d[0] + d[1] * d[1] + d[2] * d[2])
    return F.cos(kappa * r) / (FOUR_PI * r), F.sin(kappa * r) / (FOUR_PI * r)


FIELDS = {"f1": f1, "f2": f2, "f3": f3}


def normal_derivative(name: str, x, y, z, nx, ny, nz) -> Column:
    if name == "f1":
        return 2 * x * nx - 2 * z * nz
    s = SOURCE2 if name == "f2" else SOURCE3
    d = [c - v for c, v in zip((x, y, z), s, strict=True)]
    r2 = d[0] * d[0] + d[1] * d[1] + d[2] * d[2]
    return -(d[0] * nx + d[1] * ny + d[2] * nz) / (FOUR_PI * r2 * F.sqrt(r2))


def project(panels: DataFrame, field, how: str = "centroid", n: int = 3) -> DataFrame:
    """(i, value): the field at the centroid, or its mean over the panel by quadrature."""
    if how == "centroid":
        return panels.select(F.col("pid").alias("i"), field(F.col("gx"), F.col("gy"), F.col("gz")).alias("value"))
    total = F.lit(0.0)
    for s, t, w in triangle_rule(n):
        p = [F.col(f"a{a}") + float(s) * (F.col(f"b{a}") - F.col(f"a{a}")) + float(t) * (F.col(f"c{a}") - F.col(f"b{a}")) for a in "xyz"]
        total = total + 2.0 * float(w) * field(*p)
    return panels.select(F.col("pid").alias("i"), total.alias("value"))


def targets_from(table: DataFrame, key: str, value: str, lattice: int = 7) -> DataFrame:
    """(tid, x, y, z): points outside the sphere, direction and radius (2 to 3) from a table's key and value."""
    k = F.col(key).cast("long")
    a, b, c = (F.pmod(k * m, F.lit(2 * lattice + 1)).cast("double") - lattice + 0.5 for m in (3, 5, 11))
    r = F.sqrt(a * a + b * b + c * c)
    far = 2.0 + F.pmod(F.floor(F.col(value)).cast("long"), F.lit(1000)) / 1000.0
    return table.select(k.alias("tid"), (a / r * far).alias("x"), (b / r * far).alias("y"), (c / r * far).alias("z"))


def evaluate(targets: DataFrame, panels: DataFrame, density: DataFrame, kernel: KernelSpec, n: int = 3, broadcast_rows: int = 1_000_000) -> DataFrame:
    """(tid, re, im): the potential of density(i, re, im) at targets off the surface.

    The smaller role, targets, is broadcast while it is counted below broadcast_rows; else both are dealt by blocks.
    """
    rule = targets.sparkSession.createDataFrame([tuple(map(float, r)) for r in triangle_rule(n)], "s double, t double, w double")
    p = panels.join(density.select(F.col("i").alias("pid"), F.col("re").alias("d_re"), F.col("im").alias("d_im")), "pid").crossJoin(F.broadcast(rule))
    y = {a: F.col(f"a{a}") + F.col("s") * (F.col(f"b{a}") - F.col(f"a{a}")) + F.col("t") * (F.col(f"c{a}") - F.col(f"b{a}")) for a in "xyz"}
    p = p.select(*[y[a].alias(f"y{a}") for a in "xyz"], "nx", "ny", "nz", (F.col("w") * F.col("gram")).alias("w"), "d_re", "d_im")
    t = targets.select("tid", "x", "y", "z")
    if t.count() <= broadcast_rows:
        rows = p.crossJoin(F.broadcast(t))
    else:  # a stated target set against all panels, in blocks
        blocks = 256
        rows = p.withColumn("blk", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).join(t.withColumn("blk", F.pmod(F.xxhash64("tid"), F.lit(blocks)).cast("int")), "blk")
    re, im = kernel.columns(F.col("x") - F.col("yx"), F.col("y") - F.col("yy"), F.col("z") - F.col("yz"), F.col("nx"), F.col("ny"), F.col("nz"))
    rows = rows.select("tid", (F.col("w") * (re * F.col("d_re") - im * F.col("d_im"))).alias("re"), (F.col("w") * (re * F.col("d_im") + im * F.col("d_re"))).alias("im"))
    return rows.groupBy("tid").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))


def combined_field(targets: DataFrame, panels: DataFrame, density: DataFrame, kappa: float, eta: float = 1.0) -> DataFrame:
    """(tid, re, im): the double layer potential minus i eta times the single layer potential of density(i, re, im)."""
    double = evaluate(targets, panels, density, KernelSpec("dlp", kappa))
    single = evaluate(targets, panels, density, KernelSpec("slp", kappa)).select("tid", F.col("re").alias("sr"), F.col("im").alias("si"))
    return double.join(single, "tid").select("tid", (F.col("re") + eta * F.col("si")).alias("re"), (F.col("im") - eta * F.col("sr")).alias("im"))
