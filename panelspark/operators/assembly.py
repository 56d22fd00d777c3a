"""Matrix entries by quadrature over panel pairs: the expression path, the Arrow path and the assembly orders.

Entry (i, j) of piecewise constants is gram_i * gram_j * sum over the rule of w * kernel(x - y). All methods return
(i, j, re, im). Pairs are made by joins on blocks or on shared vertices; only `dense` makes all pairs, behind a guard.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import BASIC, QuadSpec
from . import quadrature
from .classify import aligned, touching
from .kernels import FOUR_PI, KernelSpec, waves

GEOMETRY = ["v0", "v1", "v2", "ax", "ay", "az", "bx", "by", "bz", "cx", "cy", "cz", "gram", "nx", "ny", "nz"]
ENTRY = "i long, j long, re double, im double"


def side(panels: DataFrame, name: str) -> DataFrame:
    """The geometry columns of panels, prefixed, and the id as i (a) or j (b)."""
    return panels.select(F.col("pid").alias("i" if name == "a" else "j"), *[F.col(c).alias(f"{name}_{c}") for c in GEOMETRY])


def with_geometry(pairs: DataFrame, panels: DataFrame) -> DataFrame:
    return pairs.join(side(panels, "a"), "i").join(side(panels, "b"), "j")


def _point(s: str, p: Column, q: Column) -> list[Column]:
    return [F.col(f"{s}_a{x}") + p * (F.col(f"{s}_b{x}") - F.col(f"{s}_a{x}")) + q * (F.col(f"{s}_c{x}") - F.col(f"{s}_b{x}")) for x in "xyz"]


def integrated(points: DataFrame, kernel: KernelSpec) -> DataFrame:
    """Adds re and im, the kernel at the rule point of each row times all weights; stepwise, so that the difference and
    the distance are computed once."""
    d = [x - y for x, y in zip(_point("a", F.col("s"), F.col("t")), _point("b", F.col("u"), F.col("v")), strict=True)]
    rows = points.withColumns({f"_d{a}": c for a, c in zip("xyz", d, strict=True)})
    re, im = kernel.columns(*(F.col(f"_d{x}") for x in "xyz"), *(F.col(f"b_n{x}") for x in "xyz"))
    scale = F.col("w") * F.col("a_gram") * F.col("b_gram")
    return rows.withColumns({"re": re * scale, "im": im * scale})


def entries(pairs: DataFrame, panels: DataFrame, kernel: KernelSpec, quad: QuadSpec = BASIC) -> DataFrame:
    """Expression path. pairs(i, j, case): joined with the rule of its case (an equi-join on `case`), then summed.

    The rule table has a fixed size (see rule_frame), so it is broadcast; all arithmetic stays in generated code.
    """
    rows = with_geometry(pairs, panels)
    near, far = aligned(rows.where("case > 0")), rows.where("case = 0")
    rules = F.broadcast(quadrature.rule_frame(panels.sparkSession, quad))
    points = far.unionByName(near).join(rules, "case")
    return integrated(points, kernel).groupBy("i", "j").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))


def batch_values(a: np.ndarray, b: np.ndarray, normal: np.ndarray, scale: np.ndarray, case: int, n: int, kernel: KernelSpec, most: int = 1 << 16) -> np.ndarray:
    """One rule over a batch of pairs. a, b: (pairs, 3 corners, 3); the work of every pair is the same. Works through slices
    of about `most` points, which stay in the caches; a coordinate's differences are a small matrix product."""
    r = quadrature.rule(case, n)
    wa = np.stack([1 - r[:, 0], r[:, 0] - r[:, 1], r[:, 1]])
    wb = -np.stack([1 - r[:, 2], r[:, 2] - r[:, 3], r[:, 3]])
    both = np.concatenate([wa, wb])
    corners = np.ascontiguousarray(np.concatenate([a, b], 1).transpose(2, 0, 1))  # by coordinate, pair, corner
    weights = r[:, 4] / FOUR_PI
    step = max(1, most // len(r))
    out = np.zeros(len(a), complex if kernel.complex else float)
    for k in range(0, len(a), step):
        part = slice(k, k + step)
        r2 = corners[0, part] @ both
        r2 *= r2
        for x in (1, 2):
            d = corners[x, part] @ both
            d *= d
            r2 += d
        dist = np.sqrt(r2)
        with np.errstate(divide="ignore", invalid="ignore"):
            value = np.reciprocal(dist)
            if kernel.layer == "dlp":
                value /= r2
                value *= np.einsum("xpk,px->pk", corners[:, part], normal[part]) @ both
            if kernel.complex:
                for z, factor in waves(kernel, value, dist, r2):
                    out[part] += (z @ weights) * factor
            else:
                out[part] = value @ weights
    return out * scale


def run_package(batches, kernel: KernelSpec, quad: QuadSpec):
    """Arrow batches of aligned pairs -> entries. A batch is the merged buffer of a package; rows of a case run together."""
    for batch in batches:
        col = {name: np.asarray(batch.column(k)) for k, name in enumerate(batch.schema.names)}
        value = np.zeros(batch.num_rows, complex)
        for case in np.unique(col["case"]):
            rows = np.flatnonzero(col["case"] == case)
            corner = {s: np.stack([np.stack([col[f"{s}_{p}{x}"][rows] for x in "xyz"], 1) for p in "abc"], 1) for s in "ab"}
            normal = np.stack([col[f"b_n{x}"][rows] for x in "xyz"], 1)
            value[rows] = batch_values(corner["a"], corner["b"], normal, col["a_gram"][rows] * col["b_gram"][rows], int(case), quad.points(int(case)), kernel)
        yield pa.RecordBatch.from_arrays([batch.column(batch.schema.get_field_index("i")), batch.column(batch.schema.get_field_index("j")), pa.array(value.real.copy()), pa.array(value.imag.copy())], ["i", "j", "re", "im"])


def package_entries(pairs: DataFrame, panels: DataFrame, kernel: KernelSpec, quad: QuadSpec = BASIC, by_case: bool = True) -> DataFrame:
    """Arrow path. by_case: rows of a case are dealt together, so that batches hold one rule each."""
    rows = with_geometry(pairs, panels)
    rows = rows.where("case = 0").unionByName(aligned(rows.where("case > 0")))
    if by_case:
        rows = rows.sortWithinPartitions("case")
    return rows.mapInArrow(lambda it: run_package(it, kernel, quad), ENTRY)


def all_pairs(panels: DataFrame, max_pairs: int) -> DataFrame:
    """Every ordered pair, for small meshes: refused beyond max_pairs."""
    n = panels.count()
    if n * n > max_pairs:
        raise ValueError(f"{n}^2 pairs are more than max_pairs={max_pairs}; use a compressed form")
    return panels.select(F.col("pid").alias("i")).crossJoin(F.broadcast(panels.select(F.col("pid").alias("j"))))


def one_pass(panels: DataFrame, kernel: KernelSpec, quad: QuadSpec = BASIC, pairs: DataFrame | None = None, max_pairs: int = 50_000_000, arrow: bool = False, skip_coplanar: bool = False) -> DataFrame:
    """Each pair is classified first and integrated once by the rule of its class.

    arrow: all classes as packages; else the many pairs without a common vertex as generated expressions, and the few
    others, whose rules have a thousand points and more, as packages.
    """
    pairs = all_pairs(panels, max_pairs) if pairs is None else pairs
    known = pairs.join(touching(panels), ["i", "j"], "left").withColumn("case", F.coalesce("case", F.lit(0)))
    zero = None
    if skip_coplanar and kernel.layer == "dlp":  # x - y is orthogonal to the normal within one panel
        zero = known.where("case = 3").select("i", "j", F.lit(0.0).alias("re"), F.lit(0.0).alias("im"))
        known = known.where("case < 3")
    if arrow:
        out = package_entries(known, panels, kernel, quad)
    else:
        out = entries(known.where("case = 0"), panels, kernel, quad).unionByName(package_entries(known.where("case > 0"), panels, kernel, quad))
    return out if zero is None else out.unionByName(zero)


def regular_only(panels: DataFrame, kernel: KernelSpec, quad: QuadSpec = BASIC, pairs: DataFrame | None = None, max_pairs: int = 50_000_000) -> DataFrame:
    """The regular rule for every pair; wrong by design where panels touch, and null where points coincide."""
    pairs = all_pairs(panels, max_pairs) if pairs is None else pairs
    return entries(pairs.withColumn("case", F.lit(0)), panels, kernel, quad)


def two_phase(panels: DataFrame, kernel: KernelSpec, quad: QuadSpec = BASIC, pairs: DataFrame | None = None, max_pairs: int = 50_000_000) -> DataFrame:
    """Regular rule everywhere first, then touching pairs again by their own rules, laid over the first values."""
    pairs = all_pairs(panels, max_pairs) if pairs is None else pairs
    first = regular_only(panels, kernel, quad, pairs)
    fixes = package_entries(touching(panels).join(pairs, ["i", "j"], "left_semi"), panels, kernel, quad).select("i", "j", F.col("re").alias("re2"), F.col("im").alias("im2"))
    both = first.join(fixes, ["i", "j"], "left")
    return both.select("i", "j", F.coalesce("re2", "re").alias("re"), F.coalesce("im2", "im").alias("im"))


def dense(panels: DataFrame, kernel: KernelSpec, quad: QuadSpec = BASIC, max_pairs: int = 50_000_000) -> DataFrame:
    """All N^2 entries, in the Arrow path."""
    return one_pass(panels, kernel, quad, None, max_pairs, arrow=True)


def symmetric_half(pairs: DataFrame) -> DataFrame:
    """The lower triangle; `mirrored` restores the rest of a symmetric matrix at use."""
    return pairs.where("i >= j")


def mirrored(values: DataFrame) -> DataFrame:
    return values.unionByName(values.where("i > j").select(F.col("j").alias("i"), F.col("i").alias("j"), "re", "im"))


def row_sums(values: DataFrame, density: DataFrame | None = None) -> DataFrame:
    """Sum over j of entry * density_j (all ones by default), by i."""
    if density is None:
        return values.groupBy("i").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))
    rows = values.join(density.select(F.col("pid").alias("j"), "density"), "j")
    return rows.groupBy("i").agg(F.sum(F.col("re") * F.col("density")).alias("re"), F.sum(F.col("im") * F.col("density")).alias("im"))


def p1_scatter(pairs: DataFrame, panels: DataFrame, kernel: KernelSpec, quad: QuadSpec = BASIC) -> DataFrame:
    """Hat functions: the 3 x 3 local matrix of each pair, scattered to its vertices and summed: (vi, vj, re, im)."""
    rows = with_geometry(pairs, panels)
    rows = rows.where("case = 0").unionByName(aligned(rows.where("case > 0")))
    points = rows.join(F.broadcast(quadrature.rule_frame(panels.sparkSession, quad)), "case")
    hat = {"a": (1 - F.col("s"), F.col("s") - F.col("t"), F.col("t")), "b": (1 - F.col("u"), F.col("u") - F.col("v"), F.col("v"))}
    local = [F.struct(F.col(f"a_v{p}").alias("vi"), F.col(f"b_v{q}").alias("vj"), (F.col("re") * hat["a"][p] * hat["b"][q]).alias("re"), (F.col("im") * hat["a"][p] * hat["b"][q]).alias("im")) for p in range(3) for q in range(3)]
    rows = integrated(points, kernel).select(F.explode(F.array(*local)).alias("e")).select("e.*")
    return rows.groupBy("vi", "vj").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))


def p1_mass(panels: DataFrame) -> DataFrame:
    """Mass matrix of hat functions: area / 6 on the diagonal of a panel, area / 12 beside it."""
    cells = [F.struct(F.col(f"v{p}").alias("vi"), F.col(f"v{q}").alias("vj"), (F.col("area") / (6.0 if p == q else 12.0)).alias("m")) for p in range(3) for q in range(3)]
    return panels.select(F.explode(F.array(*cells)).alias("e")).select("e.*").groupBy("vi", "vj").agg(F.sum("m").alias("mass"))


def mass_matrix(panels: DataFrame) -> DataFrame:
    return panels.select(F.col("pid").alias("i"), F.col("area").alias("mass"))
