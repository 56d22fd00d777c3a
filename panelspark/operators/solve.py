"""Iterative solvers over dataframes: vectors are rows (i, ..), matrices any function of a vector.

Each step writes the state once to shared storage and brings only scalars to the driver.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import discard, settled

Apply = Callable[[DataFrame], DataFrame]


@dataclass
class Report:
    steps: int = 0
    residuals: list[float] = field(default_factory=list)
    alphas: list[float] = field(default_factory=list)
    betas: list[float] = field(default_factory=list)

    def eigenvalues(self) -> tuple[float, float]:
        """Estimates of the extreme eigenvalues from the scalars of the conjugate gradients."""
        a, b = np.array(self.alphas), np.array(self.betas)
        diagonal = 1 / a + np.concatenate([[0.0], b[: len(a) - 1] / a[:-1]])
        side = np.sqrt(b[: len(a) - 1]) / a[:-1]
        e = np.linalg.eigvalsh(np.diag(diagonal) + np.diag(side, 1) + np.diag(side, -1))
        return float(e[0]), float(e[-1])


def entry_apply(values: DataFrame) -> Apply:
    """The product with a matrix given as (i, j, re)."""
    return lambda x: values.join(x.select(F.col("i").alias("j"), "value"), "j").groupBy("i").agg(F.sum(F.col("re") * F.col("value")).alias("value"))


def cg(apply: Apply, rhs: DataFrame, tol: float = 1e-8, maxit: int = 500, precond: DataFrame | Apply | None = None) -> tuple[DataFrame, Report]:
    """Conjugate gradients for rhs(i, value). precond: a diagonal (i, d) or a function of a residual."""

    def pre(r: DataFrame) -> DataFrame:
        if precond is None:
            return r.withColumn("z", F.col("r"))
        if callable(precond):
            return r.join(precond(r.select("i", F.col("r").alias("value"))).select("i", F.col("value").alias("z")), "i")
        return r.join(precond, "i").withColumn("z", F.col("r") / F.col("d")).drop("d")

    state = pre(rhs.select("i", F.lit(0.0).alias("x"), F.col("value").alias("r")))
    state = settled(state.withColumn("p", F.col("z")))
    rz, start = state.agg(F.sum(F.col("r") * F.col("z")), F.sum(F.col("r") * F.col("r"))).first()
    report, nxt = Report(residuals=[1.0]), None
    while start and report.steps < maxit:
        q = apply(state.select("i", F.col("p").alias("value"))).select("i", F.col("value").alias("q"))
        state = settled(state.select("i", "x", "r", "p").join(q, "i", "left").withColumn("q", F.coalesce("q", F.lit(0.0))))
        if nxt is not None:
            discard(nxt)
        pq = state.agg(F.sum(F.col("p") * F.col("q"))).first()[0]
        a = rz / pq
        # settled, so that the updates and the preconditioner run once a step; the step before is deleted
        before, nxt = state, settled(pre(state.select("i", (F.col("x") + a * F.col("p")).alias("x"), (F.col("r") - a * F.col("q")).alias("r"), "p")))
        discard(before)
        new, rr = nxt.agg(F.sum(F.col("r") * F.col("z")), F.sum(F.col("r") * F.col("r"))).first()
        b = new / rz
        state = nxt.withColumn("p", F.col("z") + b * F.col("p"))
        report.steps += 1
        report.residuals.append((rr / start) ** 0.5)
        report.alphas.append(a)
        report.betas.append(b)
        rz = new
        if rr <= tol * tol * start:
            break
    return state.select("i", F.col("x").alias("value")), report


def block_diagonal(nearfield: DataFrame, membership: DataFrame) -> Apply:
    """Preconditioner: solves with the diagonal block of each leaf, one bounded task a leaf."""
    leaf = membership.select("i", "node")
    block = nearfield.join(leaf, "i").join(leaf.select(F.col("i").alias("j"), F.col("node").alias("other")), "j").where("node = other")
    rows = settled(block.groupBy("node", "i").agg(F.sort_array(F.collect_list(F.struct("j", "re"))).alias("row")))

    def solve(pdf):
        pdf = pdf.sort_values("i").reset_index(drop=True)
        a = np.array([[e["re"] for e in r] for r in pdf["row"]])
        return pdf[["i"]].assign(value=np.linalg.solve(a, pdf["value"].to_numpy()))

    return lambda r: rows.join(r, "i").groupBy("node").applyInPandas(solve, "i long, value double")


def dirichlet(v: Apply, k: Apply, mass: DataFrame, beta: DataFrame, **options) -> tuple[DataFrame, Report]:
    """Solves V alpha = (M / 2 + K) beta for beta(i, value); mass(i, mass) is diagonal."""
    return cg(v, dirichlet_rhs(k, mass, beta), **options)


def dirichlet_rhs(k: Apply, mass: DataFrame, beta: DataFrame) -> DataFrame:
    kb = k(beta).select("i", F.col("value").alias("k"))
    half = mass.join(beta, "i").select("i", (F.col("mass") * F.col("value") / 2).alias("m"))
    return half.join(kb, "i", "left").select("i", (F.col("m") + F.coalesce("k", F.lit(0.0))).alias("value"))


def _dot(df: DataFrame, *pairs: tuple[str, str]) -> list[complex]:
    """Sums of conj(a) * b of complex columns a_re, a_im, ..."""
    out = []
    for a, b in pairs:
        ar, ai, br, bi = (F.col(f"{x}_{p}") for x in (a, b) for p in ("re", "im"))
        out += [F.sum(ar * br + ai * bi), F.sum(ar * bi - ai * br)]
    got = df.agg(*out).first()
    return [complex(got[2 * n], got[2 * n + 1]) for n in range(len(pairs))]


def _axpy(name: str, base: str, *terms: tuple[complex, str]):
    re, im = F.col(f"{base}_re"), F.col(f"{base}_im")
    for c, v in terms:
        re = re + c.real * F.col(f"{v}_re") - c.imag * F.col(f"{v}_im")
        im = im + c.real * F.col(f"{v}_im") + c.imag * F.col(f"{v}_re")
    return {f"{name}_re": re, f"{name}_im": im}


def bicgstab(apply: Apply, rhs: DataFrame, tol: float = 1e-8, maxit: int = 200) -> tuple[DataFrame, Report]:
    """Stabilised bi-conjugate gradients for complex systems that are not Hermitian; vectors are (i, re, im)."""
    zero = F.lit(0.0)
    s = rhs.select("i", *[c.alias(f"{v}_{p}") for v in ("r", "h", "p") for c, p in ((F.col("re"), "re"), (F.col("im"), "im"))], *[zero.alias(f"x_{p}") for p in ("re", "im")])
    s = settled(s)

    def times(df: DataFrame, v: str, out: str) -> DataFrame:
        y = apply(df.select("i", F.col(f"{v}_re").alias("re"), F.col(f"{v}_im").alias("im"))).select("i", F.col("re").alias(f"{out}_re"), F.col("im").alias(f"{out}_im"))
        return settled(df.join(y, "i"))

    rho, start = _dot(s, ("h", "r"), ("r", "r"))
    report = Report(residuals=[1.0])
    while abs(start) and report.steps < maxit:
        s = times(s, "p", "v")
        alpha = rho / _dot(s, ("h", "v"))[0]
        s = times(s.withColumns(_axpy("s", "r", (-alpha, "v"))), "s", "t")
        ts, tt = _dot(s, ("t", "s"), ("t", "t"))
        omega = ts / tt if tt else 0j
        s = s.withColumns(_axpy("x", "x", (alpha, "p"), (omega, "s")) | _axpy("r", "s", (-omega, "t")))
        new, rr = _dot(s, ("h", "r"), ("r", "r"))
        report.steps += 1
        report.residuals.append((abs(rr) / abs(start)) ** 0.5)
        if abs(rr) <= tol * tol * abs(start):
            break
        beta = new / rho * alpha / omega
        rho = new
        keep = s.withColumns(_axpy("p", "p", (-omega, "v")))
        s = keep.withColumns(_axpy("p", "r", (beta, "p"))).select("i", *[f"{v}_{p}" for v in ("r", "h", "p", "x") for p in ("re", "im")])
    return s.select("i", F.col("x_re").alias("re"), F.col("x_im").alias("im")), report


def complex_apply(values: DataFrame) -> Apply:
    """The product with a complex matrix (i, j, re, im)."""
    def run(x: DataFrame) -> DataFrame:
        rows = values.join(x.select(F.col("i").alias("j"), F.col("re").alias("xr"), F.col("im").alias("xi")), "j")
        return rows.groupBy("i").agg(F.sum(F.col("re") * F.col("xr") - F.col("im") * F.col("xi")).alias("re"), F.sum(F.col("re") * F.col("xi") + F.col("im") * F.col("xr")).alias("im"))
    return run


def combined_apply(v: Apply, k: Apply, mass: DataFrame, eta: float) -> Apply:
    """The product with M / 2 + K - i eta V from the products with both layers."""

    def run(x: DataFrame) -> DataFrame:
        half = mass.join(x, "i").select("i", (F.col("mass") * F.col("re") / 2).alias("re"), (F.col("mass") * F.col("im") / 2).alias("im"))
        turned = v(x).select("i", (eta * F.col("im")).alias("re"), (-eta * F.col("re")).alias("im"))
        return half.unionByName(k(x).select("i", "re", "im")).unionByName(turned).groupBy("i").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))

    return run


def combined_layers(v: DataFrame, k: DataFrame, mass: DataFrame, eta: float) -> DataFrame:
    """Entries of M / 2 + K - i eta V; the half comes from the trace from outside."""
    m = mass.select("i", F.col("i").alias("j"), (F.col("mass") / 2).alias("re"), F.lit(0.0).alias("im"))
    turned = v.select("i", "j", (eta * F.col("im")).alias("re"), (-eta * F.col("re")).alias("im"))
    return k.select("i", "j", "re", "im").unionByName(turned).unionByName(m).groupBy("i", "j").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))


def wave_exterior(v: DataFrame, k: DataFrame, mass: DataFrame, rhs: DataFrame, eta: float = 1.0, formulation: str = "combined", **options) -> tuple[DataFrame, Report]:
    """The density of the exterior wave problem. formulation 'single' solves V w = f, which fails near interior eigenvalues."""
    matrix = settled(combined_layers(v, k, mass, eta) if formulation == "combined" else v.select("i", "j", "re", "im"))
    return bicgstab(complex_apply(matrix), rhs, **options)
