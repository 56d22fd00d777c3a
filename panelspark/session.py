"""The facade: mesh, classify, assemble, compress, apply, solve, measure."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .config import EngineConfig
from .operators import assembly, baselines, blocks, clustering, classify, fields, fill, geometry, h2, measures, solve
from .operators.kernels import KernelSpec, dlp, slp
from .plans import planner
from .plans.scratch import settled


class Session:
    def __init__(self, spark: SparkSession, cfg: EngineConfig | None = None):
        self.spark, self.cfg = spark, cfg or EngineConfig()

    def mesh(self, n: int, project: bool = True) -> DataFrame:
        self.panels = geometry.with_metrics(geometry.sphere_panels(self.spark, n, project))
        return self.panels

    def classify(self) -> DataFrame:
        """Ordered pairs of panels by their number of common vertices."""
        return classify.class_histogram(self.panels)

    def tree(self, symmetric: bool = False) -> DataFrame:
        pts = self.panels.select(F.col("pid").alias("i"), F.col("gx").alias("x"), F.col("gy").alias("y"), F.col("gz").alias("z"))
        self.membership = settled(clustering.geometric_tree(pts, self.cfg.leaf_size))
        self.clusters = settled(clustering.boxes(self.membership, clustering.panel_extents(self.panels)))
        self.blocks = settled(blocks.block_tree(self.clusters, self.cfg.eta, self.cfg.norm, symmetric, self.cfg.broadcast_rows))
        return self.blocks

    def assemble(self, kernel: KernelSpec, method: str | None = None) -> DataFrame:
        """Entries (i, j, re, im) by two_phase, one_pass, packages (of the tree's blocks), direct or dense."""
        method = method or planner.choose(self.panels.count(), kernel, self.cfg).method
        if method == "two_phase":
            return assembly.two_phase(self.panels, kernel, self.cfg.quad, max_pairs=self.cfg.max_pairs)
        if method == "one_pass":
            return assembly.one_pass(self.panels, kernel, self.cfg.quad, max_pairs=self.cfg.max_pairs)
        if method == "packages":
            self.tree()
            member = fill.members(clustering.ancestors(self.membership).select("node", "i").join(h2.geometry_rows(self.panels), "i"))
            return fill.fill(self.blocks, member, member, kernel, self.cfg).select("i", "j", "re", "im")
        if method == "direct":
            self.tree()
            return baselines.direct(self.blocks, self.membership, self.panels, kernel, self.cfg.quad)
        if method == "dense":
            return assembly.dense(self.panels, kernel, self.cfg.quad, self.cfg.max_pairs)
        raise ValueError(f"{method}: call compress for a mesh of this size")

    def compress(self, kernel: KernelSpec, method: str = "nested"):
        """The compressed matrix. 'nested': H2 tables; 'one_sided', 'two_sided', 'unpivoted': entries (t, s, i, j, re) of the far
        blocks by flat bases or by the plain separation; 'aca': rank and cost of each block approximated by itself."""
        half = method == "nested" and self.cfg.symmetric and kernel.layer == "slp"
        self.tree(half)
        rows = h2.geometry_rows(self.panels)
        if method == "nested":
            return h2.build(self.membership, self.clusters, self.blocks, rows, kernel, self.cfg, symmetric=half)
        far = self.blocks.where("kind = 'far'")
        member = clustering.ancestors(self.membership).select("node", "i").join(rows, "i")
        if method == "aca":
            return h2.aca_blocks(far, member, kernel, self.cfg)
        if method == "unpivoted":
            return h2.unpivoted(far, self.clusters, member, kernel, self.cfg)
        flat = lambda side: settled(h2.flat_basis(self.membership, self.clusters, rows, kernel, self.cfg, side, self.blocks))
        if method == "one_sided":
            return h2.one_sided(far, flat("row"), member, kernel, self.cfg)
        if method == "two_sided":
            return h2.two_sided(far, flat("row"), flat("col"), kernel, self.cfg)
        raise ValueError(method)

    def apply(self, matrix, x: DataFrame) -> DataFrame:
        return h2.matvec(matrix, x) if isinstance(matrix, h2.H2) else solve.entry_apply(matrix)(x)

    def solve(self, matrix, rhs: DataFrame, **options):
        """Conjugate gradients with a compressed or an explicit matrix: (i, value) and the report."""
        return solve.cg(lambda x: self.apply(matrix, x), rhs, **options)

    def measure(self, matrix) -> dict[str, float]:
        """Seconds of the set-up by step, and per degree of freedom; bytes against the dense matrix."""
        n = self.panels.count()
        used = sum(r["bytes"] for r in h2.storage(matrix).collect())
        return {**matrix.seconds, "us_per_dof": sum(matrix.seconds.values()) * 1e6 / n, "bytes": used, "of_dense": used / measures.dense_bytes(n)}

    def dirichlet(self, field: str = "f1", compressed: bool = False, **options):
        """alpha, the solver's report and the error of the exterior normal derivative of a harmonic test field."""
        make = (lambda k: (lambda a: lambda x: h2.matvec(a, x))(self.compress(k))) if compressed else (lambda k: solve.entry_apply(settled(self.assemble(k, "dense"))))
        beta = fields.project(self.panels, fields.FIELDS[field])
        alpha, report = solve.dirichlet(make(slp()), make(dlp()), assembly.mass_matrix(self.panels), beta, **options)
        g = [F.col(c) for c in ("gx", "gy", "gz", "nx", "ny", "nz")]
        exact = self.panels.select(F.col("pid").alias("i"), fields.normal_derivative(field, *g).alias("value"))
        return alpha, report, measures.neumann_error(alpha, exact, self.panels).first()[0]

    def wave_exterior(self, kappa: float, rhs: DataFrame, eta: float = 1.0, **options):
        """Density (i, re, im) of the exterior wave problem with both layers compressed: M / 2 + K - i eta V."""
        v, k = self.compress(slp(kappa)), self.compress(dlp(kappa))
        return solve.bicgstab(solve.combined_apply(lambda x: h2.complex_matvec(v, x), lambda x: h2.complex_matvec(k, x), assembly.mass_matrix(self.panels), eta), rhs, **options)
