"""Boundary-integral separation of the kernel over the surface of a box around a cluster.

The box of a cluster is enlarged on every side by scale * diameter / 2. Gauss nodes on its six faces separate x inside
from y outside: g(x, y) is about the sum over nodes of w * (g(x, z) dg/dn(z, y) - dg/dn(x, z) g(z, y)). The row factor holds
the parts in x and depends on the row cluster only.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .kernels import FOUR_PI, KernelSpec
from .quadrature import gauss, triangle_rule

GEOMETRY = ["ax", "ay", "az", "bx", "by", "bz", "cx", "cy", "cz", "gram", "nx", "ny", "nz"]


@lru_cache(maxsize=32)
def face_rule(q: int) -> list[tuple]:
    """(nu, u, v, w of the unit cube's surface point, axis, sign, weight) of 6 q^2 nodes."""
    g, w = gauss(q)
    out = []
    for axis in range(3):
        for sign in (0, 1):
            for a in range(q):
                for b in range(q):
                    p = [0.0, 0.0, 0.0]
                    p[axis], p[(axis + 1) % 3], p[(axis + 2) % 3] = float(sign), float(g[a]), float(g[b])
                    out.append((len(out), *p, axis, 2 * sign - 1, float(w[a] * w[b])))
    return out


def box_nodes(clusters: DataFrame, q: int, scale: float = 1.0, norm: str = "max") -> DataFrame:
    """(node, nu, zx, zy, zz, nx, ny, nz, w, delta): the nodes on the enlarged box of each cluster.

    The rule has 6 q^2 rows, a parameter, so it is broadcast.
    """
    rule = clusters.sparkSession.createDataFrame(face_rule(q), "nu int, ux double, uy double, uz double, axis int, sign int, uw double")
    delta = F.col("diam_max" if norm == "max" else "diam")
    rows = clusters.withColumn("delta", delta).crossJoin(F.broadcast(rule))
    lo = {a: F.col(f"lo{a}") - F.col("delta") * (scale / 2) for a in "xyz"}
    hi = {a: F.col(f"hi{a}") + F.col("delta") * (scale / 2) for a in "xyz"}
    ext = [hi[a] - lo[a] for a in "xyz"]
    area = F.when(F.col("axis") == 0, ext[1] * ext[2]).when(F.col("axis") == 1, ext[2] * ext[0]).otherwise(ext[0] * ext[1])
    return rows.select("node", "nu", *[(lo[a] + F.col(f"u{a}") * (hi[a] - lo[a])).alias(f"z{a}") for a in "xyz"], *[F.when(F.col("axis") == k, F.col("sign")).otherwise(0).cast("double").alias(f"n{a}") for k, a in enumerate("xyz")], (area * F.col("uw")).alias("w"), "delta")


def point_factor(members: DataFrame, nodes: DataFrame) -> DataFrame:
    """(node, i, nu, plus, minus) for point clusters and the static kernel: the row factor as a join on the cluster."""
    rows = members.join(nodes, "node")
    d = {a: F.col(a) - F.col(f"z{a}") for a in "xyz"}
    r2 = d["x"] ** 2 + d["y"] ** 2 + d["z"] ** 2
    r = F.sqrt(r2)
    turn = d["x"] * F.col("nx") + d["y"] * F.col("ny") + d["z"] * F.col("nz")
    root = F.sqrt("w")
    return rows.select("node", "i", "nu", (root / (FOUR_PI * r)).alias("plus"), (root * F.col("delta") * turn / (FOUR_PI * r2 * r)).alias("minus"))


def surface(lo: np.ndarray, hi: np.ndarray, q: int, scale: float, norm: str) -> tuple:
    """Nodes, normals, weights and diameter of one cluster, in numpy."""
    delta = float((hi - lo).max()) if norm == "max" else float(np.linalg.norm(hi - lo))
    lo, hi = lo - scale * delta / 2, hi + scale * delta / 2
    rule = np.array([r[1:] for r in face_rule(q)])
    ext = hi - lo
    axis = rule[:, 3].astype(int)
    normal = np.zeros((len(rule), 3))
    normal[np.arange(len(rule)), axis] = rule[:, 4]
    area = np.array([ext[1] * ext[2], ext[2] * ext[0], ext[0] * ext[1]])[axis]
    return lo + rule[:, :3] * ext, normal, rule[:, 5] * area, delta


def sample_points(geo: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """Points and weights that stand for basis functions: rows of 13 numbers are panels, rows of 3 are points."""
    if geo.shape[1] == 3:
        return geo[:, None, :], np.ones((len(geo), 1)), None
    r = triangle_rule(n)
    a, b, c = geo[:, 0:3], geo[:, 3:6], geo[:, 6:9]
    x = a[:, None] + r[None, :, 0, None] * (b - a)[:, None] + r[None, :, 1, None] * (c - b)[:, None]
    return x, geo[:, 9:10] * r[None, :, 2], geo[:, 10:13]


def row_factor(geo: np.ndarray, box: tuple, kernel: KernelSpec, side: str = "row", n: int = 3) -> np.ndarray:
    """A = [A+ A-] of the members of a cluster. side 'col' of a double layer carries the derivative at y as well."""
    z, normal, w, delta = box
    x, weight, own = sample_points(geo, n)
    middle = z.mean(0)
    x, z, root, shape = x - middle, z - middle, np.sqrt(w), (*x.shape[:2], len(z))
    p = x.reshape(-1, 3)
    dist = np.concatenate([-2 * p, (p * p).sum(1)[:, None], np.ones((len(p), 1))], 1) @ np.concatenate([z, np.ones((len(z), 1)), (z * z).sum(1)[:, None]], 1).T
    np.sqrt(dist, out=dist)
    across = np.concatenate([p, np.ones((len(p), 1))], 1) @ np.concatenate([normal, -(z * normal).sum(1)[:, None]], 1).T  # (x - z) along the normal at z
    k = kernel.kappa
    wave = [np.cos(k * dist), np.sin(k * dist)] if k else [1.0]

    def total(value, a=1.0, b=0.0):
        """The weighted sum over the points of a member of value * (a + i b) * wave."""
        turned = [value * a] if not k else [value * (a * wave[0] - b * wave[1]), value * (a * wave[1] + b * wave[0])]
        out = [np.matmul(weight[:, None, :], t.reshape(shape))[:, 0] for t in turned]
        return out[0] + 1j * out[1] if k else out[0]

    inverse = np.reciprocal(dist)
    cube = inverse * inverse
    cube *= inverse
    if side == "col" and kernel.layer == "dlp":
        face = (x[:, 0] * own).sum(1)[:, None] - own @ z.T  # (x - z) along the normal at x: the same for all points of a panel
        bare = total(cube, 1.0, -k * dist)
        plus = -face * bare  # derivative at y = x of g(z - y)
        across *= cube
        across *= inverse
        across *= inverse
        minus = (own @ normal.T) * bare + face * total(across, (k * dist) ** 2 - 3, 3 * k * dist)
    else:
        plus = total(inverse)
        cube *= across
        minus = total(cube, 1.0, -k * dist)  # derivative at z
    return np.concatenate([plus * (root / FOUR_PI), minus * (root * delta / FOUR_PI)], 1)


def column_factor(geo: np.ndarray, box: tuple, kernel: KernelSpec, n: int = 3) -> np.ndarray:
    """B with A @ B.T about the block of the kernel: the explicit, un-pivoted form of rank 2 m."""
    z, normal, w, delta = box
    x, weight, _ = sample_points(geo, n)
    d = x[:, :, None, :] - z[None, None]
    root = np.sqrt(w)
    value = KernelSpec("slp", kernel.kappa).values(d)
    turned = KernelSpec("dlp", kernel.kappa).values(d, np.broadcast_to(normal[None, None], d.shape))
    return np.concatenate([np.einsum("ip,ipm->im", weight, turned) * root, -np.einsum("ip,ipm->im", weight, value) * root / delta], 1)


def expand(spark: SparkSession, matrix: np.ndarray, schema: str) -> DataFrame:
    """A small dense matrix as (r, c, value) rows."""
    return spark.createDataFrame([(r, c, float(v)) for r, row in enumerate(matrix) for c, v in enumerate(row)], schema)
