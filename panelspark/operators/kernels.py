"""Kernels as column expressions and as numpy functions of the difference d = x - y and the normal at y."""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
from numpy.polynomial import chebyshev
from pyspark.sql import functions as F

FOUR_PI = 4 * math.pi


@dataclass(frozen=True)
class KernelSpec:
    """layer: 'slp' for the kernel, 'dlp' for its derivative along the normal at y; kappa 0 is the static kernel."""

    layer: str = "slp"
    kappa: float = 0.0

    @property
    def complex(self) -> bool:
        return self.kappa != 0

    def columns(self, dx, dy, dz, nx=None, ny=None, nz=None):
        """Real and imaginary part as columns; a vanishing distance gives null, not an error."""
        r2 = dx * dx + dy * dy + dz * dz
        r = F.sqrt(r2)
        if self.layer == "slp":
            base = F.try_divide(F.lit(1.0), FOUR_PI * r)
            if not self.complex:
                return base, F.lit(0.0)
            return base * F.cos(self.kappa * r), base * F.sin(self.kappa * r)
        base = F.try_divide(dx * nx + dy * ny + dz * nz, FOUR_PI * r2 * r)
        if not self.complex:
            return base, F.lit(0.0)
        c, s = F.cos(self.kappa * r), F.sin(self.kappa * r)
        return base * (c + self.kappa * r * s), base * (s - self.kappa * r * c)

    def values(self, d: np.ndarray, normal: np.ndarray | None = None) -> np.ndarray:
        """d: (..., 3)."""
        r2 = np.einsum("...k,...k->...", d, d)
        r = np.sqrt(r2)
        wave = np.exp(1j * self.kappa * r) if self.complex else 1.0
        with np.errstate(divide="ignore", invalid="ignore"):
            if self.layer == "slp":
                return wave / (FOUR_PI * r)
            turn = np.einsum("...k,...k->...", d, normal)
            return (1 - 1j * self.kappa * r) * wave * turn / (FOUR_PI * r2 * r) if self.complex else turn / (FOUR_PI * r2 * r)


def slp(kappa: float = 0.0) -> KernelSpec:
    return KernelSpec("slp", kappa)


def dlp(kappa: float = 0.0) -> KernelSpec:
    return KernelSpec("dlp", kappa)


def second_normal(d: np.ndarray, n_z: np.ndarray, n_y: np.ndarray, kappa: float) -> np.ndarray:
    """Derivative along n_z at z and n_y at y of the kernel of d = z - y."""
    r2 = np.einsum("...k,...k->...", d, d)
    r = np.sqrt(r2)
    nn = np.einsum("...k,...k->...", n_z, n_y)
    dy, dz = np.einsum("...k,...k->...", d, n_y), np.einsum("...k,...k->...", d, n_z)
    k = kappa
    body = nn * (1 - 1j * k * r) / (r2 * r) + dy * dz * (k * k * r2 - 3 + 3j * k * r) / (r2 * r2 * r)
    out = np.exp(1j * k * r) * body / FOUR_PI
    return out if k else out.real


def waves(kernel: KernelSpec, value: np.ndarray, dist: np.ndarray, room: np.ndarray):
    """(real array, complex factor) terms whose sum is value times the wave's factor on the static kernel of the layer.

    Where the distances spread over few wave lengths, the terms are powers of the distance from the middle one; else a cosine
    and a sine. The arrays are used again for the next term."""
    k, low, most = kernel.kappa, float(dist.min()), float(dist.max())
    middle, spread = (low + most) / 2, abs(k) * (most - low) / 2
    if not spread <= 4:
        phase = k * dist
        c, s = np.cos(phase), np.sin(phase)
        if kernel.layer == "dlp":
            c, s = c + phase * s, s - phase * c
        yield np.multiply(value, c, out=room), 1.0
        yield np.multiply(value, s, out=room), 1j
        return
    step = max(0, math.ceil(4 * math.log2(max(spread, 2.0**-12)) + 48))
    scale = 2.0 ** (step / 4 - 12)  # spread or a little more
    series = wave_series(step)
    if kernel.layer == "dlp":
        series = (1 - 1j * k * middle) * np.append(series, 0) - 1j * scale * np.append(0, series)
    dist -= middle
    dist *= k / scale
    turn = np.exp(1j * k * middle)
    for n, a in enumerate(series.tolist()):
        if n:
            value *= dist
        yield value, turn * a


@lru_cache(maxsize=128)
def wave_series(step: int) -> np.ndarray:
    """Coefficients of a polynomial that is exp(1j * scale * v) for -1 <= v <= 1 to 14 digits, scale = 2 ** (step / 4 - 12)."""
    scale, n = 2.0 ** (step / 4 - 12), 1
    while 2 * (scale / 2) ** (n + 1) / math.factorial(n + 1) > 1e-14:
        n += 1
    parts = [chebyshev.cheb2poly(chebyshev.chebinterpolate(lambda v: f(scale * v), n)) for f in (np.cos, np.sin)]  # noqa: B023
    out = np.zeros(n + 1, complex)
    for part, unit in zip(parts, (1, 1j), strict=True):
        out[: len(part)] += unit * part
    return out
