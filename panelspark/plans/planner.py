"""Rewrites that need domain knowledge, made while the plan is built."""

from __future__ import annotations

from dataclasses import dataclass

from ..config import EngineConfig
from ..operators.kernels import KernelSpec


@dataclass(frozen=True)
class Choice:
    method: str
    symmetric: bool
    skip_coplanar: bool
    broadcast_nodes: bool


def choose(n_panels: int, kernel: KernelSpec, cfg: EngineConfig) -> Choice:
    """Dense up to max_pairs, compressed beyond; half the matrix for symmetric layers; no identical class for double layers."""
    dense = n_panels * n_panels <= cfg.max_pairs
    return Choice("dense" if dense else "h2", cfg.symmetric and kernel.layer == "slp", kernel.layer == "dlp", 2 * n_panels // max(cfg.leaf_size, 1) <= cfg.broadcast_rows)
