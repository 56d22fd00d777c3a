"""Parameters of the engine."""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace


@dataclass(frozen=True)
class QuadSpec:
    """One-dimensional Gauss points for pairs without and with a common vertex."""

    regular: int = 3
    singular: int = 5

    def points(self, case: int) -> int:
        return self.regular if case == 0 else self.singular


BASIC, HIGHER = QuadSpec(3, 5), QuadSpec(4, 6)


@dataclass(frozen=True)
class EngineConfig:
    eta: float = 1.0
    leaf_size: int = 32
    norm: str = "max"
    green_q: int = 4
    box_scale: float = 1.0
    aca_eps: float = 1e-4
    kmax: int | None = None
    pivot: str = "full"
    quad: QuadSpec = field(default_factory=QuadSpec)
    kappa: float = 0.0
    limit_bytes: int = 8 << 20
    slots: int = 2
    symmetric: bool = True
    max_pairs: int = 50_000_000
    broadcast_rows: int = 1_000_000
    band: int = 6

    def __post_init__(self):
        if self.norm not in ("max", "l2"):
            raise ValueError("norm must be max or l2")
        if not 0 < self.eta <= 1:
            raise ValueError("the separation of the boxes is only guaranteed for 0 < eta <= 1")

    def for_level(self, n: int) -> EngineConfig:
        """Tighter accuracy for finer grids, so that compression stays below the discretization error."""
        level = max(0.0, math.log2(max(n, 1) / 16))
        return replace(self, aca_eps=self.aca_eps / 4**level, green_q=self.green_q + int(level // 2))


@dataclass(frozen=True)
class RunConfig:
    """How many tasks share a core pool: slots a worker and the number of workers."""

    slots_per_worker: int = 2
    executors: int = 1
    repeats: int = 5

    def spark_conf(self) -> dict[str, str]:
        return {"spark.task.cpus": "1", "spark.executor.cores": str(self.slots_per_worker), "spark.executor.instances": str(self.executors), "spark.scheduler.mode": "FAIR"}
