"""Choice of parts, rounds and legality for an instance."""

from __future__ import annotations

import math
from dataclasses import dataclass

from ..schema import ClusterSpec
from . import bounds

#: Points that a task holds, by default.
ROWS = 50_000
#: Rows that a seed is expected to leave in a one-round summary.
PER_SEED = 16


@dataclass(frozen=True)
class Plan:
    parts: int
    rounds: int
    ratio: float
    why: str
    guarantee: bool
    rows_per_part: int


def part_count(n: int, least: int = 4, rows: int = ROWS) -> int:
    """Parts so that none holds more than `rows` points; `least` for small inputs."""
    return max(least, -(-n // rows))


def resolve(n: int, spec: ClusterSpec, alpha: float = 5.0, rounds: int | None = None, rows: int = ROWS, continuous: bool = False) -> Plan:
    """Balanced parts: (n/k)^(1/3) for two rounds; for one, so many that a part is as large as the summary; more where a task's memory asks for it.

    Above the crossover eps the one-round form has the smaller proven ratio and is preferred.
    """
    eps = float(spec.eps)
    if rounds is None:
        rounds = 1 if continuous or eps >= bounds.crossover(spec.objective) else 2
    balanced = math.ceil((max(n, 1) / spec.k) ** (1 / 3) if rounds == 2 else (max(n, 1) / (PER_SEED * spec.m)) ** (1 / 2))
    parts = max(1, balanced, -(-n // rows))
    value, why = bounds.ratio(alpha, eps, spec.objective, rounds, continuous)
    return Plan(parts, rounds, value, why, spec.proven and math.isfinite(value), -(-n // parts))
