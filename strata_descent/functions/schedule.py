"""Step sizes as functions of the step t = 1, 2, ..."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass


@dataclass(frozen=True)
class Schedule:
    name: str
    at: Callable[[int], float]


def inverse(lam: float) -> Schedule:
    """1 / (lam t), the schedule of the experiments."""
    return Schedule(f"inverse({lam:g})", lambda t: 1.0 / (lam * t))


def shifted_inverse(a: float, h: float) -> Schedule:
    """1 / (a + h t)."""
    return Schedule(f"shifted_inverse({a:g},{h:g})", lambda t: 1.0 / (a + h * t))


def constant(eta: float) -> Schedule:
    return Schedule(f"constant({eta:g})", lambda t: eta)


def theory_covered(schedule: Schedule, smoothness: float, steps: int) -> bool:
    """Whether every step size lies in (0, 1 / smoothness], as the decrease bound asks."""
    return all(0 < schedule.at(t) <= 1.0 / smoothness + 1e-15 for t in range(1, steps + 1))
