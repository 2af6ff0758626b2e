"""Integer linear programs with few rows and many columns, and what solving one returns."""

from __future__ import annotations

import time
from dataclasses import dataclass, field
from enum import Enum

import numpy as np

INF = float("inf")
TOL = 1e-7


class SolveStatus(str, Enum):
    OPTIMAL = "optimal"
    FEASIBLE = "feasible"
    INFEASIBLE = "infeasible"
    UNBOUNDED = "unbounded"
    LIMIT_TIME = "time limit"
    LIMIT_NODES = "node limit"
    LIMIT_MEMORY = "memory limit"


@dataclass(frozen=True)
class SolverLimits:
    """Defaults of the reference's setup: an hour and 512 MB of working memory.

    patience: once a solution is known, so many nodes without a better one end the search; the solution is feasible, not
    proven optimal.
    """

    seconds: float = 3600.0
    bytes: int = 512 << 20
    nodes: int = 200_000
    gap: float = 0.0
    patience: int | None = None

    def columns(self, rows: int) -> int:
        """Columns of an ILP whose matrix, bounds and work arrays fit in bytes."""
        return self.bytes // (8 * (rows + 12))


@dataclass
class IlpProblem:
    """sense of cost @ x, lo <= A x <= hi, 0 <= x <= upper, x whole. ids names the columns."""

    A: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    cost: np.ndarray
    upper: np.ndarray
    sense: str
    ids: np.ndarray
    names: list[str] = field(default_factory=list)

    def __post_init__(self):
        self.A = np.ascontiguousarray(self.A, float).reshape(len(self.lo), len(self.cost))
        self.lo, self.hi, self.cost, self.upper = (np.asarray(v, float) for v in (self.lo, self.hi, self.cost, self.upper))

    @property
    def n(self) -> int:
        return len(self.cost)

    def minimized(self) -> np.ndarray:
        return self.cost if self.sense == "min" else -self.cost

    def scale(self) -> np.ndarray:
        return np.maximum(1.0, np.abs(self.A).max(1, initial=0.0))

    def feasible(self, x: np.ndarray, tol: float = 1e-6) -> bool:
        r, t = self.A @ x, tol * self.scale()
        return bool(np.all(r >= self.lo - t) and np.all(r <= self.hi + t) and np.all(x >= -tol) and np.all(x <= self.upper + tol))


@dataclass
class Solution:
    status: SolveStatus
    x: np.ndarray | None = None
    objective: float | None = None
    bound: float | None = None
    nodes: int = 0
    iterations: int = 0
    seconds: float = 0.0

    @property
    def found(self) -> bool:
        return self.x is not None


class Clock:
    def __init__(self, seconds: float):
        self.start, self.seconds = time.perf_counter(), seconds

    def spent(self) -> float:
        return time.perf_counter() - self.start

    def over(self) -> bool:
        return self.spent() > self.seconds
