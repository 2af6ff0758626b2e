"""Bounds without collecting: the Lagrangian dual is one aggregation per set of multipliers.

For a maximum, any multipliers give max f <= sum(ub * max(0, obj - lam @ c)) + sum(lam+ * hi - lam- * lo); minima
are mirrored. A few subgradient steps tighten it. Columns that the bound and a known package rule out can be
dropped before a whole solve, without changing its answer.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..lang.ast import INF
from ..plans.coefficients import Translation
from ..solve.problem import IlpProblem
from ..solve.simplex import Simplex


@dataclass
class Dual:
    bound: float
    multipliers: np.ndarray
    rounds: int


def _margin(t: Translation, lam: np.ndarray, sign: float) -> Column:
    out = F.col("obj") * sign
    for w, i in zip(lam, t.branches[0], strict=True):
        out = out - F.lit(float(w)) * F.col(f"c_{i}")
    return out


def dual_value(frame: DataFrame, t: Translation, lam: np.ndarray) -> tuple[float, np.ndarray]:
    """The bound at the multipliers and a subgradient (row activity of the relaxed package)."""
    sign = 1.0 if t.query.sense == "max" else -1.0
    gain = _margin(t, lam, sign)
    taken = F.when(gain > 0, F.col("ub")).otherwise(0.0)
    row = frame.agg(F.coalesce(F.sum(taken * gain), F.lit(0.0)).alias("v"), *(F.coalesce(F.sum(taken * F.col(f"c_{i}")), F.lit(0.0)).alias(f"r{k}") for k, i in enumerate(t.branches[0]))).first()
    lo, hi = t.lo(0), t.hi(0)
    paid = sum((w * h if w > 0 else w * low) for w, low, h in zip(lam, lo, hi, strict=True) if w)
    return sign * (row["v"] + paid), np.array([row[f"r{k}"] for k in range(len(lo))])


def multipliers_of(p: IlpProblem) -> np.ndarray | None:
    """Multipliers from a small program that stands for the large one, such as the coarse problem."""
    r = Simplex(p.A, p.lo, p.hi, p.minimized()).solve(np.zeros(p.n), p.upper)
    return -r.duals if r.status == "optimal" else None


def dual_bound(frame: DataFrame, t: Translation, rounds: int = 8, start: np.ndarray | None = None) -> Dual:
    """frame needs finite ub (REPEAT given). start: multipliers to begin with."""
    sign = 1.0 if t.query.sense == "max" else -1.0
    lo, hi = t.lo(0), t.hi(0)
    lam = np.zeros(len(lo)) if start is None else np.where(np.isinf(hi), np.minimum(start, 0), np.where(np.isinf(lo), np.maximum(start, 0), start))
    best, at = INF, lam
    scale = frame.agg(F.stddev("obj").alias("o"), *(F.coalesce(F.stddev(f"c_{i}") + F.avg(F.abs(f"c_{i}")), F.lit(1.0)).alias(f"s{k}") for k, i in enumerate(t.branches[0]))).first()
    unit = np.array([scale[f"s{k}"] or 1.0 for k in range(len(lo))])
    step = float(scale["o"] or 1.0) * (1.0 if start is None else 0.02)
    for r in range(rounds):
        value, used = dual_value(frame, t, lam)
        if sign * value < best:
            best, at = sign * value, lam.copy()
        over, under = used - np.where(np.isinf(hi), used, hi), np.where(np.isinf(lo), used, lo) - used
        push = np.where(over > 0, 1.0, 0.0) - np.where(under > 0, 1.0, 0.0)
        if not push.any():
            break
        lam = lam + step / (1 + r) ** 0.7 * push / unit
        lam = np.where(np.isinf(hi), np.minimum(lam, 0), lam)
        lam = np.where(np.isinf(lo), np.maximum(lam, 0), lam)
    return Dual(sign * best, at, rounds)


def column_generation(frame: DataFrame, t: Translation, start: np.ndarray | None = None, rounds: int = 6, width: int = 2000) -> Dual:
    """The relaxation's bound: a program over the most promising tuples gives multipliers, which find more such tuples.

    Each round collects at most width tuples and runs one aggregation; it ends early when no other tuple could help.
    """
    sign = 1.0 if t.query.sense == "max" else -1.0
    lam = np.zeros(len(t.branches[0])) if start is None else start
    pool: dict[int, tuple] = {}
    best, at, done = INF, lam, 0
    for done in range(1, rounds + 1):
        value, _ = dual_value(frame, t, lam)
        if sign * value < best:
            best, at = sign * value, lam
        gain = _margin(t, lam, sign)
        before = len(pool)
        some = [c for i in t.branches[0] for c in (F.struct((-F.col(f"c_{i}")).alias("v"), "tid"),)] if not pool and start is None else []
        for order in (gain.desc(), *(c.asc() for c in some)):
            for r in frame.orderBy(order, "tid").limit(width).collect():
                pool[r.tid] = (r.obj, r.ub, *(r[f"c_{i}"] for i in t.branches[0]))
        if len(pool) == before:
            break
        x = np.array(list(pool.values()), float)
        p = IlpProblem(x[:, 2:].T, t.lo(0), t.hi(0), x[:, 0], x[:, 1], t.query.sense, np.arange(len(x)))
        found = multipliers_of(p)
        if found is None:
            break
        lam = found
    return Dual(sign * best, at, done)


def prune_columns(frame: DataFrame, t: Translation, dual: Dual, incumbent: float) -> DataFrame:
    """Tuples that some better package than the incumbent could still use."""
    sign = 1.0 if t.query.sense == "max" else -1.0
    gap = sign * (dual.bound - incumbent)
    return frame.filter(_margin(t, dual.multipliers, sign) >= -gap - 1e-9)


def certified_ratio(objective: float, bound: float, sense: str) -> float | None:
    """An upper bound of the approximation ratio where no whole solve is known."""
    if objective <= 0 or bound <= 0:
        return None
    return bound / objective if sense == "max" else objective / bound


def pruned_whole_solve(part, q, limits=None):
    """The exact optimum of a large relation: coarse-fine gives a package, the relaxation a bound, and only tuples that
    the two don't rule out are collected and solved. Needs REPEAT and one alternative; part is a Partitioning."""
    from ..package.result import PackageResult
    from ..plans.coefficients import coefficient_frame, limits_columns, translate
    from ..scratch import stored
    from ..solve.problem import SolverLimits
    from .coarse_fine import coarse_fine
    from .reduced import reduced_solve

    limits = limits or SolverLimits()
    t = translate(part.df, q)
    if q.repeat is None or len(t.branches) != 1:
        raise ValueError("needs a REPEAT bound and a condition without alternatives")
    known = coarse_fine(part, q)
    frame = stored(coefficient_frame(part.df, t), "coefficients")
    r = reduced_solve(frame, t, 0, limits, limits_columns(limits, t), (known.objective, known.chosen) if known.found else None)
    s = r.solution
    return PackageResult(q, part.df.drop("gid"), s.status, r.chosen, s.objective, s.bound, counters={"columns": r.kept, "nodes": s.nodes})
