"""Exact answers for programs with more columns than the driver should hold.

The relaxation is solved by column generation until no tuple of the relation could improve it: a hash sample of the
tuples gives first multipliers, each further round fetches tuples that violate them. While the tuples
fetched so far have no solution, multipliers of the smallest violation choose the next ones; if no tuple lowers it, the program
is infeasible. A package over the fetched tuples and the relaxation's value then rule out all tuples that no better package
can hold; what is left is solved exactly. Only fetched and left tuples come to the driver.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..lang.ast import INF
from ..plans.coefficients import TooManyColumns, Translation, branch_problem, collect_columns
from ..solve.branch import BranchAndBound
from ..solve.problem import Clock, IlpProblem, Solution, SolverLimits, SolveStatus
from ..solve.simplex import Simplex

#: Programs of more columns are reduced before they are solved; the answer is the same.
DIRECT_COLUMNS = 400_000
#: Fewer columns than this in memory aren't enough for a reduction.
LEAST_COLUMNS = 10_000
WIDTH, NEAR, ROUNDS = 20_000, 60_000, 100


@dataclass
class Relaxed:
    """status: optimal, infeasible, unbounded or limit. data: tids, coefficients, objective and bounds of the fetched tuples."""

    status: str
    bound: float | None
    multipliers: np.ndarray | None
    data: tuple
    rounds: int


def gain_of(t: Translation, branch: int, lam: np.ndarray) -> Column:
    """What a unit of a tuple adds to the objective (the larger the better) beyond what its rows cost at the multipliers."""
    out = F.col("obj") * (1.0 if t.query.sense == "max" else -1.0)
    for w, i in zip(lam, t.branches[branch], strict=True):
        out = out - F.lit(float(w)) * F.col(f"c_{i}")
    return out


def _violation(p: IlpProblem) -> tuple[float, np.ndarray | None]:
    """The smallest sum of scaled row violations over the columns, and its duals."""
    k = len(p.lo)
    unit = np.abs(p.A).max(1, initial=0.0)
    unit = np.diag(np.where(unit > 0, unit, 1.0))
    r = Simplex(np.hstack((p.A, unit, -unit)), p.lo, p.hi, np.concatenate((np.zeros(p.n), np.ones(2 * k)))).solve(np.zeros(p.n + 2 * k), np.concatenate((p.upper, np.full(2 * k, INF))))
    return (r.value, r.duals) if r.status == "optimal" else (INF, None)


def _joined(a: tuple | None, b: tuple) -> tuple:
    """Columns of both, each tuple once, by tid."""
    if a is None:
        return b
    fresh = ~np.isin(b[0], a[0])
    tids, C, obj, upper = (np.concatenate((x, y[..., fresh]), -1) for x, y in zip(a, b, strict=True))
    order = np.argsort(tids, kind="stable")
    return tids[order], C[:, order], obj[order], upper[order]


def relaxation(frame: DataFrame, t: Translation, branch: int = 0, clock: Clock | None = None) -> Relaxed:
    """The linear relaxation over all tuples of a coefficient frame; its value is exact, not only a bound."""
    data = collect_columns(frame.orderBy(F.xxhash64("tid"), "tid").limit(WIDTH), t, WIDTH)
    for done in range(1, ROUNDS + 1):
        p = branch_problem(t, branch, *data)
        if not p.n:
            return Relaxed("optimal" if np.all(p.lo <= 0) and np.all(p.hi >= 0) else "infeasible", 0.0, np.zeros(len(p.lo)), data, done)
        r = Simplex(p.A, p.lo, p.hi, p.minimized()).solve(np.zeros(p.n), p.upper, clock=clock)
        if r.status == "infeasible":
            value, y = _violation(p)
            if y is None or value <= 1e-9:
                return Relaxed("limit", None, None, data, done)
            lam, bound = -y, None
            gain = gain_of(t, branch, lam) - F.col("obj") * (1.0 if t.query.sense == "max" else -1.0)
            room = 1e-9 * float(np.abs(y) @ np.abs(p.A).max(1))
        elif r.status == "optimal":
            lam, bound = -r.duals, r.value if p.sense == "min" else -r.value
            gain = gain_of(t, branch, lam)
            room = 1e-8 * max(1e-6, float(np.abs(p.cost).max()))
        else:
            return Relaxed(r.status, None, None, data, done)
        more = collect_columns(frame.filter(gain > room).orderBy(gain.desc(), "tid").limit(WIDTH), t, WIDTH)
        before = len(data[0])
        data = _joined(data, more)
        if len(data[0]) == before:
            return Relaxed(r.status, bound, lam, data, done)
        if clock and clock.over():
            break
    return Relaxed("limit", None, None, data, ROUNDS)


@dataclass
class Reduced:
    solution: Solution
    chosen: dict[int, int]
    kept: int


def reduced_solve(frame: DataFrame, t: Translation, branch: int, limits: SolverLimits, most: int, known: tuple[float, dict[int, int]] | None = None) -> Reduced:
    """The optimum over a coefficient frame of any size. most: the columns that fit. known: objective and tuples of a package to begin with."""
    r = relaxation(frame, t, branch)
    if r.status in ("infeasible", "unbounded"):
        return Reduced(Solution(SolveStatus(r.status)), {}, 0)
    if r.status == "limit":
        return _whole(frame, t, branch, limits, most, known)
    sign = 1.0 if t.query.sense == "max" else -1.0
    best, chosen = known if known else (None, {})
    steps = nodes = 0
    clock = Clock(limits.seconds)

    def offer(data: tuple, lim: SolverLimits) -> Solution:
        nonlocal best, chosen, steps, nodes
        s = BranchAndBound(replace(lim, seconds=max(0.1, limits.seconds - clock.spent()))).solve(branch_problem(t, branch, *data))
        steps, nodes = steps + s.iterations, nodes + s.nodes
        if s.found and (best is None or sign * s.objective > sign * best):
            best, chosen = s.objective, {int(i): int(round(k)) for i, k in zip(data[0], s.x, strict=True) if k > 0.5}
        return s

    def ended(status: SolveStatus, kept: int) -> Reduced:
        return Reduced(Solution(status, np.zeros(0) if best is not None else None, best, r.bound, nodes, steps), chosen, kept)

    fast = replace(limits, gap=max(limits.gap, 1e-5), patience=100, nodes=min(limits.nodes, 2_000))
    gain, size = gain_of(t, branch, r.multipliers), max(1e-6, float(np.abs(r.data[2]).max(initial=0.0)))
    offer(r.data, fast)
    while True:
        gap = sign * (r.bound - best) if best is not None else INF
        if gap <= max(1e-9 * max(1.0, abs(best or 0.0)), limits.gap * abs(best or 0.0)):
            return ended(SolveStatus.OPTIMAL, len(r.data[0]))
        left = frame.filter(gain >= -gap - 1e-7 * size) if gap < INF else frame
        try:
            data = collect_columns(left, t, min(most, DIRECT_COLUMNS))
        except TooManyColumns:
            if clock.over():
                return ended(SolveStatus.LIMIT_TIME, 0)
            before = best
            offer(collect_columns(left.orderBy(gain.desc(), "tid").limit(NEAR), t, NEAR), fast)
            if best == before:
                return _whole(left, t, branch, limits, most, (best, chosen) if best is not None else None)
            continue
        s = offer(data, limits)
        good = s.status in (SolveStatus.OPTIMAL, SolveStatus.INFEASIBLE)
        return ended((SolveStatus.OPTIMAL if best is not None else SolveStatus.INFEASIBLE) if good else s.status, len(data[0]))


def _whole(frame: DataFrame, t: Translation, branch: int, limits: SolverLimits, most: int, known) -> Reduced:
    """All columns at once, where they fit."""
    best, chosen = known or (None, {})
    try:
        data = collect_columns(frame, t, most)
    except TooManyColumns:
        return Reduced(Solution(SolveStatus.LIMIT_MEMORY, np.zeros(0) if known else None, best), chosen, 0)
    s = BranchAndBound(limits).solve(branch_problem(t, branch, *data))
    if s.found and (best is None or (s.objective > best) == (t.query.sense == "max")):
        best, chosen = s.objective, {int(i): int(round(k)) for i, k in zip(data[0], s.x, strict=True) if k > 0.5}
    if best is not None and s.status is SolveStatus.INFEASIBLE:
        s.status = SolveStatus.OPTIMAL
    return Reduced(Solution(s.status, np.zeros(0) if best is not None else None, best, s.bound, s.nodes, s.iterations), chosen, len(data[0]))
