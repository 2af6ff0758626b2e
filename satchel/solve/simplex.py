"""A bounded primal simplex in numpy for programs with few rows and many columns.

Row activities are variables of their own (A x - r = 0, lo <= r <= hi), so any basis can start, also one left
over from a program with other bounds: basic variables outside their bounds are first driven in by the sum of
their violations. Columns are priced all at once; after many steps without progress the lowest index enters.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from .problem import INF, Clock

PRICE, PIVOT, FEAS = 1e-9, 1e-9, 1e-9
REFACTOR, STALL, MAX_STEPS = 40, 60, 20_000


@dataclass
class Basis:
    rows: np.ndarray  # basic variable of each row
    at_upper: np.ndarray  # of nonbasic variables

    def copy(self) -> Basis:
        return Basis(self.rows.copy(), self.at_upper.copy())


@dataclass
class LpResult:
    status: str  # optimal, infeasible, unbounded, limit
    x: np.ndarray | None = None
    value: float = INF
    reduced: np.ndarray | None = None
    basis: Basis | None = None
    steps: int = 0
    duals: np.ndarray | None = None  # of the rows


class Simplex:
    """Minimises cost @ x; bounds may change between calls of solve()."""

    def __init__(self, A: np.ndarray, lo: np.ndarray, hi: np.ndarray, cost: np.ndarray):
        self.m, self.n = A.shape
        self.unit = np.maximum(1e-12, np.abs(A).max(1, initial=1e-12))
        self.A = A / self.unit[:, None]
        self.row_lo, self.row_hi = lo / self.unit, hi / self.unit
        self.size = max(1.0, float(np.abs(cost).max(initial=0.0)))
        self.cost = cost / self.size

    def start(self) -> Basis:
        return Basis(np.arange(self.n, self.n + self.m), np.zeros(self.n + self.m, bool))

    def column(self, j: int) -> np.ndarray:
        if j < self.n:
            return self.A[:, j]
        out = np.zeros(self.m)
        out[j - self.n] = -1.0
        return out

    def _inverse(self, basis: Basis) -> np.ndarray:
        return np.linalg.inv(np.stack([self.column(j) for j in basis.rows], 1)) if self.m else np.zeros((0, 0))

    def solve(self, low: np.ndarray, high: np.ndarray, basis: Basis | None = None, clock: Clock | None = None) -> LpResult:
        m, n = self.m, self.n
        low, high = np.concatenate((low, self.row_lo)), np.concatenate((high, self.row_hi))
        if np.any(low > high + 1e-12):
            return LpResult("infeasible")
        basis = basis.copy() if basis else self.start()
        basic = np.zeros(n + m, bool)
        basic[basis.rows] = True
        up = basis.at_upper
        up[:] = np.where(np.isinf(high), False, np.where(np.isinf(low), True, up)) & ~basic
        free = np.isinf(low) & np.isinf(high)
        try:
            inverse = self._inverse(basis)
        except np.linalg.LinAlgError:
            return self.solve(low[:n], high[:n], None, clock)
        x = np.where(up, high, np.where(free, 0.0, np.where(np.isinf(low), 0.0, low)))
        movable = high > low
        cost = np.concatenate((self.cost, np.zeros(m)))

        def settle() -> None:
            x[basis.rows] = 0.0
            rest = self.A @ x[:n] - x[n:]
            x[basis.rows] = -inverse @ rest

        settle()
        steps = stalled = since = 0
        last = INF
        while True:
            rows = basis.rows
            xb, lb, hb = x[rows], low[rows], high[rows]
            room = FEAS * np.maximum(1.0, np.abs(np.where(np.isfinite(lb), lb, 0)) + np.abs(np.where(np.isfinite(hb), hb, 0)))
            under, over = xb < lb - room, xb > hb + room
            first = bool(under.any() or over.any())
            cb = over.astype(float) - under.astype(float) if first else cost[rows]
            y = cb @ inverse
            d = (0.0 if first else self.cost) - y @ self.A
            reduced = np.concatenate((d, y if first else y))  # a row's column is minus a unit vector
            value = float((lb - xb)[under].sum() + (xb - hb)[over].sum()) if first else float(cost[rows] @ xb + self.cost @ np.where(basic[:n], 0.0, x[:n]))
            gain = np.where(up, reduced, -reduced)
            gain[free] = np.abs(reduced[free])
            gain[basic | ~movable] = 0.0
            if stalled > STALL:
                can = np.flatnonzero(gain > PRICE)
                enter = int(can[0]) if len(can) else -1
            else:
                enter = int(np.argmax(gain)) if len(gain) else -1
                enter = enter if enter >= 0 and gain[enter] > PRICE else -1
            if enter < 0:
                if first:
                    return LpResult("infeasible", steps=steps)
                return LpResult("optimal", x[:n].copy(), value * self.size, d * self.size, basis, steps, y * self.size / self.unit)
            if steps >= MAX_STEPS or (clock and steps % 16 == 15 and clock.over()):
                return LpResult("limit", steps=steps)
            way = -1.0 if (up[enter] or (free[enter] and reduced[enter] > 0)) else 1.0
            w = inverse @ self.column(enter) * way  # basics move by -w per unit
            falls, rises = w > PIVOT, w < -PIVOT
            limit = np.full(m, INF)
            # A basic outside its bounds blocks where it comes in; one inside blocks where it would leave.
            stop_low = np.where(over, hb, lb)
            stop_high = np.where(under, lb, hb)
            f = falls & ~under
            limit[f] = (xb[f] - stop_low[f]) / w[f]
            r = rises & ~over
            limit[r] = (xb[r] - stop_high[r]) / w[r]
            limit = np.maximum(limit, 0.0)
            own = high[enter] - low[enter]
            t = float(limit.min(initial=INF))
            if min(t, own) == INF:
                return LpResult("unbounded" if not first else "infeasible", steps=steps)
            steps += 1
            if own <= t:
                x[rows] = xb - own * w
                x[enter] = low[enter] if up[enter] else high[enter]
                up[enter] = not up[enter]
            else:
                ties = np.flatnonzero(limit <= t + 1e-12 * (1 + t))
                leave = int(ties[np.argmin(rows[ties])]) if stalled > STALL else int(ties[np.argmax(np.abs(w[ties]))])
                out = int(rows[leave])
                x[rows] = xb - t * w
                x[enter] += way * t
                target = (stop_low if w[leave] > 0 else stop_high)[leave]
                x[out] = target
                up[out] = bool(target == high[out])
                if np.isinf(low[out]) and not up[out]:
                    up[out] = True
                basic[out], basic[enter] = False, True
                rows[leave] = enter
                pivot = w[leave] * way
                line = inverse[leave] / pivot
                inverse -= np.outer(w * way, line)
                inverse[leave] = line
                since += 1
                if since >= REFACTOR:
                    try:
                        inverse = self._inverse(basis)
                    except np.linalg.LinAlgError:
                        return LpResult("limit", steps=steps)
                    settle()
                    since = 0
            mark = value if not first else value + 1e30
            stalled = 0 if mark < last - 1e-12 * (1 + abs(last if last < INF else 0)) else stalled + 1
            last = min(last, mark)
