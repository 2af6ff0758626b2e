"""Coarse-fine evaluation: solve over group centroids, then replace each used centroid by tuples of its group.

A coarse variable stands for a group; its coefficients are the means over the group's eligible tuples (or the
stored centroids, where that is the same), its bound the tuples times their repetition. Only groups in the
coarse package are fetched, by one pruned scan. The fine search holds a stack of frames on the driver: a frame knows
the totals of what is chosen, the groups still open and those that failed. Replacing a group solves a program
over its tuples with bounds less what the rest of the package uses. If it fails, the frame is given up and
its parent tries the failing group first. Every limit ends the search honestly, and a package that comes out is
checked against all rows.
"""

from __future__ import annotations

import math
import random
import time
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lang.ast import INF, PackageQuery
from ..package.result import PackageResult
from ..partition.quad import Partitioning, quad_partition
from ..plans.coefficients import Translation, coefficient_frame, translate
from ..plans.rules import analyze, query_attributes
from ..solve.branch import BranchAndBound, conflict_set
from ..solve.problem import IlpProblem, Solution, SolverLimits, SolveStatus
from .reduced import relaxation

FETCH_ROWS = 2_000_000
#: Chosen groups with more tuples than this are partitioned more finely on Spark, until what is chosen has fewer.
REFINE_ROWS = 500_000
#: Groups of the hybrid remedy that one scan fetches.
HYBRID_FETCH = 16


@dataclass
class Coarse:
    """Groups with eligible tuples: mean coefficients (rows x m), mean objective, eligible tuples and bounds."""

    gids: list[str]
    C: np.ndarray
    obj: np.ndarray
    sizes: np.ndarray
    upper: np.ndarray

    def problem(self, t: Translation, branch: int, keep: np.ndarray | None = None) -> IlpProblem:
        own = t.branches[branch]
        at = np.arange(len(self.gids)) if keep is None else keep
        return IlpProblem(self.C[np.ix_(own, at)], t.lo(branch), t.hi(branch), self.obj[at], self.upper[at], t.query.sense, at)


@dataclass
class Group:
    """Eligible tuples of one group."""

    tids: np.ndarray
    C: np.ndarray
    obj: np.ndarray
    upper: np.ndarray
    ids: np.ndarray | None = None  # what the solver knows the columns by, where it isn't tids


@dataclass
class FineLimits:
    """seconds: of the direct attempt and of each remedy."""

    solves: int = 2_000
    seconds: float = 600.0
    columns: int = 100_000
    gap: float = 1e-3  # of coarse and fine programs
    nodes: int = 5_000  # while a program has no solution
    patience: int = 100  # nodes without a better solution that end a program which has one


@dataclass
class Counters:
    solves: int = 0
    backtracks: int = 0
    nodes: int = 0
    largest: int = 0
    deadline: float = INF
    limit: SolveStatus | None = None  # a limit that cut the search
    proven: bool | None = None  # whether the relaxation over all tuples is infeasible, once that was asked

    def spent(self, limits: FineLimits) -> bool:
        """Whether the time or solve limit is reached, which then is noted."""
        late = time.perf_counter() > self.deadline
        if late or self.solves >= limits.solves:
            self.limit = SolveStatus.LIMIT_TIME if late else SolveStatus.LIMIT_NODES
            return True
        return False

    def count(self, p: IlpProblem, s: Solution) -> Solution:
        if s.status in (SolveStatus.LIMIT_TIME, SolveStatus.LIMIT_NODES, SolveStatus.LIMIT_MEMORY):
            self.limit = s.status
        self.solves, self.nodes, self.largest = self.solves + 1, self.nodes + s.nodes, max(self.largest, p.n)
        return s


def coarse_frame(part: Partitioning, t: Translation) -> DataFrame:
    """gid, mean coefficients, mean objective and eligible tuples per group: one aggregation over the clustered relation."""
    frame = coefficient_frame(part.df, t, ("gid",))
    return frame.groupBy("gid").agg(*(F.avg(c).alias(c) for c in t.names), F.avg("obj").alias("obj"), F.count(F.lit(1)).alias("n"))


def stored_frame(part: Partitioning, t: Translation) -> DataFrame:
    """The same from stored centroids, without reading tuples; exact where no filter applies and all terms are plain sums of partition attributes."""
    centres = part.groups.select("gid", "n", *(F.col(f"avg_{a}").alias(a) for a in part.attrs))
    return centres.select("gid", *(r.column.alias(f"c_{i}") for i, r in enumerate(t.rows)), F.expr(f"CAST({t.objective} AS DOUBLE)").alias("obj"), "n")


def load_coarse(frame: DataFrame, t: Translation, most: int) -> Coarse | None:
    """None where more groups than fit on the driver have eligible tuples."""
    got = frame.limit(most + 1).toArrow().sort_by("gid")  # one more than fits tells that it doesn't, without a scan to count
    n = len(got)
    if n > most:
        return None
    sizes = got["n"].to_numpy().astype(float)
    upper = sizes * t.query.upper if t.query.upper < INF else np.full(n, INF)
    return Coarse(got["gid"].to_pylist(), np.array([got[c].to_numpy() for c in t.names]).reshape(len(t.rows), n), got["obj"].to_numpy(), sizes, upper)


def fetch_groups(part: Partitioning, t: Translation, gids: list[str], most: int = FETCH_ROWS) -> dict[str, Group]:
    """Coefficients of the tuples of a few groups: one scan, pruned by the clustering on gid."""
    if not gids:
        return {}
    frame = coefficient_frame(part.df.filter(F.col("gid").isin(gids)), t, ("gid", "tid"))
    got = frame.limit(most + 1).toArrow()
    if len(got) > most:
        raise MemoryError(f"more than {most} tuples in {len(gids)} groups, which is what fits on the driver")
    coded = got["gid"].combine_chunks().dictionary_encode()
    names, codes = coded.dictionary.to_pylist(), coded.indices.to_numpy()
    columns = [got[c].to_numpy() for c in t.names]
    tids, obj = got["tid"].to_numpy(), got["obj"].to_numpy()
    upper = np.nan_to_num(got["ub"].to_numpy(zero_copy_only=False).astype(float), nan=INF)
    order = np.lexsort((tids, codes))
    ends = np.searchsorted(codes[order], np.arange(len(names) + 1))
    place = {g: order[ends[i] : ends[i + 1]] for i, g in enumerate(names)}
    out = {}
    for g in gids:
        at = place.get(g, order[:0])
        out[g] = Group(tids[at], np.array([c[at] for c in columns]).reshape(len(t.rows), len(at)), obj[at], upper[at])
    return out


@dataclass
class _Frame:
    totals: np.ndarray
    open: list[str]
    queue: list[str]
    failed: set[str] = field(default_factory=set)

    def blame(self, failed: set[str]) -> None:
        """Groups that failed further down are tried first from here on."""
        self.failed |= failed
        self.queue.sort(key=lambda g: g not in failed)


class FineSearch:
    """Replaces the groups of a coarse answer one by one."""

    def __init__(self, t: Translation, branch: int, groups: dict[str, Group], centres: dict[str, np.ndarray], solver, limits: FineLimits, counters: Counters, rank: Callable[[list[str]], list[str]]):
        self.t, self.branch, self.groups, self.centres = t, branch, groups, centres
        self.solver = solver if isinstance(solver, Bounded) else Bounded(solver, limits.columns, counters, limits)
        self.limits, self.counters, self.rank = limits, counters, rank
        self.own = t.branches[branch]
        self.lo, self.hi = t.lo(branch), t.hi(branch)
        self.ended = ""

    def step(self, gid: str, totals: np.ndarray, times: int) -> Solution:
        """Tuples of one group that take the place of its centroid, given what the others use."""
        g = self.groups[gid]
        kept = totals - times * self.centres[gid][self.own]
        p = IlpProblem(g.C[self.own], self.lo - kept, self.hi - kept, g.obj, g.upper, self.t.query.sense, g.tids if g.ids is None else g.ids)
        return self.solver.solve(p)

    def run(self, support: dict[str, int], fixed: dict[str, tuple[dict[int, int], np.ndarray]] | None = None) -> dict[int, int] | None:
        """tid -> multiplicity, or None. fixed: groups that are tuples already, with their aggregates."""
        begin = time.perf_counter()
        picks: dict[str, dict[int, int]] = {}
        base = np.zeros(len(self.own))
        for g, (chosen, total) in (fixed or {}).items():
            picks[g] = chosen
            base = base + total[self.own]
        totals = base + sum((k * self.centres[g][self.own] for g, k in support.items()), np.zeros(len(self.own)))
        first = self.rank(list(support))
        if not first:
            return self._gathered(picks) if self._holds(totals) else None
        stack, path = [_Frame(totals, first, list(first))], []
        urgent: dict[str, int] = {}
        while stack:
            late = time.perf_counter() - begin > self.limits.seconds
            if self.counters.spent(self.limits) or late:
                self.counters.limit = SolveStatus.LIMIT_TIME if late else self.counters.limit
                self.ended = "limit"
                return None
            top = stack[-1]
            if not top.queue:
                stack.pop()
                if path:
                    picks.pop(path.pop(), None)
                if stack:  # all that failed below comes first above
                    stack[-1].blame(top.failed)
                continue
            gid = top.queue.pop(0)
            found = self.step(gid, top.totals, support[gid])
            if found.found:
                group = self.groups[gid]
                rest = [g for g in top.open if g != gid]
                picks[gid] = {int(i): int(round(x)) for i, x in zip(group.tids, found.x, strict=True) if x > 0.5}
                after = top.totals - support[gid] * self.centres[gid][self.own] + group.C[self.own] @ found.x
                path.append(gid)
                if not rest:
                    return self._gathered(picks)
                stack.append(_Frame(after, rest, sorted(rest, key=lambda g: -urgent.get(g, 0))))
                continue
            top.failed.add(gid)
            self.counters.backtracks += 1
            if len(stack) > 1:  # give this frame up and let its parent begin with what failed
                urgent[gid] = urgent.get(gid, 0) + 1
                stack.pop()
                picks.pop(path.pop(), None)
                stack[-1].blame(top.failed)
        return None

    def _gathered(self, picks: dict[str, dict[int, int]]) -> dict[int, int]:
        return {i: k for chosen in picks.values() for i, k in chosen.items()}

    def _holds(self, totals: np.ndarray) -> bool:
        return bool(np.all(totals >= self.lo - 1e-6) and np.all(totals <= self.hi + 1e-6))


def group_rank(order: str, coarse: Coarse, support: dict[str, int], seed: int) -> Callable[[list[str]], list[str]]:
    """The order in which groups are replaced: random, size (large first) or multiplicity (high first)."""
    sizes = dict(zip(coarse.gids, coarse.sizes, strict=True))

    def rank(gids: list[str]) -> list[str]:
        gids = sorted(gids)
        if order == "random":
            random.Random(seed).shuffle(gids)
        elif order == "size":
            gids.sort(key=lambda g: (-sizes[g], g))
        else:
            gids.sort(key=lambda g: (-support.get(g, 0), g))
        return gids

    return rank


class Bounded:
    """Solves programs of any size by programs of at most budget columns each, by the coarse and fine steps themselves.

    Too many columns are dealt into budget runs of like ones; the means of the runs make a program, whose used runs are then
    replaced one by one, with backtracking, by programs over their own columns, which are dealt again where they are too many.
    An answer is feasible but need not be optimal; none found is no proof that there is none. Counts every program.
    """

    def __init__(self, solver, budget: int, counters: Counters, limits: FineLimits, order: Callable[[IlpProblem], np.ndarray] | None = None, weight: Callable[[IlpProblem], np.ndarray] | None = None):
        self.solver, self.budget, self.counters, self.limits = solver, max(2, budget), counters, limits
        self.order, self.weight = order or _by_value, weight or (lambda p: np.ones(p.n))

    def solve(self, p: IlpProblem) -> Solution:
        if p.n <= self.budget:
            return self.counters.count(p, self.solver.solve(p))
        runs = np.array_split(self.order(p), self.budget)
        w = self.weight(p)
        mean = np.stack([np.append(p.A[:, r] @ w[r], p.cost[r] @ w[r]) / w[r].sum() for r in runs], 1)
        top = IlpProblem(mean[:-1], p.lo, p.hi, mean[-1], np.array([p.upper[r].sum() for r in runs]), p.sense, np.arange(len(runs)))
        s = self.counters.count(top, self.solver.solve(top))
        if not s.found:
            return s
        support = {f"{j:09d}": int(round(k)) for j, k in enumerate(s.x) if k > 0.5}
        groups = {g: Group(runs[int(g)], p.A[:, runs[int(g)]], p.cost[runs[int(g)]], p.upper[runs[int(g)]], p.ids[runs[int(g)]]) for g in support}
        shape = _Shape(p.sense, list(range(len(p.lo))), p.lo, p.hi)
        search = FineSearch(shape, 0, groups, {g: mean[:-1, int(g)] for g in support}, self, self.limits, self.counters, sorted)
        picked = search.run(support)
        if picked is None:
            return Solution(self.counters.limit or SolveStatus.INFEASIBLE)
        x = np.zeros(p.n)
        x[list(picked)] = list(picked.values())
        return Solution(SolveStatus.FEASIBLE, x, float(p.cost @ x))


def _by_value(p: IlpProblem) -> np.ndarray:
    return np.lexsort((*p.A, p.cost)) if len(p.A) else np.argsort(p.cost, kind="stable")


def hierarchy_coarse(coarse: Coarse, t: Translation, branch: int, budget: int, solver, counters: Counters, limits: FineLimits = FineLimits()) -> Solution:
    """The coarse answer, also for more groups than the budget: neighbours by path are solved as one, then taken apart again."""
    p = coarse.problem(t, branch)  # in the order of gids, so of paths
    return Bounded(solver, budget, counters, limits, lambda q: np.argsort(q.ids, kind="stable"), lambda q: coarse.sizes[q.ids]).solve(p)


def fine_recursive(solver, budget: int, counters: Counters | None = None, limits: FineLimits = FineLimits()) -> Bounded:
    """A solver for groups of more tuples than the budget: runs of like tuples become groups."""
    return Bounded(solver, budget, counters or Counters(), limits)


def _hybrid(part: Partitioning, t: Translation, branch: int, coarse: Coarse, solver, limits: FineLimits, counters: Counters, seed: int):
    """Groups in random order: one by its tuples, the others by centroids. Yields a fixed group, its tuples and the others' support."""
    order = list(range(len(coarse.gids)))
    random.Random(seed).shuffle(order)
    groups: dict[str, Group] = {}
    for k, j in enumerate(order):
        if counters.spent(limits):
            return
        if coarse.gids[j] not in groups:
            upto = int(np.searchsorted(np.cumsum(coarse.sizes[order[k : k + HYBRID_FETCH]]), REFINE_ROWS, "right"))
            groups = fetch_groups(part, t, [coarse.gids[i] for i in order[k : k + max(1, upto)]])
        gid, g = coarse.gids[j], groups[coarse.gids[j]]
        rest = np.array([i for i in range(len(coarse.gids)) if i != j], int)
        p = coarse.problem(t, branch, rest)
        own = t.branches[branch]
        both = IlpProblem(np.hstack((g.C[own], p.A)), p.lo, p.hi, np.concatenate((g.obj, p.cost)), np.concatenate((g.upper, p.upper)), p.sense, np.arange(len(g.tids) + len(rest)))
        s = Bounded(solver, limits.columns, counters, limits).solve(both)
        if s.found:
            x = s.x[: len(g.tids)]
            chosen = {int(i): int(round(k)) for i, k in zip(g.tids, x, strict=True) if k > 0.5}
            support = {coarse.gids[i]: int(round(k)) for i, k in zip(rest, s.x[len(g.tids) :], strict=True) if k > 0.5}
            yield gid, chosen, g.C @ x, support


def coarse_fine(part: Partitioning, q: PackageQuery, limits: FineLimits = FineLimits(), solver=None, order: str = "random", seed: int = 0, remedies: tuple[str, ...] = ("hybrid",), rep_mode: str = "eligible", budget: int | None = None, parallel: str | None = None, width: int = 4) -> PackageResult:
    """Evaluates a query over a partitioning.

    remedies, tried in turn when the coarse or fine step finds nothing: hybrid (every group), smaller_tau, drop, merge (from
    the given groups down to one, whose tuples are the original problem). Each goes on until it is exhausted or a limit is
    reached; the status is infeasible only if no limit cut the search.
    rep_mode: eligible (means over tuples that pass the filter) or stored (centroids of the partitioning).
    budget: the most coarse variables at once. parallel: None, groups (all groups at once, then repair) or orders.
    """
    begin = time.perf_counter()
    analyze(part.df.drop("gid"), q)
    t = translate(part.df, q)
    solver = solver or BranchAndBound(SolverLimits(seconds=limits.seconds, gap=limits.gap, nodes=limits.nodes, patience=limits.patience))
    translated = time.perf_counter()
    out = PackageResult(q, part.df.drop("gid"), SolveStatus.INFEASIBLE)
    out.timing["translate"] = translated - begin
    counters = Counters(deadline=time.perf_counter() + limits.seconds)

    def attempt(groups: Partitioning, hybrid: bool) -> None:
        try:
            _attempt(groups, t, q, out, counters, solver, limits, order, seed, hybrid, rep_mode, budget, parallel, width)
        except MemoryError as e:
            counters.limit, out.note = SolveStatus.LIMIT_MEMORY, str(e)

    attempt(part, "hybrid" in remedies)
    out.attempts.append("direct" + (" or hybrid" if "hybrid" in remedies else ""))
    current = part
    for remedy in remedies:
        if out.found or out.status is SolveStatus.UNBOUNDED or remedy == "hybrid" or _impossible(part, t, counters):
            continue
        counters.deadline = time.perf_counter() + limits.seconds
        current, last = part if remedy == "merge" else current, False
        while not (out.found or last or counters.spent(limits)):
            if remedy == "smaller_tau":
                if current.tau <= 1:
                    break
                current = current.refine(max(1, current.tau // 4))
            elif remedy == "drop":
                gone = _blocking_attributes(current, t, q)
                if not gone or len(current.attrs) <= 1:
                    break
                current = current.drop_attributes(gone)
            else:
                n = current.groups.count()
                current, last = current.merge() if n > 1 else current, n <= 2
                if last:
                    counters.limit = None  # the tuples of the only group are the original problem, so its answer counts
            attempt(current, last)
            out.attempts.append(remedy)
    if counters.limit and out.status is SolveStatus.INFEASIBLE and not counters.proven:
        out.status = counters.limit
    out.counters = {"solves": counters.solves, "backtracks": counters.backtracks, "nodes": counters.nodes, "largest": counters.largest}
    out.timing["total"] = time.perf_counter() - begin
    out.timing["solve"] = out.timing["total"] - out.timing["translate"] - out.timing.get("load", 0.0)
    return out


def _impossible(part: Partitioning, t: Translation, counters: Counters) -> bool:
    """Whether no alternative has a solution even in fractions of tuples, over all tuples; then no remedy can find a package."""
    if counters.proven is None:
        frame = coefficient_frame(part.df, t)
        counters.proven = all(relaxation(frame, t, b).status == "infeasible" for b in range(len(t.branches)))
    return counters.proven


def _blocking_attributes(part: Partitioning, t: Translation, q: PackageQuery) -> set[str]:
    """Partition attributes in an irreducible set of rows that the centroids can't satisfy; those in all rows otherwise left."""
    coarse = load_coarse(coarse_frame(part, t), t, 1 << 20)
    rows = conflict_set(coarse.problem(t, 0)) if coarse else []
    text = " ".join(t.rows[t.branches[0][i]].sql for i in rows) or " ".join(query_attributes(q))
    hit = {a for a in part.attrs if a in text}
    return hit if hit and len(hit) < len(part.attrs) else set(sorted(hit)[:1])


def _attempt(part, t, q, out: PackageResult, counters, solver, limits, order, seed, hybrid, rep_mode, budget, parallel, width) -> None:
    start = time.perf_counter()
    frame = stored_frame(part, t) if rep_mode == "stored" else coarse_frame(part, t)
    most = limits.columns
    coarse = load_coarse(frame, t, max(most, 1_000_000))
    out.timing["load"] = out.timing.get("load", 0.0) + time.perf_counter() - start
    if coarse is None:
        out.status, out.note = SolveStatus.LIMIT_MEMORY, "more groups than the driver holds: use a larger tau"
        return
    answers = []
    for b in range(len(t.branches)):
        s = hierarchy_coarse(coarse, t, b, budget or most, solver, counters, limits)
        if s.status is SolveStatus.UNBOUNDED:
            out.status = s.status
            return
        answers.append((b, s))
    found = [(b, s) for b, s in answers if s.found]
    found.sort(key=lambda x: x[1].objective if q.sense == "min" else -x[1].objective)
    for b, s in found:
        support = {coarse.gids[i]: int(round(k)) for i, k in enumerate(s.x) if k > 0.5}
        if _fine(part, t, b, coarse, support, None, out, counters, solver, limits, order, seed, parallel, width, budget):
            out.bound = s.objective
            return
    if hybrid and not counters.spent(limits) and not _impossible(part, t, counters):
        for b in range(len(t.branches)):
            for gid, chosen, total, support in _hybrid(part, t, b, coarse, solver, limits, counters, seed):
                if _fine(part, t, b, coarse, support, {gid: (chosen, total)}, out, counters, solver, limits, order, seed, None, width, budget):
                    out.attempts.append("hybrid")
                    return


def _fine(part, t, b, coarse, support, fixed, out: PackageResult, counters, solver, limits, order, seed, parallel, width, budget=None) -> bool:
    start = time.perf_counter()
    at = {g: i for i, g in enumerate(coarse.gids)}
    centres = {g: coarse.C[:, at[g]] for g in support}
    if parallel == "groups" and not fixed:  # the groups stay where they are; only what is chosen comes to the driver
        if (done := _parallel_groups(part, t, b, support, centres, solver)) is not None:
            out.status, out.chosen, out.branch, out.objective = SolveStatus.FEASIBLE, done[0], b, done[1]
            counters.solves += len(support)
            return True
        start = time.perf_counter()
    if not fixed and (rows := sum(coarse.sizes[at[g]] for g in support)) > REFINE_ROWS:
        tau = min(REFINE_ROWS // 8, math.ceil(part.tau / 4))
        if tau >= part.tau:
            raise MemoryError(f"{rows:.0f} tuples in {len(support)} groups, which can't be finer")
        kept = part.df.filter(F.col("gid").isin(sorted(support))).drop("gid")
        finer = quad_partition(kept, part.attrs, tau, part.radius, part.digits)
        out.timing["load"] = out.timing.get("load", 0.0) + time.perf_counter() - start
        _attempt(finer, t, t.query, out, counters, solver, limits, order, seed, False, "eligible", budget, parallel, width)
        return out.found
    groups = fetch_groups(part, t, sorted(support))
    out.timing["load"] = out.timing.get("load", 0.0) + time.perf_counter() - start
    inner = Bounded(solver, budget or limits.columns, counters, limits)
    search = FineSearch(t, b, groups, centres, inner, limits, counters, group_rank(order, coarse, support, seed))
    picked = None
    if parallel == "orders" and not fixed:
        picked = _parallel_orders(part.df.sparkSession, t, b, groups, centres, support, solver, limits, seed, width)
    if picked is None:
        picked = search.run(support, fixed)
    if picked is None:
        out.note = search.ended or "no order of the groups succeeded"
        return False
    objective = _checked(picked, groups, fixed, part, t, b)
    if objective is None:
        return False
    out.status, out.chosen, out.branch, out.objective = SolveStatus.FEASIBLE, picked, b, objective
    return True


def _holding(total: np.ndarray, t: Translation, b: int) -> bool:
    """Whether the rows of an alternative hold for these aggregates."""
    own = t.branches[b]
    room = 1e-6 * np.maximum(1.0, np.abs(total[own]))
    return bool(np.all(total[own] >= t.lo(b) - room) and np.all(total[own] <= t.hi(b) + room))


def _checked(picked: dict[int, int], groups: dict[str, Group], fixed, part: Partitioning, t: Translation, b: int) -> float | None:
    """The objective if all rows hold over the chosen tuples, else None."""
    known = dict(groups)
    if fixed:
        known |= fetch_groups(part, t, list(fixed))
    total, value = np.zeros(len(t.rows)), 0.0
    for g in known.values():
        x = np.array([picked.get(int(i), 0) for i in g.tids], float)
        total, value = total + g.C @ x, value + float(g.obj @ x)
    return value if _holding(total, t, b) else None


def _parallel_groups(part: Partitioning, t: Translation, b: int, support, centres, solver) -> tuple[dict[int, int], float] | None:
    """Every used group is solved at the same time against the coarse rest: tuples and objective, or None if the parts don't fit together.

    Only chosen tuples come back, with their coefficients, so the check needs no further scan.
    """
    own = t.branches[b]
    totals = sum((k * centres[g][own] for g, k in support.items()), np.zeros(len(own)))
    lo, hi, sense, names = t.lo(b), t.hi(b), t.query.sense, [f"c_{i}" for i in own]
    columns = ["tid", *t.names, "obj"]

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        gid = pdf["gid"].iloc[0]
        pdf = pdf.sort_values("tid")
        kept = totals - support[gid] * centres[gid][own]
        upper = pdf["ub"].astype(float).fillna(INF).to_numpy()
        s = solver.solve(IlpProblem(pdf[names].to_numpy().T, lo - kept, hi - kept, pdf["obj"].to_numpy(), upper, sense, pdf["tid"].to_numpy()))
        if not s.found:
            return pdf.head(1)[columns].assign(x=-1)
        return pdf[columns].assign(x=np.round(s.x).astype("int64"))[lambda d: d["x"] != 0]

    frame = coefficient_frame(part.df.filter(F.col("gid").isin(sorted(support))), t, ("gid", "tid"))
    rows = frame.groupBy("gid").applyInPandas(solve, "tid long, " + ", ".join(f"{c} double" for c in t.names) + ", obj double, x long").collect()
    if any(r["x"] < 0 for r in rows):
        return None
    total = sum((r["x"] * np.array([r[c] for c in t.names], float) for r in rows), np.zeros(len(t.rows)))
    return ({r["tid"]: r["x"] for r in rows}, float(sum(r["x"] * r["obj"] for r in rows))) if _holding(total, t, b) else None


def _parallel_orders(spark, t: Translation, b: int, groups, centres, support, solver, limits: FineLimits, seed: int, width: int) -> dict[int, int] | None:
    """Several random orders at once, one task each; the first (by seed) that succeeds."""
    own, lo, hi = t.branches[b], t.lo(b), t.hi(b)
    shape = _Shape(t.query.sense, own, lo, hi)

    def run(batches):
        for pdf in batches:
            for s in pdf["seed"]:
                ranked = sorted(support)
                random.Random(int(s)).shuffle(ranked)
                search = FineSearch(shape, 0, groups, centres, solver, limits, Counters(), lambda gids, r=ranked: [g for g in r if g in set(gids)])
                for tid, k in (search.run(support) or {}).items():
                    yield pd.DataFrame({"seed": [s], "tid": [tid], "k": [k]})

    seeds = spark.createDataFrame([(seed + i,) for i in range(width)], "seed long").repartition(width, "seed")
    rows = seeds.mapInPandas(run, "seed long, tid long, k long").collect()
    first = min((r.seed for r in rows), default=None)
    return {r.tid: r.k for r in rows if r.seed == first} if first is not None else None


class _Shape:
    """The parts of a translation that a search needs in a task."""

    def __init__(self, sense: str, own: list[int], lo: np.ndarray, hi: np.ndarray):
        self.query = PackageQuery(sense=sense)
        self.branches, self._lo, self._hi = [own], lo, hi

    def lo(self, _: int) -> np.ndarray:
        return self._lo

    def hi(self, _: int) -> np.ndarray:
        return self._hi
