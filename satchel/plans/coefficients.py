"""Coefficient frames: one scan of the relation gives every row's coefficients, the objective and the bound."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lang.ast import INF, PackageQuery
from ..scratch import stored
from ..solve.problem import IlpProblem, SolverLimits
from .rules import LinearRow, linear_branches, objective_sql


def with_tid(df: DataFrame, key: list[str] | None = None) -> DataFrame:
    """df with a unique long tid per row, in key order where a key is given; written once, so it stays the same."""
    if "tid" in df.columns:
        return df
    if key:
        n = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
        df = df.repartitionByRange(n, *key).sortWithinPartitions(*key)
    return stored(df.withColumn("tid", F.monotonically_increasing_id()), "tid")


def eligible(df: DataFrame, q: PackageQuery) -> DataFrame:
    return df.filter(q.where) if q.where else df


@dataclass
class Translation:
    """A query's rows (of all alternatives, each once), which rows each alternative needs, and its frame's columns."""

    query: PackageQuery
    rows: list[LinearRow]
    branches: list[list[int]]
    objective: str

    @property
    def names(self) -> list[str]:
        return [f"c_{i}" for i in range(len(self.rows))]

    def lo(self, branch: int) -> np.ndarray:
        return np.array([self.rows[i].lo for i in self.branches[branch]])

    def hi(self, branch: int) -> np.ndarray:
        return np.array([self.rows[i].hi for i in self.branches[branch]])


def translate(df: DataFrame, q: PackageQuery) -> Translation:
    rows: list[LinearRow] = []
    branches = []
    for branch in linear_branches(df, q):
        own = []
        for r in branch:
            at = next((i for i, x in enumerate(rows) if (x.sql, x.lo, x.hi) == (r.sql, r.lo, r.hi)), None)
            if at is None:
                at = len(rows)
                rows.append(r)
            own.append(at)
        branches.append(sorted(set(own)))
    return Translation(q, rows, branches, objective_sql(q))


def coefficient_frame(df: DataFrame, t: Translation, keep: tuple[str, ...] = ("tid",)) -> DataFrame:
    """keep, c_0.., obj and ub of every eligible tuple, by one narrow scan."""
    upper = F.lit(None if t.query.upper == INF else t.query.upper).cast("double").alias("ub")
    columns = [r.column.alias(f"c_{i}") for i, r in enumerate(t.rows)]
    return eligible(df, t.query).select(*keep, *columns, F.expr(f"CAST({t.objective} AS DOUBLE)").alias("obj"), upper)


def base_relations(df: DataFrame, t: Translation, mode: str = "single") -> DataFrame | list[DataFrame]:
    """The rows' base relations: coefficients by one scan (single), or one narrow frame for each row (separate)."""
    if mode == "single":
        return coefficient_frame(df, t)
    return [eligible(df, t.query).select("tid", r.column.alias("c")).filter("c <> 0") for r in t.rows]


class TooManyColumns(Exception):
    """More columns than the limits allow on the driver."""


def collect_columns(frame: DataFrame, t: Translation, most: int):
    """tids, coefficients (rows x n), objective and bounds, by one scan that stops at one column more than fits."""
    got = frame.limit(most + 1).toArrow()
    n = len(got)
    if n > most:
        raise TooManyColumns(f"more than {most} columns, which is what fits")
    order = np.argsort(got["tid"].to_numpy(), kind="stable")
    C = np.array([got[c].to_numpy()[order] for c in t.names]).reshape(len(t.rows), n)
    upper = np.nan_to_num(got["ub"].to_numpy(zero_copy_only=False).astype(float)[order], nan=INF)
    return got["tid"].to_numpy()[order], C, got["obj"].to_numpy()[order], upper


def branch_problem(t: Translation, branch: int, tids, C, obj, upper) -> IlpProblem:
    own = t.branches[branch]
    return IlpProblem(C[own], t.lo(branch), t.hi(branch), obj, upper, t.query.sense, tids, [t.rows[i].name for i in own])


def indicator_problem(t: Translation, tids, C, obj, upper) -> IlpProblem | None:
    """All alternatives in one program: a 0-1 column each, of which one must be 1, frees the others' rows by a large constant.

    None where no finite constant is known: repetition is unlimited and no row bounds the count.
    """
    n, k = len(tids), len(t.branches)
    everywhere = set.intersection(*map(set, t.branches))
    counts = [r.hi for i, r in enumerate(t.rows) if i in everywhere and r.sql == "1.0" and r.hi < INF]
    most = min(counts, default=INF)
    rows, lo, hi, names = [], [], [], []
    for i, r in enumerate(t.rows):
        if i in everywhere:
            rows.append(np.concatenate((C[i], np.zeros(k))))
            lo.append(r.lo)
            hi.append(r.hi)
            names.append(r.name)
    for b, branch in enumerate(t.branches):
        for i in sorted(set(branch) - everywhere):
            c, r = C[i], t.rows[i]
            least = min(float(np.minimum(c * np.where(np.isinf(upper), 0 if most < INF else INF, upper), 0).sum()) if most == INF or np.all(upper < INF) else -INF, 0.0)
            top = float(np.maximum(c * np.where(np.isinf(upper), 0 if most < INF else INF, upper), 0).sum()) if most == INF or np.all(upper < INF) else INF
            if most < INF:
                least, top = max(least, most * min(0.0, float(c.min(initial=0)))), min(top, most * max(0.0, float(c.max(initial=0))))
            mark = np.zeros(k)
            if r.lo > -INF:
                if not np.isfinite(least):
                    return None
                mark[b] = -(r.lo - least)
                rows.append(np.concatenate((c, mark)))
                lo.append(least)
                hi.append(INF)
                names.append(f"{r.name}_if{b}")
            mark = np.zeros(k)
            if r.hi < INF:
                if not np.isfinite(top):
                    return None
                mark[b] = top - r.hi
                rows.append(np.concatenate((c, mark)))
                lo.append(-INF)
                hi.append(top)
                names.append(f"{r.name}_if{b}")
    rows.append(np.concatenate((np.zeros(n), np.ones(k))))
    lo.append(1.0)
    hi.append(float(k))
    return IlpProblem(np.array(rows), np.array(lo), np.array(hi), np.concatenate((obj, np.zeros(k))), np.concatenate((upper, np.ones(k))), t.query.sense, np.concatenate((tids, -1 - np.arange(k))), [*names, "some"])


def limits_columns(limits: SolverLimits, t: Translation) -> int:
    return limits.columns(len(t.rows) + len(t.branches))
