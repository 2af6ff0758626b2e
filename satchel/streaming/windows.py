"""Packages over streams: one per event-time window, and group statistics kept up to date."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.listener import StreamingQueryListener

from ..lang.ast import INF, PackageQuery
from ..partition.quad import Partitioning, scaled
from ..plans.coefficients import branch_problem, coefficient_frame, translate
from ..solve.branch import BranchAndBound
from ..solve.problem import SolverLimits

RESULT = "window_start timestamp, status string, objective double, size long, columns long"


def windowed_packages(events: DataFrame, q: PackageQuery, time_col: str, key: str, window: str = "1 day", watermark: str = "1 hour", limits: SolverLimits = SolverLimits(seconds=30), slide: str | None = None, gap: str | None = None, by: str | None = None) -> DataFrame:
    """One package per window of a batch or stream. On a stream, append mode answers a window once the watermark passes it.

    Windows tumble, or start every slide where that is given; with gap, a window is a session that ends when nothing came
    for so long (window is not used then). by: a column whose values have windows of their own; sessions of a stream need one.

    A window's eligible tuples are gathered as coefficients only; a window must fit the memory limit.
    """
    rows = events.withColumn(time_col, F.col(time_col).cast("timestamp"))
    rows = rows.withWatermark(time_col, watermark) if events.isStreaming else rows
    keyed = rows.withColumn("tid", F.col(key).cast("long"))
    t = translate(keyed, q)
    own = [by] if by else []
    frame = coefficient_frame(keyed, t, ("tid", time_col, *own))
    span = F.session_window(time_col, gap) if gap else F.window(time_col, window, slide)
    grouped = frame.groupBy(span.alias("window"), *own).agg(F.sort_array(F.collect_list(F.struct("tid", *t.names, "obj", "ub"))).alias("rows"))
    shape = (t.names, [list(b) for b in t.branches], [(t.lo(b), t.hi(b)) for b in range(len(t.branches))], q.sense)

    def solve(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names, branches, bounds, sense = shape
        from ..solve.problem import IlpProblem

        for pdf in batches:
            out = []
            for start, items in zip(pdf["window_start"], pdf["rows"], strict=True):
                C = np.array([[float(r[c]) for r in items] for c in names]).reshape(len(names), len(items))
                obj = np.array([float(r["obj"]) for r in items])
                upper = np.array([INF if r["ub"] is None else float(r["ub"]) for r in items])
                best = None
                for branch, (lo, hi) in zip(branches, bounds, strict=True):
                    s = BranchAndBound(limits).solve(IlpProblem(C[branch], lo, hi, obj, upper, sense, np.arange(len(obj))))
                    if best is None or (s.found and (not best.found or (s.objective < best.objective) == (sense == "min"))):
                        best = s
                out.append((start, best.status.value, best.objective, int(best.x.sum()) if best.found else 0, len(obj)))
            found = pd.DataFrame(out, columns=["window_start", "status", "objective", "size", "columns"])
            yield found.assign(**{by: pdf[by].to_numpy()}) if by else found

    schema = RESULT + (f", `{by}` {keyed.schema[by].dataType.simpleString()}" if by else "")
    return grouped.select(F.col("window.start").alias("window_start"), "rows", *own).mapInPandas(solve, schema)


class LateRows(StreamingQueryListener):
    """Counts, per query id, what stateful operators drop as later than the watermark: spark.streams.addListener(LateRows()).

    Rows of one window that a task combines before they reach the operator count once.
    """

    def __init__(self):
        self.dropped: dict[str, int] = {}

    def onQueryStarted(self, event) -> None:
        self.dropped.setdefault(str(event.id), 0)

    def onQueryProgress(self, event) -> None:
        key = str(event.progress.id)
        self.dropped[key] = self.dropped.get(key, 0) + sum(s.numRowsDroppedByWatermark for s in event.progress.stateOperators)

    def onQueryIdle(self, event) -> None:
        pass

    def onQueryTerminated(self, event) -> None:
        pass


def route(rows: DataFrame, part: Partitioning) -> DataFrame:
    """rows with the gid of the nearest centroid (relative to the overall spread); for tuples that arrive after partitioning.

    The centroids are compared in one expression, so this takes partitionings of up to a few hundred groups.
    """
    centres = part.groups.select("gid", *(f"avg_{a}" for a in part.attrs)).orderBy("gid").limit(513).collect()
    if len(centres) > 512:
        raise ValueError("routing takes at most 512 groups; cut the partitioning first")
    spread = part.groups.agg(*(F.greatest(F.max(f"max_{a}") - F.min(f"min_{a}"), F.lit(1e-9)).alias(a) for a in part.attrs)).first()
    options = [F.struct(sum((((F.col(a) - F.lit(float(c[f"avg_{a}"]))) / F.lit(float(spread[a]))) ** 2 for a in part.attrs), F.lit(0.0)).alias("d"), F.lit(c.gid).alias("gid")) for c in centres]
    return rows.withColumn("gid", F.array_min(F.array(*options))["gid"])


def maintained_statistics(rows: DataFrame, part: Partitioning) -> DataFrame:
    """gid, n and sums of routed tuples: on a stream in update or complete mode, a running representative relation."""
    routed = route(rows, part)
    return routed.groupBy("gid").agg(F.count(F.lit(1)).alias("n"), *(F.sum(scaled(a, part.digits)).alias(f"sum_{a}") for a in part.attrs))


def overfull(statistics: DataFrame, part: Partitioning) -> DataFrame:
    """Groups that outgrew tau with what has arrived, to be partitioned further."""
    joined = part.groups.select("gid", F.col("n").alias("before")).join(statistics.select("gid", "n"), "gid", "left")
    return joined.withColumn("now", F.col("before") + F.coalesce("n", F.lit(0))).filter(F.col("now") > part.tau).select("gid", "before", "now")


def one_window_problem(events: DataFrame, q: PackageQuery):
    """The program of all given events, for tests against the windows."""
    t = translate(events, q)
    from ..plans.coefficients import collect_columns

    return branch_problem(t, 0, *collect_columns(coefficient_frame(events, t), t, 1 << 20))
