"""The experiments EX0-EX7: each returns rows to plot; seconds are response times without materialising."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.build import count_, package_of, sum_
from ..measure.measures import approximation_ratio, best_tau, coverage_ratio, repeat_runs, timed
from ..operators.baselines import self_join_packages
from ..operators.coarse_fine import FineLimits, coarse_fine
from ..operators.whole import whole_solve
from ..partition.cluster import kmeans_partition
from ..partition.quad import Partitioning, coverage, kd_partition, partition_report, quad_partition, radius_for
from ..plans.rules import query_attributes
from ..solve.problem import SolverLimits
from .definitions import LINE_ATTRS, WORKLOADS, first_lines, flat_embeddings, lines

#: The whole solve may take this long before it counts as failed; the reference gives it an hour.
LIMITS = SolverLimits(seconds=10)
FINE = FineLimits(seconds=20)


def _pair(part: Partitioning, name: str, runs: int) -> tuple:
    """status, seconds of whole and coarse-fine, objectives, ratio."""
    relation = part.df.drop("gid")
    q = WORKLOADS[name].query(relation)
    whole = whole_solve(relation, q, LIMITS)
    fine = coarse_fine(part, q, FINE)
    seconds = repeat_runs(lambda: coarse_fine(part, q, FINE), runs)["seconds"] if fine.found and runs > 1 else fine.timing["total"]
    return whole.status.value, fine.status.value, whole.timing["total"], seconds, whole.objective, fine.objective, approximation_ratio(fine.objective, whole.objective, q.sense)


PAIR = "whole_status string, fine_status string, whole_s double, fine_s double, whole double, fine double, ratio double"


def ex0_self_join(spark: SparkSession, sf_dir: str, most: int = 7, cap: float = 30.0) -> DataFrame:
    """Self join against the whole solve as the package grows to 7, on 100 rows.

    A size whose expected time (the last one's times the growth of the number of sets, once that is above a job's fixed
    cost) is over cap isn't run: its row has the expectation only.
    """
    df, out = first_lines(spark, sf_dir), []
    rows, expected = df.count(), 0.0
    for k in range(1, most + 1):
        band = (20.0 * k, 30.0 * k)
        a, found = None, []
        if expected <= cap:
            a, found = timed(lambda k=k, band=band: self_join_packages(df, k, "tid", {"l_quantity": band}, "l_extendedprice", "max").collect())
        q = package_of(df).repeat(0).such_that((count_() == k) & sum_("l_quantity").between(*band)).maximize(sum_("l_extendedprice")).query
        r = whole_solve(df, q, LIMITS)
        out.append((k, a, expected if a is None else None, r.timing["total"], found[0]["l_extendedprice"] if found else None, r.objective))
        spent = expected if a is None else a
        expected = spent * (rows - k) / (k + 1) if spent > 3 else 0.0
    return spark.createDataFrame(out, "k int, self_join_s double, expected_s double, whole_s double, self_join double, whole double")


def ex1_scaling(spark: SparkSession, sf_dir: str, names=("w1", "w2", "w3", "w4", "w5", "w6", "w7", "v1", "v2", "v4", "v5", "v7"), fractions=(0.1, 0.25, 0.5, 0.75, 1.0), runs: int = 1) -> DataFrame:
    """Whole solve and coarse-fine over samples of the data; tau is a tenth of all tuples, no radius."""
    out = []
    for name in names:
        w = WORKLOADS[name]
        full = quad_partition(w.relation(spark, sf_dir), list(w.attrs), 0.1, digits=w.digits)
        for f in fractions:
            part = full if f == 1.0 else full.sample(f)
            out.append((name, f, part.df.count(), *_pair(part, name, runs)))
    return spark.createDataFrame(out, "query string, fraction double, n long, " + PAIR)


def ex1_failures(rows: DataFrame) -> DataFrame:
    """From ex1_scaling's rows, by query: shares of points at which a method found nothing, by reason, and at which only coarse-fine failed."""
    lost = lambda side: F.col(f"{side}_status").isin("optimal", "feasible") == F.lit(False)
    share = lambda c: F.avg(c.cast("double"))
    reason = lambda side, text: share(F.col(f"{side}_status") == text).alias(f"{side}_{text.split()[0]}")
    reasons = [reason(side, text) for side in ("whole", "fine") for text in ("infeasible", "time limit", "node limit", "memory limit")]
    return rows.groupBy("query").agg(share(lost("whole")).alias("whole_failed"), share(lost("fine")).alias("fine_failed"), share(~lost("whole") & lost("fine")).alias("falsely_infeasible"), *reasons)


def ex1b_radius(spark: SparkSession, sf_dir: str, eps: float = 1.0) -> DataFrame:
    """W2 without a radius and with the one that belongs to eps."""
    df, out = lines(spark, sf_dir), []
    for label, radius in (("none", None), (f"eps {eps}", radius_for(eps, "min"))):
        part = quad_partition(df, ["p_size", "p_retailprice"], 0.1, radius, digits=2)
        out.append((label, part.groups.count(), *_pair(part, "w2", 1)))
    return spark.createDataFrame(out, "radius string, groups long, " + PAIR)


def ex2_tau(spark: SparkSession, sf_dir: str, name: str = "w1", taus=(0.5, 0.1, 0.03, 0.01, 0.003, 0.001), fraction: float = 1.0) -> DataFrame:
    """Response time over tau, beside the whole solve; best marks the smallest."""
    w, out = WORKLOADS[name], []
    df = w.relation(spark, sf_dir)
    for tau in taus:
        part = quad_partition(df, list(w.attrs), tau, digits=w.digits)
        part = part if fraction == 1.0 else part.sample(fraction)
        out.append((name, part.tau, part.groups.count(), *_pair(part, name, 1)))
    best = best_tau({r[1]: r[6] for r in out})
    return spark.createDataFrame([(*r, r[1] == best) for r in out], "query string, tau long, groups long, " + PAIR + ", best boolean")


def ex3_coverage(spark: SparkSession, sf_dir: str, name: str = "w1") -> DataFrame:
    """Partition attributes below, at and above the query's: time against coverage 1."""
    df = lines(spark, sf_dir)
    own = sorted(query_attributes(WORKLOADS[name].query(df)))
    sets = [own[:1], own[:2], own, own + [a for a in LINE_ATTRS if a not in own][:2], own + [a for a in LINE_ATTRS if a not in own]]
    out = []
    for attrs in sets:
        part = quad_partition(df, attrs, 0.01, digits=2, split="adaptive")
        out.append((coverage(attrs, set(own)), len(attrs), part.groups.count(), *_pair(part, name, 1)))
    base = next(r[6] for r in out if r[0] == 1.0)  # the query's own attributes
    return spark.createDataFrame([(*r, coverage_ratio(r[6], base)) for r in out], "coverage double, attributes int, groups long, " + PAIR + ", time_ratio double")


def ex3_coverage_vectors(spark: SparkSession, sf_dir: str, name: str = "v6", dims: int = 64) -> DataFrame:
    """The same on embeddings, up to all dims components: coverage far over 1. Codes of a level are cut to the widest attributes."""
    df = flat_embeddings(spark, sf_dir, dims)
    own = sorted(query_attributes(WORKLOADS[name].query(df)))
    others = [f"e{i + 1}" for i in range(dims) if f"e{i + 1}" not in own]
    out = []
    for attrs in (own[:2], own, own + others[:11], own + others):
        part = quad_partition(df, attrs, 0.1, digits=6, split="adaptive")
        out.append((coverage(attrs, set(own)), len(attrs), part.groups.count(), *_pair(part, name, 1)))
    base = next(r[6] for r in out if r[0] == 1.0)
    return spark.createDataFrame([(*r, coverage_ratio(r[6], base)) for r in out], "coverage double, attributes int, groups long, " + PAIR + ", time_ratio double")


def ex4_partitioning(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds, levels and jobs of the offline step for every workload's relation."""
    out = []
    for name, w in WORKLOADS.items():
        p = quad_partition(w.relation(spark, sf_dir), list(w.attrs), 0.1, digits=w.digits)
        out.append((name, p.df.count(), p.tau, p.groups.count(), p.metrics["seconds"], int(p.metrics["levels"]), int(p.metrics["jobs"])))
    return spark.createDataFrame(out, "query string, n long, tau long, groups long, seconds double, levels int, jobs int")


def ex5_remedies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Remedies by themselves and in a chain, on the queries that are hard for centroids."""
    out = []
    for name in ("v3", "v6"):
        w = WORKLOADS[name]
        part = quad_partition(w.relation(spark, sf_dir), list(w.attrs), 0.1, digits=w.digits)
        q = w.query(part.df.drop("gid"))
        for chain in ((), ("hybrid",), ("smaller_tau",), ("drop",), ("merge",), ("hybrid", "smaller_tau", "drop", "merge")):
            r = coarse_fine(part, q, FineLimits(seconds=60), remedies=chain)
            out.append((name, " ".join(chain) or "none", r.found, r.counters["solves"], r.counters["backtracks"], r.timing["total"]))
    return spark.createDataFrame(out, "query string, remedies string, found boolean, solves int, backtracks int, seconds double")


def ex6_methods(spark: SparkSession, sf_dir: str, name: str = "v5") -> DataFrame:
    """Quad, k-d and k-means groups of about the same number: sizes, time, ratio."""
    w = WORKLOADS[name]
    df = w.relation(spark, sf_dir)
    quad = quad_partition(df, list(w.attrs), 0.05, digits=w.digits)
    made = {"quad": quad, "adaptive": quad_partition(df, list(w.attrs), 0.05, digits=w.digits, split="adaptive"), "kd": kd_partition(df, list(w.attrs), 0.05, digits=w.digits), "kmeans": kmeans_partition(df, list(w.attrs), min(60, quad.groups.count()))}
    out = []
    for label, part in made.items():
        r = partition_report(part, quad.tau).first()
        out.append((label, r.groups, r.largest, r.over_tau, *_pair(part, name, 1)))
    return spark.createDataFrame(out, "method string, groups long, largest long, over_tau double, " + PAIR)


def ex7_dynamic(spark: SparkSession, sf_dir: str, name: str = "w5", epsilons=(0.1, 0.3, 0.6)) -> DataFrame:
    """A partitioning made for each eps against cuts of one fine tree."""
    w = WORKLOADS[name]
    df = w.relation(spark, sf_dir)
    attrs = list(w.attrs)
    tree = quad_partition(df, attrs, 0.05, radius_for(0.1, "max"), digits=w.digits)
    out = []
    for eps in epsilons:
        radius = radius_for(eps, "max")
        a, made = timed(lambda radius=radius: quad_partition(df, attrs, 0.05, radius, digits=w.digits))
        b, cut = timed(lambda radius=radius: tree.cut(radius))
        out += [(eps, "made", made.groups.count(), a, *_pair(made, name, 1)), (eps, "cut", cut.groups.count(), b, *_pair(cut, name, 1))]
    return spark.createDataFrame(out, "eps double, how string, groups long, prepare_s double, " + PAIR)
