from __future__ import annotations

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from satchel.functions.build import count_, package_of, sum_
from satchel.measure import measures
from satchel.operators.coarse_fine import Coarse, Counters, FineLimits, FineSearch, Group, _Shape, coarse_fine, fine_recursive, group_rank, hierarchy_coarse
from satchel.operators.dual import column_generation, dual_bound, prune_columns
from satchel.operators.whole import top_k_packages, whole_solve
from satchel.package import result as packages
from satchel.partition.quad import Absolute, Partitioning, Relative, kd_partition, partition_report, quad_partition, radius_for
from satchel.plans.coefficients import coefficient_frame, translate, with_tid
from satchel.plans.reduction import ilp_to_package
from satchel.session import explain_package, package_sql
from satchel.solve.branch import BranchAndBound, Enumerator
from satchel.solve.problem import INF, IlpProblem, SolverLimits, SolveStatus
from satchel.workloads.definitions import WORKLOADS, lines, meal, parts


@pytest.fixture(scope="module")
def numbers(spark):
    rng = np.random.default_rng(1)
    rows = [(i, float(rng.integers(1, 60)), float(rng.integers(1, 1000)), float(np.round(rng.gamma(2, 30), 2))) for i in range(1500)]
    return with_tid(spark.createDataFrame(rows, "k long, a double, b double, c double"), ["k"])


@pytest.fixture(scope="module")
def part(numbers):
    return quad_partition(numbers, ["a", "b", "c"], 150, digits=2)


def test_partition_invariants(numbers, part):
    report = partition_report(part).first()
    assert report.over_tau == 0 and part.groups.agg(F.sum("n")).first()[0] == 1500
    assert part.df.select("tid").distinct().count() == 1500
    for r in measures.check_centroid_mean(part).collect():
        assert abs(r.centroids - r.tuples) < 1e-6
    by = {r.gid: r.n for r in part.groups.collect()}
    assert by == {r.gid: r["count"] for r in part.df.groupBy("gid").count().collect()}


def test_radius(numbers):
    p = quad_partition(numbers, ["a", "b"], 500, Relative(0.3), digits=2)
    assert measures.check_tuple_bounds(p, 0.3).count() == 0 and partition_report(p).first().over_radius == 0
    q = quad_partition(numbers, ["a", "b"], 500, Absolute(100.0), digits=2)
    assert q.groups.agg(F.max("radius")).first()[0] <= 100
    assert radius_for(1.0, "min").gamma == 0.5 and radius_for(0.2, "max").gamma == 0.2
    exact = quad_partition(numbers.limit(200), ["a"], 10_000, Relative(0.0), digits=2)
    assert exact.groups.filter("min_a <> max_a").count() == 0  # radius 0: equal tuples only


def test_equal_tuples_are_sliced(spark):
    df = with_tid(spark.range(500).select(F.col("id").alias("k"), F.lit(1.0).alias("a")), ["k"])
    assert partition_report(quad_partition(df, ["a"], 20)).first().largest <= 20
    assert partition_report(quad_partition(df, ["a"], 1)).first().largest == 1


def test_other_splits(numbers):
    for p in (kd_partition(numbers, ["a", "b"], 100, digits=2), quad_partition(numbers, ["a", "b", "c"], 100, digits=2, split="adaptive")):
        r = partition_report(p).first()
        assert r.over_tau == 0 and p.groups.agg(F.sum("n")).first()[0] == 1500


def test_edits(part, tmp_path):
    part.save(tmp_path.as_uri() + "/p")
    again = Partitioning.load(part.df.sparkSession, tmp_path.as_uri() + "/p")
    assert again.tau == part.tau and again.groups.count() == part.groups.count() and again.attrs == part.attrs
    merged = part.merge()
    assert merged.groups.count() == math.ceil(part.groups.count() / 2)
    while merged.groups.count() > 1:
        merged = merged.merge()
    assert merged.groups.first().n == 1500
    assert part.refine(20).groups.agg(F.max("n")).first()[0] <= 20
    assert part.drop_attributes({"c"}).attrs == ["a", "b"]
    half = part.sample(0.5)
    assert half.df.join(part.sample(0.25).df.select("tid"), "tid", "left_semi").count() == part.sample(0.25).df.count() < half.df.count()
    cut = part.cut(None, 10_000)
    assert cut.groups.count() == 1
    assert part.cut(None, 150).groups.count() == part.groups.count()


def query(df, repeat=0):
    return package_of(df).repeat(repeat).such_that((count_() == 8) & (sum_("a") <= 260) & sum_("c").between(300, 420)).maximize(sum_("b")).query


@pytest.mark.parametrize("options", [{}, {"order": "size"}, {"order": "multiplicity"}, {"rep_mode": "stored"}, {"budget": 12}, {"parallel": "groups"}, {"parallel": "orders", "width": 2}], ids=str)
def test_coarse_fine(numbers, part, options):
    q = query(numbers)
    whole = whole_solve(numbers, q, SolverLimits(seconds=60))
    r = coarse_fine(part, q, FineLimits(seconds=60), **options)
    assert r.found and packages.is_feasible(r.package, q, numbers)
    ratio = measures.approximation_ratio(r.objective, whole.objective, "max")
    assert 1 - 1e-9 <= ratio < 1.5
    assert abs(packages.objective_value(r.package, q) - r.objective) < 1e-6


@pytest.mark.parametrize("repeat", [None, 0, 3])
def test_repetition(numbers, part, repeat):
    q = query(numbers, repeat)
    a, b = whole_solve(numbers, q), coarse_fine(part, q)
    assert a.found and b.found and packages.is_feasible(b.package, q, numbers)
    assert repeat is None or max(a.chosen.values()) <= repeat + 1
    assert b.objective <= a.objective + 1e-6


def test_alternatives_and_filters(numbers, part):
    q = package_of(numbers).repeat(0).where("a > 10").such_that((count_() == 5) & ((sum_("c") <= 60) | (sum_("c") >= 900))).maximize(sum_("b")).query
    a, b = whole_solve(numbers, q), whole_solve(numbers, q, mode="branches")
    assert abs(a.objective - b.objective) < 1e-6
    r = coarse_fine(part, q)
    assert r.found and packages.is_feasible(r.package, q, numbers) and r.objective <= a.objective + 1e-6


def test_unbounded_infeasible_empty(numbers, part):
    big = package_of(numbers).repeat(None).such_that(count_() >= 1).maximize(sum_("b")).query
    assert whole_solve(numbers, big).status is coarse_fine(part, big).status is SolveStatus.UNBOUNDED
    none = package_of(numbers).repeat(0).such_that((count_() == 3) & (sum_("a") >= 10_000)).query
    assert whole_solve(numbers, none).status is SolveStatus.INFEASIBLE and not coarse_fine(part, none).found
    nobody = package_of(numbers).repeat(0).where("a < 0").such_that(count_() == 1).query
    assert whole_solve(numbers, nobody).status is SolveStatus.INFEASIBLE and not coarse_fine(part, nobody).found
    assert whole_solve(numbers, query(numbers), SolverLimits(bytes=1000)).status is SolveStatus.LIMIT_MEMORY


def test_false_infeasibility_and_remedies(spark):
    """Values sit at 0 and 10, centroids at 5; only tuples can reach the narrow band."""
    rows = [(i, float(10 * (i % 2)), 1.0 + i % 7) for i in range(40)]
    df = with_tid(spark.createDataFrame(rows, "k long, v double, w double"), ["k"])
    one = quad_partition(df, ["w"], 40)
    q = package_of(df).repeat(0).such_that((count_() == 3) & sum_("v").between(29.9, 30.1)).maximize(sum_("w")).query
    assert not coarse_fine(one, q, remedies=()).found
    for chain in (("hybrid",), ("smaller_tau",), ("merge", "smaller_tau")):
        r = coarse_fine(one, q, remedies=chain)
        assert r.found and packages.is_feasible(r.package, q, df)


def _search(groups, centres, lo, hi, support, order):
    shape = _Shape("max", list(range(len(lo))), np.array(lo, float), np.array(hi, float))
    c = Counters()
    s = FineSearch(shape, 0, groups, centres, Enumerator(), FineLimits(), c, lambda g: [x for x in order if x in g])
    return s.run(support), c


def _group(first, values):
    v = np.array(values, float)
    return Group(np.arange(first, first + len(v)), v[None, :], v, np.ones(len(v)))


def test_backtracking_changes_the_order():
    """Sum must be 10. A alone can take 7 (its best fit), which leaves B without an answer; B first takes 4, then A takes 6."""
    groups = {"A": _group(0, [7, 6]), "B": _group(10, [4])}
    picked, c = _search(groups, {"A": np.array([6.0]), "B": np.array([3.0])}, [9.9], [10.1], {"A": 1, "B": 1}, ["A", "B"])
    assert picked == {1: 1, 10: 1} and c.backtracks >= 1
    none, c = _search({"A": _group(0, [7]), "B": _group(10, [4])}, {"A": np.array([6.0]), "B": np.array([4.0])}, [9.9], [10.1], {"A": 1, "B": 1}, ["A", "B"])
    assert none is None and c.backtracks >= 2


def test_published_factor_has_a_counterexample(spark):
    df = spark.createDataFrame([(1, 10.0, 100.0), (2, 10.2, 100.0), (3, 5.0, 10.0)], "tid long, w double, v double")
    p = quad_partition(df, ["w", "v"], 2, digits=2)
    q = package_of(df).repeat(0).such_that(sum_("w") <= 10).maximize(sum_("v")).query
    whole, r = whole_solve(df, q), coarse_fine(p, q, remedies=())
    assert whole.objective == 100 and r.objective == 10
    assert r.objective < measures.guarantee(0.03, "max") * whole.objective


def test_recursion_matches_rows():
    rng = np.random.default_rng(0)
    m = 300
    coarse = Coarse([f"r/{i % 7}/{i:03d}" for i in range(m)], np.stack([np.ones(m), rng.random(m)]), rng.random(m), np.full(m, 5.0), np.full(m, 5.0))

    class T:
        branches = [[0, 1]]
        query = package_of("x").repeat(0).maximize(count_()).query

        def lo(self, _):
            return np.array([10.0, 0.0])

        def hi(self, _):
            return np.array([10.0, 6.0])

    c = Counters()
    s = hierarchy_coarse(coarse, T(), 0, 20, BranchAndBound(), c)
    assert s.found and abs(s.x.sum() - 10) < 1e-9 and coarse.C[1] @ s.x <= 6 + 1e-6 and c.largest <= 20
    p = IlpProblem(coarse.C, [10, 0], [10, 6], coarse.obj, np.ones(m), "max", np.arange(m))
    for budget in (40, 7):  # with 7, runs are dealt again
        d = Counters()
        r = fine_recursive(BranchAndBound(), budget, d).solve(p)
        assert r.found and p.feasible(r.x) and d.largest <= budget


def test_no_program_exceeds_the_budget(numbers, part):
    q = query(numbers)
    r = coarse_fine(part, q, FineLimits(seconds=60), budget=25)
    assert r.found and packages.is_feasible(r.package, q, numbers) and r.counters["largest"] <= 25
    few = coarse_fine(part, q, FineLimits(seconds=60, columns=3), remedies=())
    assert few.counters["largest"] <= 3


def test_limits_are_statuses(numbers, part, monkeypatch):
    q = query(numbers)
    assert coarse_fine(part, q, FineLimits(seconds=0)).status is SolveStatus.LIMIT_TIME
    assert coarse_fine(part, q, FineLimits(solves=1)).status is SolveStatus.LIMIT_NODES
    from satchel.operators import coarse_fine as module

    whole = module.fetch_groups
    monkeypatch.setattr(module, "fetch_groups", lambda p, t, gids, most=10: whole(p, t, gids, most))
    assert coarse_fine(part, q, FineLimits(seconds=60)).status is SolveStatus.LIMIT_MEMORY


def test_rank():
    coarse = Coarse(["a", "b", "c"], np.zeros((0, 3)), np.zeros(3), np.array([1.0, 5.0, 3.0]), np.ones(3))
    assert group_rank("size", coarse, {}, 0)(["a", "b", "c"]) == ["b", "c", "a"]
    assert group_rank("multiplicity", coarse, {"c": 4, "a": 1}, 0)(["a", "b", "c"]) == ["c", "a", "b"]
    assert group_rank("random", coarse, {}, 1)(["c", "a", "b"]) == group_rank("random", coarse, {}, 1)(["a", "b", "c"])


def test_dual_bound(numbers):
    q = query(numbers)
    t = translate(numbers, q)
    frame = coefficient_frame(numbers, t)
    whole = whole_solve(numbers, q)
    d = dual_bound(frame, t, 12)
    assert d.bound >= whole.objective - 1e-6
    c = column_generation(frame, t, d.multipliers, width=200)
    assert whole.objective - 1e-6 <= c.bound <= d.bound + 1e-6 and c.bound <= 1.05 * whole.objective
    kept = {r.tid for r in prune_columns(frame, t, c, whole.objective).collect()}
    assert len(kept) < 1500
    assert set(whole.chosen) <= kept


def test_reduction(spark):
    rng = np.random.default_rng(4)
    for _ in range(3):
        cost, B, b = rng.integers(1, 9, 4).astype(float), rng.integers(1, 5, (2, 4)).astype(float), rng.integers(5, 12, 2).astype(float)
        df, q = ilp_to_package(spark, cost, B, b)
        p = IlpProblem(B, np.full(2, -INF), b, cost, np.full(4, 12.0), "max", np.arange(4))
        assert abs(whole_solve(df, q).objective - Enumerator().solve(p).objective) < 1e-9


def test_top_packages(numbers):
    few = numbers.limit(12)
    q = package_of(few).repeat(0).such_that(count_() == 2).maximize(sum_("b")).query
    found = [r.objective for r in top_k_packages(few, q, 5)]
    b = sorted((x.b + y.b for i, x in enumerate(few.collect()) for y in few.collect()[:i]), reverse=True)[:5]
    assert found == pytest.approx(b)


def test_measures(numbers, spark):
    assert measures.approximation_ratio(50, 100, "max") == 2 and measures.approximation_ratio(100, 50, "min") == 2
    assert measures.approximation_ratio(0, 5, "max") is None
    assert measures.guarantee(0.0, "max") == 1 and round(measures.guarantee(0.1, "min"), 6) == 1.771561
    assert measures.hoeffding_gamma(0, 5, 0, 1) == 1 and measures.hoeffding_gamma(5, 5, 0, 1) == pytest.approx(2 * math.exp(-10))
    assert measures.at_least_as_good(0.9**3, 1, 3, 0.1, "max") and not measures.at_least_as_good(0.7, 1, 3, 0.1, "max")
    q = query(numbers)
    t = translate(numbers, q)
    s = measures.selectivity(numbers, q, (8, 8), 300).agg(F.avg(F.col("infeasible").cast("int"))).first()[0]
    assert 0.2 < s < 1
    assert measures.guarantee_applies(numbers, t)
    assert measures.best_tau({5: 2.0, 10: 1.0, 20: 1.0}) == 10
    r = measures.repeat_runs(lambda: whole_solve(numbers, q), 2)
    assert r["found"] == 1
    summary = {x.query: x for x in measures.ratio_summary(spark.createDataFrame([("a", 1.0), ("a", 2.0), ("b", 1.5)], "query string, ratio double")).collect()}
    assert summary["a"].mean_ratio == 1.5 and summary[None].n == 3


def test_projection_and_relaxation(numbers):
    p = quad_partition(numbers, ["a", "b", "c"], 500, Relative(0.3), digits=2)
    q = query(numbers)
    whole = whole_solve(numbers, q)
    assert measures.check_projection_bounds(p, whole.package, 0.3).filter("not holds").count() == 0
    assert measures.project_package(whole.package, p).agg(F.sum("multiplicity")).first()[0] == 8
    assert measures.is_relaxation(whole.package, translate(numbers, q), 0.1, 1)
    groups = measures.project_package(whole.package, p)
    drawn = measures.draw_package(groups, p)
    assert drawn.agg(F.sum("multiplicity")).first()[0] == 8
    assert sorted(measures.project_package(drawn, p).collect()) == sorted(groups.collect())


def test_statements_on_views(spark, sf):
    spark.read.parquet(f"{sf}/part.parquet").createOrReplaceTempView("part")
    text = "SELECT PACKAGE(P) AS M FROM part P REPEAT 0 WHERE P.p_type = 'PROMO' SUCH THAT COUNT(M.*) = 3 AND SUM(M.p_size) BETWEEN 60 AND 75 MINIMIZE SUM(M.p_retailprice)"
    assert package_sql(spark, text).objective == pytest.approx(2702.8)
    assert package_sql(spark, text, "coarse-fine", tau=30).found
    df = parts(spark, sf)
    assert "alternatives: 1" in explain_package(df, meal(df))


def test_workload_is_solved(spark, sf):
    df = lines(spark, sf)
    q = WORKLOADS["w7"].query(df)
    p = quad_partition(df, list(WORKLOADS["w7"].attrs), 0.1, digits=2)
    r = coarse_fine(p, q)
    assert r.found and packages.is_feasible(r.package, q, df)
    assert packages.audit(r.package, q, df).filter("not satisfied").count() == 0


@pytest.fixture(scope="module")
def outliers(spark):
    """100 groups of four; the last tuple of each is far from their centroid."""
    rows = [(i * 4 + j, float(1000 * i + (0, 1, 9, 90)[j])) for i in range(100) for j in range(4)]
    df = with_tid(spark.createDataFrame(rows, "k long, x double"), ["k"])
    return df, quad_partition(df, ["x"], 4, digits=0)


def only_outlier(df, i):
    return package_of(df).repeat(0).such_that((count_() == 1) & (sum_("x") == 1000.0 * i + 90)).minimize(sum_("x")).query


@pytest.mark.parametrize("i", [3, 50, 71, 97])
def test_hybrid_tries_every_group(outliers, i):
    df, part = outliers
    r = coarse_fine(part, only_outlier(df, i), remedies=("hybrid",))
    assert part.groups.count() > 64 and r.found and r.objective == 1000.0 * i + 90


def test_merge_ends_in_the_original_problem(outliers):
    df, part = outliers
    r = coarse_fine(part, only_outlier(df, 50), remedies=("merge",))
    assert r.found and r.objective == 50_090.0
    none = package_of(df).repeat(0).such_that((count_() == 1) & (sum_("x") == 50_091.0)).minimize(sum_("x")).query
    assert coarse_fine(part, none, remedies=("merge",)).status is SolveStatus.INFEASIBLE


def test_a_limit_is_not_infeasible(outliers):
    df, part = outliers
    found = [coarse_fine(part, only_outlier(df, i), FineLimits(solves=3)).status for i in (3, 50)]
    assert SolveStatus.INFEASIBLE not in found and SolveStatus.LIMIT_NODES in found


@pytest.fixture
def tiny_driver(monkeypatch):
    """Programs of more than 60 columns are reduced, with 40 tuples fetched at a time."""
    from satchel.operators import reduced, whole

    for module, name, value in ((reduced, "DIRECT_COLUMNS", 60), (whole, "DIRECT_COLUMNS", 60), (reduced, "WIDTH", 40), (reduced, "NEAR", 50)):
        monkeypatch.setattr(module, name, value)


def test_reduction_keeps_the_optimum(numbers, tiny_driver):
    from satchel.operators.reduced import relaxation
    from satchel.plans.coefficients import branch_problem, collect_columns
    from satchel.solve.branch import lp_bound

    few = package_of(numbers).repeat(2).where("a > 10").such_that((count_() == 5) & ((sum_("c") <= 60) | (sum_("c") >= 900))).minimize(sum_("b")).query
    free = package_of(numbers).repeat(0).such_that((count_() == 4) & (sum_("a") == 100)).query
    for q in (query(numbers), query(numbers, 3), few, free):
        t = translate(numbers, q)
        data = collect_columns(coefficient_frame(numbers, t), t, 2000)
        direct = whole_solve(numbers, q, solver=BranchAndBound(SolverLimits()), mode="branches")
        r = whole_solve(numbers, q)
        assert r.status is direct.status is SolveStatus.OPTIMAL and r.objective == pytest.approx(direct.objective)
        assert "kept" in r.counters and packages.is_feasible(r.package, q, numbers)
        for b in range(len(t.branches)):
            assert relaxation(coefficient_frame(numbers, t), t, b).bound == pytest.approx(lp_bound(branch_problem(t, b, *data)), abs=1e-6)


def test_reduction_statuses(numbers, tiny_driver):
    none = package_of(numbers).repeat(0).such_that((count_() == 3) & (sum_("a") >= 10_000)).query
    assert whole_solve(numbers, none).status is SolveStatus.INFEASIBLE
    big = package_of(numbers).repeat(None).such_that(count_() >= 1).maximize(sum_("b")).query
    assert whole_solve(numbers, big).status is SolveStatus.UNBOUNDED
    best = package_of(numbers).repeat(0).such_that(count_() == 10).maximize(sum_("b")).query
    top = sum(r.b for r in numbers.orderBy(F.desc("b")).limit(10).collect())
    assert whole_solve(numbers, best).objective == pytest.approx(top)


def test_impossible_ends_before_the_hybrid(numbers, part):
    """Before, every group was tried by its tuples, which ended in a time limit on many groups."""
    none = package_of(numbers).repeat(0).such_that((count_() == 3) & (sum_("a") >= 10_000)).query
    r = coarse_fine(part, none, FineLimits(seconds=60), remedies=("hybrid", "smaller_tau", "merge"))
    assert r.status is SolveStatus.INFEASIBLE and r.counters["solves"] <= 2


def test_large_groups_are_made_finer(numbers, part, monkeypatch):
    from satchel.operators import coarse_fine as module

    monkeypatch.setattr(module, "REFINE_ROWS", 160)
    fetched = []
    fetch = module.fetch_groups
    monkeypatch.setattr(module, "fetch_groups", lambda p, t, gids, most=400: fetched.append(1) or fetch(p, t, gids, most))
    q = query(numbers)
    r = coarse_fine(part.merge().merge().merge(), q, FineLimits(seconds=60))
    assert fetched and r.found and packages.is_feasible(r.package, q, numbers)


def _merged_one_by_one(x, m):
    members, centre = {i: [i] for i in range(len(x))}, {i: x[i] for i in range(len(x))}
    while len(members) > max(1, m):
        keys = list(members)
        c = np.stack([centre[k] for k in keys])
        d = ((c[:, None, :] - c[None, :, :]) ** 2).sum(2)
        np.fill_diagonal(d, math.inf)
        i, j = divmod(int(d.argmin()), len(keys))
        a, b = keys[i], keys[j]
        na, nb = len(members[a]), len(members[b])
        centre[a] = (centre[a] * na + centre[b] * nb) / (na + nb)
        members[a] += members.pop(b)
    return {frozenset(v) for v in members.values()}


def _regions_by_lists(x, eps, least):
    near = [np.flatnonzero(((x - p) ** 2).sum(1) <= eps * eps) for p in x]
    labels, k = [-1] * len(x), 0
    for i in range(len(x)):
        if labels[i] >= 0 or len(near[i]) < least:
            continue
        front, labels[i] = [i], k
        while front:
            for j in near[front.pop()]:
                if labels[j] < 0:
                    labels[j] = k
                    front += [j] * (len(near[j]) >= least)
        k += 1
    return [x if x >= 0 else k + sum(1 for y in labels[:i] if y < 0) for i, x in enumerate(labels)]


@pytest.mark.parametrize("copies", [1, 3])
def test_clusterings_without_all_distances(copies):
    from satchel.partition.cluster import density_labels, merged_labels

    x = np.repeat(np.random.default_rng(2).random((40, 2)) * 3, copies, 0)
    for m in (1, 4, 10):
        labels = merged_labels(x, m)
        assert {frozenset(np.flatnonzero(np.array(labels) == k).tolist()) for k in set(labels)} == _merged_one_by_one(x, m)
    for eps, least in ((0.1, 3), (0.3, 4), (1.0, 2)):
        assert density_labels(x, eps, least) == _regions_by_lists(x, eps, least)


def test_clusterings_take_any_number_of_tuples(spark):
    from satchel.partition.cluster import agglomerative_partition, density_partition

    df = with_tid(spark.range(2500).select(F.col("id").alias("k"), (F.col("id") % 50).cast("double").alias("a")), ["k"])
    assert agglomerative_partition(df, ["a"], 10).groups.count() == 10
    assert density_partition(df, ["a"], 0.01, 4).groups.count() == 50


def test_self_join_of_classes(spark):
    from satchel.operators.baselines import self_join_packages, self_join_summary

    rows = [(i, i % 5, (i * 7) % 11 if i % 6 else None) for i in range(25)] + [(25, None, 1), (None, 1, 1)]
    df = spark.createDataFrame(rows, "k long, v int, cents long")
    for size in (1, 2, 3, 4):
        for sense, best in (("min", F.min), ("max", F.max)):
            one = self_join_packages(df, size, "k", {"v": (2, 7)}, "cents", limit=None).agg(F.count(F.lit(1)), best("cents")).first()
            assert tuple(self_join_summary(df, size, "k", {"v": (2, 7)}, "cents", sense).first()) == tuple(one)
    many = spark.range(20_000).select("id", (F.col("id") % 50 + 1).cast("int").alias("v"), (F.col("id") % 997).alias("cents"))
    assert self_join_summary(many, 3, "id", {"v": (1, 150)}, "cents").first().packages == math.comb(20_000, 3)


def test_more_tuples_than_the_solver_holds(numbers, part, tiny_driver, monkeypatch):
    """Before, the whole solve had no objective here, and the pruned one raised or depended on coarse-fine."""
    from satchel.operators import whole
    from satchel.operators.dual import pruned_whole_solve

    monkeypatch.setattr(whole, "LEAST_COLUMNS", 100)
    q = query(numbers)
    few = SolverLimits(bytes=300 * 8 * 20)
    best = whole_solve(numbers, q, solver=BranchAndBound(SolverLimits())).objective
    a, b = whole_solve(numbers, q, few), pruned_whole_solve(part, q, few)
    assert a.objective == pytest.approx(best) and b.objective == pytest.approx(best)
    assert a.counters["columns"] == 1500 > b.counters["columns"]


def test_one_run_is_evaluated_once(numbers, part, monkeypatch):
    from satchel.workloads import experiments
    from satchel.workloads.definitions import Workload

    calls = []
    fine = experiments.coarse_fine
    monkeypatch.setattr(experiments, "coarse_fine", lambda *a: calls.append(1) or fine(*a))
    build = lambda b: b.such_that((count_() == 8) & (sum_("a") <= 260)).maximize(sum_("b"))
    monkeypatch.setitem(experiments.WORKLOADS, "x", Workload("x", lambda *_: numbers, build, ("a", "b")))
    experiments._pair(part, "x", 1)
    assert len(calls) == 1


def test_plans_of_a_level_do_not_grow(spark, monkeypatch):
    """A level reads what the last one left, so its plan joins once for the step and once for the names, at any depth; only the last two are kept."""
    from satchel.partition import quad

    joins, gone = [], []
    store, drop = quad.stored, quad.discard
    monkeypatch.setattr(quad, "stored", lambda df, name: (joins.append((name, df._jdf.queryExecution().analyzed().toString().count("Join "))), store(df, name))[1])
    monkeypatch.setattr(quad, "discard", lambda df: (gone.append(df), drop(df))[1])
    df = spark.range(4096).select(F.col("id").alias("tid"), F.col("id").cast("double").alias("a"))
    part = quad.quad_partition(df, ["a"], 64, digits=0)
    assert part.metrics["levels"] == 7
    assert max(n for name, n in joins if name != "partition") == 1
    assert len(gone) == 6
    assert (part.groups.count(), part.df.filter("gid = 'r/1/1/1/1/1/1' and a < 4032").count(), part.df.count()) == (64, 0, 4096)


def test_sums_of_groups_are_exact(spark):
    """Values near 2^52 and negative ones, whose sums need more than 53 bits."""
    from satchel.partition.quad import _statistics

    values = [(1 << 52) + 1, (1 << 52) + 3, -((1 << 52) + 7), -5, 1 << 40]
    got = _statistics(spark.createDataFrame([("r", v) for v in values] * 9, "gid string, v0 long"), ["a"]).first()
    total = 9 * sum(values)
    assert (int(got.s0), got.n, got.cut0) == (total, 45, -(-total // 45))


def test_small_groups_are_cut_to_the_end_in_tasks(spark, monkeypatch):
    """The same groups, tree and tuples as level by level, with slices of equal tuples, radii and negative values; and no table for each level."""
    from satchel.partition import quad

    rows = [(i, float((i * 7919) % 1009) - 300.25, round((i % 97) ** 2 / 7, 2), None if i % 11 == 0 else float(i % 3)) for i in range(6000)]
    df = spark.createDataFrame(rows + [(10_000 + i, 5.0, 5.0, 5.0) for i in range(400)], "tid long, a double, b double, c double")
    store, written = quad.stored, []
    monkeypatch.setattr(quad, "stored", lambda df, name: (written.append(name), store(df, name))[1])

    def tables(part):
        return [sorted(map(tuple, x.select(sorted(x.columns)).collect()), key=repr) for x in (part.df, part.groups, part.nodes)]

    for attrs, tau, radius, split, most in ((["a", "c"], 150, Relative(2.0), "all", 2000), (["b"], 1900, Absolute(800.0), "cycle", 7000)):
        found = {}
        for least in (100, 1 << 40):
            monkeypatch.setattr(quad, "LOCAL_LEAST", least, raising=False)
            monkeypatch.setattr(quad, "LOCAL_ROWS", most, raising=False)
            written.clear()
            part = quad.quad_partition(df, attrs, tau, radius, digits=2, split=split)
            found[least] = (part.metrics["levels"], written.count("partition-active"), tables(part))
        assert found[100][0] == found[1 << 40][0] and found[100][2] == found[1 << 40][2]
    assert found[100][1] == 0 < found[1 << 40][1]


def test_parts_of_known_sizes():
    from satchel.partition.quad import _places

    got = _places({"r/0": (4, 10), "r/1": (7, 70), "r/2": (9, 20)}, 5)
    assert got == [(4, "r/0", 0, 1), (7, "r/1", 0, 4), (9, "r/2", 4, 1)]
