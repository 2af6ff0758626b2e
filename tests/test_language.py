from __future__ import annotations

import pytest

from satchel.functions.build import avg_, count_, max_, min_, package_of, sum_
from satchel.lang.ast import Agg, And, Compare, Linear, Or, PackageAnalysisError, same
from satchel.lang.parser import parse_package, to_statement
from satchel.plans.coefficients import coefficient_frame, translate
from satchel.plans.rules import analyze, disjuncts, query_attributes

MEAL = """SELECT PACKAGE(R) AS P FROM part R REPEAT 0 WHERE R.p_type = 'PROMO' AND R.p_size > 1
SUCH THAT COUNT(P.*) = 3 AND SUM(P.p_size) BETWEEN 60 AND 75 MINIMIZE SUM(P.p_retailprice)"""


def test_statement_and_builder_agree():
    built = package_of("part", "R").named("P").repeat(0).where("p_type = 'PROMO' AND p_size > 1").such_that((count_() == 3) & sum_("p_size").between(60, 75)).minimize(sum_("p_retailprice")).query
    assert same(parse_package(MEAL), built)
    assert parse_package(MEAL).relation == "part"


@pytest.mark.parametrize("text", [
    MEAL,
    "SELECT PACKAGE(r) p FROM t r SUCH THAT (COUNT(*) <= 5 OR NOT SUM(p.a) > 3) AND AVG(p.b) BETWEEN 1 AND 2",
    "SELECT PACKAGE(r) AS p FROM t r REPEAT 2 SUCH THAT (SELECT COUNT(*) FROM p WHERE p.carbs > 0) >= (SELECT COUNT(*) FROM p WHERE p.protein <= 5)",
    "SELECT PACKAGE(r) AS p FROM t r SUCH THAT 2 * SUM(p.a) - COUNT(*) <= 5.5 AND (SUM(p.a) + 1) * 3 >= 2 MAXIMIZE SUM(p.a * (1 - p.b)) / 2",
    "SELECT PACKAGE(r) AS p FROM t r SUCH THAT MIN(p.a) >= 2 AND MAX(p.a) < 9 AND COUNT(*) <> 4",
])
def test_round_trip(text):
    q = parse_package(text)
    assert same(q, parse_package(to_statement(q)))


def test_qualifiers_only_outside_text():
    q = parse_package("SELECT PACKAGE(r) AS p FROM t r WHERE r.name = 'r.x' SUCH THAT SUM(p.a) <= 1")
    assert q.where == "name = 'r.x'" and q.such_that.linear.terms == ((1.0, Agg("sum", "a")),)


@pytest.mark.parametrize("text", [
    "SELECT PACKAGE(r) AS p FROM t r REPEAT -1",
    "SELECT PACKAGE(r, s) AS p FROM t r REPEAT 0, u s REPEAT 2",
    "SELECT PACKAGE(r) AS p FROM t r SUCH THAT SUM(p.a) * SUM(p.b) <= 1",
    "SELECT PACKAGE(r) AS p FROM t r SUCH THAT SUM(p.a)",
    "SELECT PACKAGE(x) AS p FROM t r",
    "SELECT PACKAGE(r) AS p FROM t r MAXIMIZE",
    "SELECT PACKAGE(r) AS p FROM t r SUCH THAT SUM(*) <= 1",
])
def test_refused(text):
    with pytest.raises(PackageAnalysisError):
        parse_package(text)


def test_linear_algebra():
    x = 2 * sum_("a") - count_() + 3 - sum_("a")
    assert dict((a, w) for w, a in x.terms) == {Agg("sum", "a"): 1.0, Agg("count"): -1.0} and x.const == 3
    assert (sum_("a") - sum_("a")).terms == ()
    c = sum_("a") >= count_()
    assert isinstance(c, Compare) and len(c.linear.terms) == 2
    assert isinstance((count_() == 1) | (count_() == 2), Or) and isinstance(sum_("a").between(count_(), 5), And)
    with pytest.raises(PackageAnalysisError):
        Linear.of("a")


def test_alternatives():
    a, b, c = count_() <= 1, sum_("a") >= 2, sum_("b").between(1, 2)
    assert len(disjuncts((a | b) & (b | c))) == 4
    assert len(disjuncts(~((a | b) & c))) == 3  # both of the first fail, or below, or above
    assert len(disjuncts(None)) == 1


@pytest.fixture(scope="module")
def little(spark):
    return spark.createDataFrame([(1, 2, 0.5, "x"), (2, None, 1.5, "y"), (3, 7, None, "x")], "tid long, a int, b double, s string")


def values(little, q, count=None):
    t = translate(little, q)
    rows = coefficient_frame(little, t).orderBy("tid").collect()
    return [(t.rows[i].lo, t.rows[i].hi, [r[f"c_{i}"] for r in rows]) for i in range(len(t.rows))]


def test_rows(little):
    one = lambda c: values(little, package_of(little).repeat(0).such_that(c).query)
    inf = float("inf")
    assert one(count_() == 2) == [(2, 2, [1, 1, 1])]
    assert one(count_("a") >= 1) == [(1, inf, [1, 0, 1])]
    assert one(sum_("a") < 5) == [(-inf, 4, [2, 0, 7])]
    assert one(sum_("a", where="s = 'x'") <= 5) == [(-inf, 5, [2, 0, 7])]
    assert one(avg_("a") <= 4)[0] == (-inf, 0, [-2, 0, 3])
    assert one(avg_("a") <= 4)[1] == (1, inf, [1, 1, 1])  # not the empty package
    assert one(avg_("b") == 1)[0] == (0, 0, [-0.5, 0.5, 0])
    assert one(count_(where="s = 'x'") >= count_(where="s = 'y'")) == [(0, inf, [1, -1, 1])]
    assert one(min_("a") >= 3) == [(-inf, 0, [1, 0, 0])]
    assert one(min_("a") <= 3) == [(1, inf, [1, 0, 0])]
    assert one(max_("a") > 3) == [(1, inf, [0, 0, 1])]
    assert one(2 * sum_("a") - count_() <= 5) == [(-inf, 5, [3, -1, 13])]


def test_analysis(little):
    for q in (
        package_of(little).such_that(sum_("nope") <= 1).query,
        package_of(little).where("nope > 1").query,
        package_of(little).maximize(avg_("a")).query,
        package_of(little).such_that(avg_("a") - avg_("b") <= 1).query,
        package_of(little.withColumnRenamed("a", "gid")).such_that(count_() <= 1).query,
    ):
        with pytest.raises(PackageAnalysisError):
            analyze(q.relation, q)
    analyze(little, package_of(little).such_that(count_() == 2).maximize(avg_("a")).query)  # the size is fixed
    with pytest.raises(PackageAnalysisError):
        package_of(little).repeat(-1)
    assert query_attributes(package_of(little).such_that(sum_("a * abs(b)") <= 1).maximize(sum_("b")).query) == {"a", "b"}
