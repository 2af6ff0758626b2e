"""Aggregates for package conditions, and a chained builder.

    package_of(df).repeat(0).where("p_type = 'PROMO'").such_that((count_() == 3) & sum_("p_size").between(60, 75)).minimize(sum_("p_retailprice"))
"""

from __future__ import annotations

from dataclasses import replace

from ..lang.ast import Agg, And, Condition, Linear, PackageAnalysisError, PackageQuery


def count_(expr: str | None = None, where: str | None = None) -> Linear:
    """Tuples of the package, or those with a non-null expr, or those that satisfy where."""
    return Linear.of(Agg("count", expr, where))


def sum_(expr: str, where: str | None = None) -> Linear:
    return Linear.of(Agg("sum", expr, where))


def avg_(expr: str, where: str | None = None) -> Linear:
    return Linear.of(Agg("avg", expr, where))


def min_(expr: str, where: str | None = None) -> Linear:
    return Linear.of(Agg("min", expr, where))


def max_(expr: str, where: str | None = None) -> Linear:
    return Linear.of(Agg("max", expr, where))


class Builder:
    def __init__(self, query: PackageQuery):
        self.query = query

    def _with(self, **changes) -> Builder:
        return Builder(replace(self.query, **changes))

    def named(self, name: str) -> Builder:
        return self._with(name=name)

    def repeat(self, k: int | None) -> Builder:
        if k is not None and (not isinstance(k, int) or k < 0):
            raise PackageAnalysisError("REPEAT takes a non-negative integer")
        return self._with(repeat=k)

    def where(self, condition: str) -> Builder:
        old = self.query.where
        return self._with(where=f"({old}) AND ({condition})" if old else condition)

    def such_that(self, condition: Condition) -> Builder:
        old = self.query.such_that
        return self._with(such_that=And((old, condition)) if old is not None else condition)

    def minimize(self, objective: Linear) -> Builder:
        return self._with(objective=Linear.of(objective), sense="min")

    def maximize(self, objective: Linear) -> Builder:
        return self._with(objective=Linear.of(objective), sense="max")

    def allow_empty(self) -> Builder:
        return self._with(require_nonempty=False)


def package_of(relation, alias: str = "r") -> Builder:
    """relation: a DataFrame (a join for several relations) or the name of a view."""
    return Builder(PackageQuery(relation=relation, alias=alias))
