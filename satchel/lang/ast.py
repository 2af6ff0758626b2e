"""Syntax tree of package queries. Scalar expressions stay Spark SQL text, so the tree is immutable and printable."""

from __future__ import annotations

from dataclasses import dataclass, replace

INF = float("inf")


class PackageAnalysisError(ValueError):
    """A query that isn't a linear package query over its relation."""


@dataclass(frozen=True)
class Agg:
    """An aggregate over the package: kind is count, sum, avg, min or max; expr and where are Spark SQL."""

    kind: str
    expr: str | None = None
    where: str | None = None


@dataclass(frozen=True)
class Linear:
    """A sum of weighted aggregates and a constant."""

    terms: tuple[tuple[float, Agg], ...] = ()
    const: float = 0.0

    @staticmethod
    def of(x) -> Linear:
        if isinstance(x, Linear):
            return x
        if isinstance(x, Agg):
            return Linear(((1.0, x),))
        if isinstance(x, (int, float)) and not isinstance(x, bool):
            return Linear((), float(x))
        raise PackageAnalysisError(f"not a linear term: {x!r}")

    def __add__(self, other) -> Linear:
        o = Linear.of(other)
        weights: dict[Agg, float] = {}
        for w, a in (*self.terms, *o.terms):
            weights[a] = weights.get(a, 0.0) + w
        return Linear(tuple((w, a) for a, w in weights.items() if w), self.const + o.const)

    __radd__ = __add__

    def __neg__(self) -> Linear:
        return self * -1

    def __sub__(self, other) -> Linear:
        return self + -Linear.of(other)

    def __rsub__(self, other) -> Linear:
        return -self + other

    def __mul__(self, k) -> Linear:
        if not isinstance(k, (int, float)):
            raise PackageAnalysisError("a product of aggregates isn't linear")
        return Linear(tuple((w * k, a) for w, a in self.terms), self.const * k)

    __rmul__ = __mul__

    def __truediv__(self, k) -> Linear:
        if not isinstance(k, (int, float)):
            raise PackageAnalysisError("a quotient of aggregates isn't linear")
        return self * (1 / k)

    def __le__(self, other) -> Compare:
        return Compare(self - other, -INF, 0.0)

    def __ge__(self, other) -> Compare:
        return Compare(self - other, 0.0, INF)

    def __lt__(self, other) -> Compare:
        return Compare(self - other, -INF, 0.0, strict_hi=True)

    def __gt__(self, other) -> Compare:
        return Compare(self - other, 0.0, INF, strict_lo=True)

    def __eq__(self, other):  # builds a condition, as Column does
        return Compare(self - other, 0.0, 0.0)

    def __ne__(self, other):
        return Not(Compare(self - other, 0.0, 0.0))

    def __hash__(self) -> int:
        return hash((self.terms, self.const))

    def between(self, lo, hi) -> Condition:
        if isinstance(lo, (int, float)) and isinstance(hi, (int, float)):
            return Compare(replace(self, const=0.0), lo - self.const, hi - self.const)
        return And((self >= lo, self <= hi))


class Condition:
    def __and__(self, other: Condition) -> Condition:
        return And((self, other))

    def __or__(self, other: Condition) -> Condition:
        return Or((self, other))

    def __invert__(self) -> Condition:
        return Not(self)


@dataclass(frozen=True, eq=False)
class Compare(Condition):
    """lo <= linear <= hi, with strict ends where marked."""

    linear: Linear
    lo: float
    hi: float
    strict_lo: bool = False
    strict_hi: bool = False


@dataclass(frozen=True, eq=False)
class And(Condition):
    parts: tuple[Condition, ...]


@dataclass(frozen=True, eq=False)
class Or(Condition):
    parts: tuple[Condition, ...]


@dataclass(frozen=True, eq=False)
class Not(Condition):
    part: Condition


@dataclass(frozen=True, eq=False)
class PackageQuery:
    """What to pick from a relation. repeat: None leaves repetition unlimited, K allows each tuple K + 1 times."""

    relation: object = None  # a DataFrame, or the name of a view
    alias: str = "r"
    name: str = "p"
    repeat: int | None = None
    where: str | None = None
    such_that: Condition | None = None
    objective: Linear | None = None
    sense: str = "min"
    require_nonempty: bool = True

    @property
    def upper(self) -> float:
        return INF if self.repeat is None else self.repeat + 1.0


def same(a, b) -> bool:
    """Structural equality; == on linear terms builds conditions instead."""
    if type(a) is not type(b):
        return False
    if isinstance(a, Linear):
        return a.const == b.const and sorted(a.terms, key=repr) == sorted(b.terms, key=repr)
    if isinstance(a, Compare):
        return same(a.linear, b.linear) and (a.lo, a.hi, a.strict_lo, a.strict_hi) == (b.lo, b.hi, b.strict_lo, b.strict_hi)
    if isinstance(a, (And, Or)):
        return len(a.parts) == len(b.parts) and all(map(same, a.parts, b.parts))
    if isinstance(a, Not):
        return same(a.part, b.part)
    if isinstance(a, PackageQuery):
        return all(same(getattr(a, k), getattr(b, k)) for k in ("repeat", "where", "such_that", "objective", "sense", "name"))
    return a == b
