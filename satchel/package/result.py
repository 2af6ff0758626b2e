"""What an evaluation returns, and packages as DataFrames."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lang.ast import INF, PackageQuery
from ..plans.coefficients import coefficient_frame, translate
from ..solve.problem import SolveStatus


@dataclass
class PackageResult:
    """chosen: tid -> multiplicity. timing has translate, load, solve and total seconds, without materialising."""

    query: PackageQuery
    relation: DataFrame
    status: SolveStatus
    chosen: dict[int, int] = field(default_factory=dict)
    objective: float | None = None
    bound: float | None = None
    branch: int = 0
    timing: dict[str, float] = field(default_factory=dict)
    counters: dict[str, int] = field(default_factory=dict)
    attempts: list[str] = field(default_factory=list)
    note: str = ""

    @property
    def found(self) -> bool:
        return self.objective is not None

    @property
    def package(self) -> DataFrame:
        return materialize(self.relation, self.chosen)


def materialize(relation: DataFrame, chosen: dict[int, int]) -> DataFrame:
    """Rows of the relation with their multiplicity; the chosen are as many as the solver's columns at most."""
    rows = relation.sparkSession.createDataFrame(sorted(chosen.items()), "tid long, multiplicity int")
    return relation.join(F.broadcast(rows), "tid")


def expand(package: DataFrame) -> DataFrame:
    """One row for each repetition."""
    return package.withColumn("repetition", F.explode(F.sequence(F.lit(1), "multiplicity"))).drop("repetition", "multiplicity")


def collapse(rows: DataFrame) -> DataFrame:
    """Equal rows as one, with their multiplicity."""
    return rows.groupBy(*rows.columns).agg(F.count(F.lit(1)).cast("int").alias("multiplicity"))


def to_nested(package: DataFrame) -> DataFrame:
    """One row: the package as an array of rows with multiplicities."""
    return package.agg(F.sort_array(F.collect_list(F.struct(*package.columns))).alias("package"))


def package_aggregates(package: DataFrame, q: PackageQuery, relation: DataFrame | None = None) -> DataFrame:
    """One row: the value of every linear row and of the objective."""
    t = translate(package.drop("multiplicity") if relation is None else relation, q)
    frame = coefficient_frame(package, t, ("multiplicity",)) if not q.where else coefficient_frame(package, t, ("multiplicity",))
    total = lambda c: F.coalesce(F.sum(F.col(c) * F.col("multiplicity")), F.lit(0.0))
    return frame.agg(*(total(c).alias(c) for c in t.names), total("obj").alias("objective"), F.coalesce(F.sum("multiplicity"), F.lit(0)).alias("size"))


def audit(package: DataFrame, q: PackageQuery, relation: DataFrame | None = None, tol: float = 1e-6) -> DataFrame:
    """One row per linear row of each alternative: branch, name, value, lo, hi, satisfied."""
    t = translate(package.drop("multiplicity") if relation is None else relation, q)
    one = package_aggregates(package, q, relation)
    facts = [F.struct(F.lit(b).alias("branch"), F.lit(t.rows[i].name).alias("name"), F.col(f"c_{i}").alias("value"), F.lit(t.rows[i].lo).alias("lo"), F.lit(t.rows[i].hi).alias("hi")) for b, branch in enumerate(t.branches) for i in branch]
    if not facts:
        return one.sparkSession.createDataFrame([], "branch int, name string, value double, lo double, hi double, satisfied boolean")
    out = one.select(F.explode(F.array(*facts)).alias("r")).select("r.*")
    room = lambda c: tol * F.greatest(F.lit(1.0), F.when(F.abs(c) < INF, F.abs(c)).otherwise(1.0))
    return out.withColumn("satisfied", (F.col("value") >= F.col("lo") - room(F.col("lo"))) & (F.col("value") <= F.col("hi") + room(F.col("hi"))))


def is_feasible(package: DataFrame, q: PackageQuery, relation: DataFrame | None = None) -> bool:
    """All rows of some alternative hold, filters hold for all tuples, and none repeats too often."""
    if q.where and not package.filter(~F.coalesce(F.expr(q.where), F.lit(False))).isEmpty():
        return False
    if q.upper < INF and not package.filter(F.col("multiplicity") > int(q.upper)).isEmpty():
        return False
    rows = audit(package, q, relation).collect()
    return not rows or any(all(r.satisfied for r in rows if r.branch == b) for b in {r.branch for r in rows})


def objective_value(package: DataFrame, q: PackageQuery) -> float:
    return package_aggregates(package, q).first()["objective"]


def exclude(relation: DataFrame, package: DataFrame) -> DataFrame:
    """Tuples that the package doesn't use."""
    return relation.join(package.select("tid"), "tid", "left_anti")


def package_union(a: DataFrame, b: DataFrame) -> DataFrame:
    """Multiset union: multiplicities add."""
    columns = [c for c in a.columns if c != "multiplicity"]
    return a.unionByName(b).groupBy(*columns).agg(F.sum("multiplicity").cast("int").alias("multiplicity"))


def package_except(a: DataFrame, b: DataFrame) -> DataFrame:
    """Multiset difference."""
    rest = F.col("multiplicity") - F.coalesce(F.col("taken"), F.lit(0))
    return a.join(b.select("tid", F.col("multiplicity").alias("taken")), "tid", "left").withColumn("multiplicity", rest.cast("int")).filter("multiplicity > 0").drop("taken")


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """tid, multiplicity in a, in b, for tuples that differ."""
    left, right = a.select("tid", F.col("multiplicity").alias("in_a")), b.select("tid", F.col("multiplicity").alias("in_b"))
    return left.join(right, "tid", "full_outer").na.fill(0).filter("in_a <> in_b")
