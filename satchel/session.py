"""Statements on views: the engine's entry point for users."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .lang.ast import PackageQuery
from .lang.parser import parse_package, to_statement
from .operators.coarse_fine import FineLimits, coarse_fine
from .operators.whole import whole_solve
from .package.result import PackageResult
from .partition.quad import Partitioning, quad_partition
from .plans.coefficients import coefficient_frame, limits_columns, translate, with_tid
from .plans.rules import query_attributes
from .solve.problem import SolverLimits


def relation_of(spark: SparkSession, q: PackageQuery) -> DataFrame:
    """The query's relation; several views are cross-referenced by the filter, so they are joined on it."""
    if isinstance(q.relation, DataFrame):
        return q.relation
    if isinstance(q.relation, str):
        return spark.table(q.relation)
    out = None
    for name, alias in q.relation:
        one = spark.table(name).alias(alias)
        out = one if out is None else out.join(one)
    return out.filter(q.where) if q.where else out


def package_sql(spark: SparkSession, text: str, method: str = "auto", part: Partitioning | None = None, tau: int = 10_000, limits: SolverLimits = SolverLimits(), **options) -> PackageResult:
    """method: whole, coarse-fine, or auto (whole where the columns fit the memory limit)."""
    q = parse_package(text)
    df = part.df.drop("gid") if part else relation_of(spark, q)
    if isinstance(q.relation, tuple):
        from dataclasses import replace

        q = replace(q, where=None)
    df = with_tid(df)
    if method == "auto":
        t = translate(df, q)
        method = "whole" if part is None and coefficient_frame(df, t).count() <= limits_columns(limits, t) else "coarse-fine"
    if method == "whole":
        return whole_solve(df, q, limits)
    if part is None:
        numeric = {f.name for f in df.schema.fields if f.dataType.typeName() in ("integer", "long", "double", "float")}
        part = quad_partition(df, sorted(query_attributes(q) & numeric), tau)
    return coarse_fine(part, q, FineLimits(seconds=limits.seconds), **options)


def explain_package(df: DataFrame, q: PackageQuery) -> str:
    """Rows, columns, alternatives and Spark's plan of the coefficient scan."""
    t = translate(df, q)
    frame = coefficient_frame(df, t)
    plan = frame._jdf.queryExecution().toString()
    rows = "\n".join(f"  {r.name}: {r.lo} <= sum({r.sql}) <= {r.hi}" for r in t.rows)
    return f"{to_statement(q)}\nalternatives: {len(t.branches)}\nrows:\n{rows}\nobjective: {q.sense} sum({t.objective})\n{plan}"
