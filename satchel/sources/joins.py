"""Relations for packages: readers, the pre-join, and three ways to package a join."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..lang.ast import PackageQuery
from ..operators.whole import whole_solve
from ..package.result import PackageResult
from ..plans.coefficients import coefficient_frame, translate
from ..scratch import stored, stored_bytes
from ..solve.problem import SolverLimits

LINE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]


def read_source(spark: SparkSession, kind: str, path: str, schema=None, **options) -> DataFrame:
    """kind: parquet, csv, json, orc or table."""
    if kind == "table":
        return spark.table(path)
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def prejoin(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem, orders, part, supplier and customer by full outer joins; sizes decide broadcast or merge."""
    line, orders, part, supplier, customer = (table(spark, sf_dir, n) for n in ("lineitem", "orders", "part", "supplier", "customer"))
    out = line.join(orders, line.l_orderkey == orders.o_orderkey, "full_outer")
    out = out.join(part, out.l_partkey == part.p_partkey, "full_outer")
    out = out.join(supplier, out.l_suppkey == supplier.s_suppkey, "full_outer")
    return out.join(customer, out.o_custkey == customer.c_custkey, "full_outer")


def non_null(df: DataFrame, columns: list[str]) -> DataFrame:
    return df.dropna(subset=columns)


def package_over_join(left: DataFrame, right: DataFrame, on, key: list[str], q: PackageQuery, mode: str = "materialized", limits: SolverLimits = SolverLimits()) -> PackageResult:
    """materialized: write the join, then evaluate. pipelined: run the join inside the scan, and again for the chosen rows.
    ids: keep only keys and coefficients, and look the chosen rows up by key."""
    joined = left.join(right, on)
    if mode == "materialized":
        kept = stored(_with_key(joined, key), "join")
        out = whole_solve(kept, q, limits)
        out.counters["bytes"] = stored_bytes(kept)
        return out
    rows = _with_key(joined, key)
    if mode == "pipelined":
        out = whole_solve(rows, q, limits)
        out.counters["bytes"] = 0
        return out
    t = translate(rows, q)
    narrow = stored(coefficient_frame(rows, t), "join-ids")
    n = narrow.count()
    from ..operators.reduced import DIRECT_COLUMNS
    from ..operators.whole import reduced_branches, solve_branches
    from ..plans.coefficients import collect_columns, limits_columns
    from ..solve.branch import BranchAndBound

    most = limits_columns(limits, t)
    if n > DIRECT_COLUMNS:
        r, branch = reduced_branches(narrow, t, limits, most)
        return PackageResult(q, rows, r.solution.status, r.chosen, r.solution.objective, r.solution.bound, branch, counters={"columns": n, "bytes": stored_bytes(narrow)})
    data = collect_columns(narrow, t, most)
    s, branch, _ = solve_branches(t, data, BranchAndBound(limits))
    chosen = {int(i): int(round(k)) for i, k in zip(data[0], s.x, strict=True) if k > 0.5} if s.found else {}
    return PackageResult(q, rows, s.status, chosen, s.objective, s.bound, branch, counters={"columns": n, "bytes": stored_bytes(narrow)})


def _with_key(joined: DataFrame, key: list[str]) -> DataFrame:
    """tid as a hash of the key: the same whenever the join runs."""
    return joined.withColumn("tid", F.xxhash64(*key))


def join_tradeoff(left: DataFrame, right: DataFrame, on, key: list[str], q: PackageQuery) -> list[tuple[str, float, int, float | None]]:
    """mode, seconds, bytes written and objective of each."""
    out = []
    for mode in ("materialized", "pipelined", "ids"):
        begin = time.perf_counter()
        r = package_over_join(left, right, on, key, q, mode)
        out.append((mode, time.perf_counter() - begin, r.counters["bytes"], r.objective))
    return out


def as_of(left: DataFrame, right: DataFrame, time_col: str, by: str) -> DataFrame:
    """Each left row with the latest right row of the same key not after it (columns prefixed r_); one sort of the union, no range join."""
    from pyspark.sql import Window

    names = [c for c in right.columns if c not in (time_col, by)]
    own, seen = F.struct(*left.columns), F.struct(*names)
    own_type, seen_type = left.select(own.alias("s")).schema["s"].dataType, right.select(seen.alias("s")).schema["s"].dataType
    a = left.select(by, time_col, own.alias("__own"), F.lit(None).cast(seen_type).alias("__seen"), F.lit(1).alias("__side"))
    b = right.select(by, time_col, F.lit(None).cast(own_type).alias("__own"), seen.alias("__seen"), F.lit(0).alias("__side"))
    w = Window.partitionBy(by).orderBy(time_col, "__side").rowsBetween(Window.unboundedPreceding, 0)
    out = a.unionByName(b).withColumn("__last", F.last("__seen", ignorenulls=True).over(w)).filter("__side = 1")
    return out.select("__own.*", *(F.col(f"__last.{n}").alias(f"r_{n}") for n in names))
