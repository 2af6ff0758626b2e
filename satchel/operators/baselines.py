"""Evaluation in SQL alone, and cheap comparisons: self joins, the powerset, greedy knapsacks, grid windows."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..lang.ast import INF, Agg, PackageQuery
from ..plans.coefficients import coefficient_frame, translate
from ..plans.rules import disjuncts
from ..scratch import stored


def self_join_packages(df: DataFrame, k: int, key: str, bounds: dict[str, tuple[float, float]], objective: str, sense: str = "min", repeat: int = 0, prune: bool = False, limit: int | None = 1) -> DataFrame:
    """Packages of exactly k tuples by joining the relation k - 1 times with itself in key order.

    bounds: column -> lowest and highest sum. prune drops partial packages over an upper bound where the column
    has no negative value. Returns the keys, the sums and the objective's sum; the best only, unless limit is None.
    """
    columns = list(dict.fromkeys([*bounds, objective]))
    signs = df.agg(*(F.min(c).alias(c) for c in columns)).first() if prune else None
    part = lambda i: df.select(F.col(key).alias(f"k{i}"), *(F.col(c).alias(f"{c}_{i}") for c in columns))
    out = part(1).select("k1", *(F.col(f"{c}_1").alias(c) for c in columns))
    for i in range(2, k + 1):
        step = F.col(f"k{i - 1}") < F.col(f"k{i}") if not repeat else F.col(f"k{i - 1}") <= F.col(f"k{i}")
        joined = out.join(part(i), step)
        if repeat and i > repeat + 1:
            joined = joined.filter(F.col(f"k{i}") != F.col(f"k{i - repeat - 1}"))
        out = joined.select(*(f"k{j}" for j in range(1, i + 1)), *((F.col(c) + F.col(f"{c}_{i}")).alias(c) for c in columns))
        if prune:
            for c, (_, hi) in bounds.items():
                if signs[c] is not None and signs[c] >= 0 and hi < INF:
                    out = out.filter(F.col(c) <= hi)
    for c, (lo, hi) in bounds.items():
        out = out.filter(F.col(c).between(lo, hi))
    if limit is None:
        return out
    best = F.col(objective).asc() if sense == "min" else F.col(objective).desc()
    return out.orderBy(best, *(f"k{j}" for j in range(1, k + 1))).limit(limit)


def self_join_summary(df: DataFrame, k: int, key: str, bounds: dict[str, tuple[float, float]], objective: str, sense: str = "min") -> DataFrame:
    """packages: how many sets of k tuples satisfy the bounds; best: their best sum of the objective.

    Tuples of equal bound columns form a class, and classes are joined with themselves in place of tuples: a class gives m of its
    n tuples in n over m ways, at best its m best ones. Partial sets that end in the same class with equal sums are one row.
    key: unique; tuples without one, or with a null in bounds, are in no package.
    """
    columns, best_of = list(bounds), F.min if sense == "min" else F.max
    rows = df.filter(F.col(key).isNotNull()).dropna(subset=columns)
    place = F.row_number().over(Window.partitionBy(*columns).orderBy(F.col(objective).asc_nulls_last() if sense == "min" else F.col(objective).desc_nulls_last()))
    firsts = rows.select(*columns, objective, place.alias("place")).filter(F.col("place") <= k)
    firsts = firsts.groupBy(*columns).agg(F.transform(F.sort_array(F.collect_list(F.struct("place", objective))), lambda s: s[objective]).alias("top"))
    classes = rows.groupBy(*columns).agg(F.count(F.lit(1)).alias("n")).join(firsts, columns)
    taken = classes.withColumn("m", F.explode(F.sequence(F.lit(1), F.least(F.lit(k).cast("long"), "n").cast("int"))))
    ways = F.expr("aggregate(sequence(0, m - 1), 1L, (w, i) -> w * (n - i) DIV (i + 1))")  # raises where it overflows
    worth = F.when(F.forall(F.slice("top", F.lit(1), F.col("m")), lambda v: v.isNotNull()), F.expr("aggregate(slice(top, 2, m - 1), top[0], (s, v) -> s + v)"))
    step = stored(taken.select(F.struct(*columns).alias("last"), F.col("m").alias("size"), *((F.col(c) * F.col("m")).alias(c) for c in columns), ways.alias("ways"), worth.alias("best")), "classes")
    signs = rows.agg(*(F.min(c).alias(c) for c in columns)).first()
    upto = [F.col(c) <= hi for c, (_, hi) in bounds.items() if signs[c] is not None and signs[c] >= 0 and hi < INF]
    fits = reduce(lambda a, b: a & b, upto, F.lit(True))
    partial, done = step.filter(fits), []
    for i in range(1, k + 1):
        done.append(partial.filter(F.col("size") == k))
        if i == k:
            break
        more = step.select(*(F.col(c).alias(f"{c}_") for c in step.columns))
        joined = partial.filter(F.col("size") < k).join(more, (F.col("last") < F.col("last_")) & (F.col("size") + F.col("size_") <= k))
        joined = joined.select(F.col("last_").alias("last"), (F.col("size") + F.col("size_")).alias("size"), *((F.col(c) + F.col(f"{c}_")).alias(c) for c in columns), (F.col("ways") * F.col("ways_")).alias("ways"), (F.col("best") + F.col("best_")).alias("best"))
        partial = joined.filter(fits).groupBy("last", "size", *columns).agg(F.sum("ways").alias("ways"), best_of("best").alias("best"))
    found = reduce(DataFrame.unionByName, done)
    for c, (lo, hi) in bounds.items():
        found = found.filter(F.col(c).between(lo, hi))
    return found.agg(F.coalesce(F.sum("ways"), F.lit(0).cast("long")).alias("packages"), best_of("best").alias("best"))


def powerset_packages(df: DataFrame, key: str, columns: list[str], most: int = 20) -> DataFrame:
    """Every non-empty subset of a tiny relation: keys (ascending), size and sums. Grown one tuple at a time."""
    n = df.count()
    if n > most:
        raise ValueError(f"the powerset of {n} tuples is refused; at most {most}")
    item = df.select(F.col(key).alias("k"), *(F.col(c).alias(f"{c}_i") for c in columns))
    front = item.select(F.array("k").alias("keys"), *(F.col(f"{c}_i").alias(c) for c in columns))
    levels = [front]
    for _ in range(n - 1):
        front = front.join(item, F.col("k") > F.element_at("keys", -1)).select(F.concat("keys", F.array("k")).alias("keys"), *((F.col(c) + F.col(f"{c}_i")).alias(c) for c in columns))
        levels.append(front)
    return reduce(DataFrame.unionByName, levels).withColumn("size", F.size("keys"))


def powerset_recursive_sql(view: str, key: str, column: str) -> str:
    """The same as one recursive statement of Spark SQL."""
    return f"""WITH RECURSIVE grown(last, size, total) AS (
      SELECT {key}, 1, {column} FROM {view}
      UNION ALL
      SELECT v.{key}, size + 1, total + v.{column} FROM grown JOIN {view} v ON v.{key} > last)
    SELECT size, total FROM grown"""


def is_knapsack(q: PackageQuery) -> bool:
    """Sums bounded from above only, a sum to maximise, no repetition."""
    branches = disjuncts(q.such_that)
    if q.sense != "max" or q.repeat != 0 or len(branches) != 1 or q.objective is None:
        return False
    terms = [(w, a) for c in branches[0] for w, a in c.linear.terms] + list(q.objective.terms)
    return all(c.lo == -INF for c in branches[0]) and all(w > 0 and a.kind in ("sum", "count") for w, a in terms)


def greedy_knapsack(df: DataFrame, q: PackageQuery) -> DataFrame:
    """tid, obj and weight of the tuples taken by density while the first bound holds; stops at the first that doesn't fit."""
    t = translate(df, q)
    i = t.branches[0][0]
    hi = t.rows[i].hi
    frame = coefficient_frame(df, t).filter(f"obj > 0 and c_{i} <= {hi!r}")
    order = Window.orderBy((F.col("obj") / F.greatest(F.col(f"c_{i}"), F.lit(1e-12))).desc(), "tid")
    running = F.sum(f"c_{i}").over(order.rowsBetween(Window.unboundedPreceding, 0))
    return frame.withColumn("upto", running).filter(F.col("upto") <= hi).select("tid", "obj", F.col(f"c_{i}").alias("weight"))


def top_by_objective(df: DataFrame, column: str, k: int, sense: str = "max") -> DataFrame:
    """Where only COUNT = k binds, a sort answers."""
    return df.orderBy(F.col(column).desc() if sense == "max" else F.col(column), "tid").limit(k)


def grid_windows(df: DataFrame, x: str, y: str, width: int, height: int, condition: str, cell: tuple[float, float] = (1.0, 1.0)) -> DataFrame:
    """Rectangles of width x height grid cells, with n and total of their tuples, that satisfy condition.

    df needs a column value. Cells are counted once; each cell then adds to the width * height rectangles that hold it.
    """
    cells = df.groupBy(F.floor(F.col(x) / cell[0]).alias("cx"), F.floor(F.col(y) / cell[1]).alias("cy")).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    spread = cells.withColumn("dx", F.explode(F.sequence(F.lit(0), F.lit(width - 1)))).withColumn("dy", F.explode(F.sequence(F.lit(0), F.lit(height - 1))))
    return spread.groupBy((F.col("cx") - F.col("dx")).alias("wx"), (F.col("cy") - F.col("dy")).alias("wy")).agg(F.sum("n").alias("n"), F.sum("total").alias("total")).filter(condition)


def count_only(q: PackageQuery) -> bool:
    return all([(w, a) for w, a in c.linear.terms] == [(1.0, Agg("count"))] for b in disjuncts(q.such_that) for c in b)


def sum_column(name: str) -> Column:
    return F.coalesce(F.sum(name), F.lit(0.0))
