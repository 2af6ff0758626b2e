"""Mixing sources to target weights by nested thresholds on a hash of the key.

Every document has a 60-bit hash. A source with target T and size S takes each of its documents
floor(T / S) times, and once more those whose hash is small enough for the rest R of the target. The
threshold is found without sorting: sizes are summed by source and the 12 highest bits of the hash, the
bucket in which the running sum passes R is the only one looked into further, by the next 12 bits, until it
holds one hash. Documents with that hash are taken if this brings the source nearer to its target. A larger
target keeps all that a smaller one takes, so mixes are nested, and reruns agree.

Weights repeat 5, 2, 1 over the sources in code-point order, null last. Targets share the total by weight but
stop at CAP times the source's size; what is left over is shared again by weight among the others.

Defined results: null and empty texts have size 0, and a source of size 0 has target 0; rows with equal keys
in a source have one hash and are taken together; a null key hashes as the text 'null'; an empty table gives
no rows. Tables of sources (one row per source) are joined as Spark sees fit; rows are only ever summed.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialize, table

WEIGHTS, CAP = (5, 2, 1), 3
HASH_BITS, STEP_BITS = 60, 12
WORD = r"[^\x20\x09-\x0D]+"


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def key_hash(key: Column) -> Column:
    """The first 60 bits of the key's MD5."""
    return F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("null")).cast("binary")), 1, HASH_BITS // 4), 16, 10).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, cap: int = CAP) -> DataFrame:
    """sizes: source, source_size (one row per source) -> also target."""
    in_order = Window.orderBy(F.col("source").asc_nulls_last())
    weighed = sizes.withColumn("nth", F.row_number().over(in_order))
    weighed = weighed.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), F.pmod(F.col("nth") - 1, F.lit(len(weights))) + 1).cast("long"))
    by_room = Window.orderBy(F.col("source_size") / F.col("weight"), "nth")
    below = by_room.rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    level = (F.col("total") - cap * F.coalesce(F.sum("source_size").over(below), F.lit(0))) / (F.col("weights") - F.coalesce(F.sum("weight").over(below), F.lit(0)))
    leveled = weighed.withColumns({"total": F.sum("source_size").over(whole), "weights": F.sum("weight").over(whole)}).withColumns({"level": level, "place": F.row_number().over(by_room)})
    fits = F.col("level") * F.col("weight") <= cap * F.col("source_size")
    leveled = leveled.withColumn("first", F.min(F.when(fits, F.struct("place", "level"))).over(whole))
    capped = F.col("first").isNull() | (F.col("place") < F.col("first.place"))
    return leveled.select("source", "source_size", F.when(capped, (cap * F.col("source_size")).cast("double")).otherwise(F.col("first.level") * F.col("weight")).alias("target"))


def thresholds(rows: DataFrame, sources: DataFrame) -> DataFrame:
    """rows: source, size, hash; sources: source, source_size, target -> also whole (times all are taken) and limit: hashes up to it are taken once more."""
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(1)).cast("long")
    state = sources.withColumn("whole", whole).withColumn("rest", F.col("target") - F.col("whole") * F.col("source_size"))
    state = state.withColumns({"path": F.lit(0).cast("long"), "before": F.lit(0).cast("long"), "limit": F.when(F.col("source_size") == 0, F.lit(-1)).cast("long")})
    state = materialize(state, "mix-sources")
    for shift in range(HASH_BITS - STEP_BITS, -1, -STEP_BITS):
        open_ = state.filter("limit is null").select(F.col("source").alias("s"), "rest", "path", "before")
        inside = rows.join(open_, F.col("source").eqNullSafe(F.col("s")) & (F.shiftright("hash", shift + STEP_BITS) == F.col("path")))
        sums = inside.groupBy("source", F.shiftright("hash", shift).alias("bucket")).agg(F.sum("size").alias("size"), F.min("hash").alias("low"), F.max("hash").alias("high"), F.first("rest").alias("rest"), F.first("before").alias("before"))
        up = Window.partitionBy("source").orderBy("bucket")
        running = sums.withColumn("upto", F.col("before") + F.sum("size").over(up))
        passing = running.filter(F.col("upto") > F.col("rest")).groupBy(F.col("source").alias("s")).agg(F.min(F.struct("bucket", "size", "low", "high", "upto")).alias("b"))
        start = F.col("b.upto") - F.col("b.size")
        one = F.col("b.low") == F.col("b.high")
        near = F.when(start + F.col("b.upto") <= 2 * F.col("rest"), F.col("b.high")).otherwise(F.col("b.low") - 1)
        joined = state.join(passing, F.col("source").eqNullSafe(F.col("s")), "left")
        found = F.when(F.col("b").isNull(), F.lit((1 << HASH_BITS) - 1)).when(one, near)
        state = materialize(joined.select("source", "source_size", "target", "whole", "rest", F.coalesce(F.col("b.bucket"), "path").alias("path"), F.coalesce(start, "before").alias("before"), F.coalesce("limit", found).alias("limit")), "mix-sources")
        if state.filter("limit is null").isEmpty():
            break
    return state


def mixed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = WEIGHTS, cap: int = CAP) -> DataFrame:
    """id_col, source, size, hash, source_size, target and copies: the times the mix takes each row."""
    rows = docs.select(F.col(id_col).alias(id_col), F.col(source_col).cast("string").alias("source"), word_count(F.col(text_col)).alias("size"), key_hash(F.col(id_col)).alias("hash"))
    rows = materialize(rows, "mix-rows")
    return _with_copies(rows, _limits(rows, weights, cap))


def _limits(rows: DataFrame, weights: tuple[int, ...], cap: int) -> DataFrame:
    sizes = rows.groupBy("source").agg(F.sum("size").alias("source_size"))
    return thresholds(rows, source_targets(sizes, weights, cap)).select(F.col("source").alias("mix_source"), "source_size", "target", "whole", "limit")


def _with_copies(rows: DataFrame, limits: DataFrame) -> DataFrame:
    once = F.when(F.col("hash") <= F.col("limit"), F.lit(1)).otherwise(F.lit(0))
    return rows.join(limits, F.col("source").eqNullSafe(F.col("mix_source"))).withColumn("copies", F.col("whole") + once).drop("mix_source", "whole", "limit")


def mix_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = WEIGHTS, cap: int = CAP) -> DataFrame:
    """The mix itself: rows of docs, each as often as it is taken."""
    names = docs.columns
    mine = F.struct(*(F.col(f"`{c}`") for c in names))
    rows = materialize(docs.select(F.col(source_col).cast("string").alias("source"), word_count(F.col(text_col)).alias("size"), key_hash(F.col(id_col)).alias("hash")), "mix-rows")
    full = docs.select(mine.alias("row"), F.col(source_col).cast("string").alias("source"), key_hash(F.col(id_col)).alias("hash"))
    taken = _with_copies(full, _limits(rows, weights, cap)).filter("copies > 0")
    return taken.select("row", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("row.*")


def op7_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mixed(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


OP7_SQL = r"""
WITH d AS (
  SELECT doc_id, source,
         CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
         CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), 'null')), 1, 15) AS BIGINT) AS h
  FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS ss, row_number() OVER (ORDER BY source NULLS LAST) AS nth FROM d GROUP BY source),
w AS (SELECT *, CASE (nth - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS wt FROM s),
l AS (
  SELECT *, row_number() OVER (ORDER BY CAST(ss AS DOUBLE) / wt, nth) AS place,
         CAST(sum(ss) OVER () - 3 * coalesce(sum(ss) OVER (ORDER BY CAST(ss AS DOUBLE) / wt, nth ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE)
         / CAST(sum(wt) OVER () - coalesce(sum(wt) OVER (ORDER BY CAST(ss AS DOUBLE) / wt, nth ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE) AS lev
  FROM w),
f AS (SELECT min(place) AS p, arg_min(lev, place) AS lev FROM l WHERE lev * wt <= 3 * ss),
t AS (SELECT l.source, ss, CASE WHEN f.p IS NULL OR place < f.p THEN CAST(3 * ss AS DOUBLE) ELSE f.lev * wt END AS target FROM l, f),
u AS (SELECT *, CASE WHEN ss > 0 THEN CAST(floor(target / ss) AS BIGINT) ELSE 1 END AS whole FROM t),
c AS (
  SELECT d.*, u.ss, u.target, u.whole, u.target - u.whole * u.ss AS rest,
         sum(size) OVER (PARTITION BY d.source ORDER BY h RANGE UNBOUNDED PRECEDING) AS upto,
         sum(size) OVER (PARTITION BY d.source, h) AS own
  FROM d JOIN u ON d.source IS NOT DISTINCT FROM u.source)
SELECT doc_id, size, ss AS source_size, target,
       CAST(size * (whole + CASE WHEN upto <= rest OR (upto - own <= rest AND 2 * upto - own <= 2 * rest) THEN 1 ELSE 0 END) AS BIGINT) AS taken
FROM c
"""
