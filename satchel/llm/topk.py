"""Exact top-k inner products: long vectors first, partial sums after a rotation, Cauchy-Schwarz bounds.

Components become integers floor(256 x). Candidates are ranged by length into bands and packed into blocks of
BLOCK_ROWS; no block is larger, whatever many vectors are equal. The block of the longest vectors is scored
with all queries first and gives each a score that its answers reach. A query then needs only bands whose
longest vector could still reach that score; query blocks are sent to those bands alone, by a shuffle that
neither side crosses the driver in: there are no more bands than keep what is sent near the size of the vectors. In a block, sums
over the first HEAD_DIMS rotated components plus the product of the residual lengths bound each score;
candidates that no query of the block can use are left out, the others are scored exactly. Rotation is by the right singular
vectors of at most SAMPLE_ROWS vectors; it changes speed only, never results.

Defined results: rows without vec_id, and vectors null or with null or non-finite components, take no part;
shorter vectors count as padded with zeros; a query's own row is every row with its vec_id, and a repeated
query id is one query (the smallest vector); repeated candidates stay; ties go to the smaller vec_id;
scores beyond 64 bits are cut to them; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialize, ship, table

BLOCK_ROWS, QUERY_ROWS, BAND_ROWS, SAMPLE_ROWS, HEAD_DIMS = 4096, 512, 16_384, 20_000, 16
#: Bands that there may always be; more only while queries sent to all of them are at most twice the vectors.
BANDS = 64
LEAST = -(1 << 63)
BLOCK = "band int, longest double, dims int, ids binary, ints binary"
QUERIES = "block long, ratio double, dims int, ids binary, ints binary, reach binary"


def integers(vector: Column) -> Column:
    return F.transform(vector, lambda x: F.floor(F.lit(256.0) * x.cast("double")).cast("long"))


def usable(vector: Column) -> Column:
    fine = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x.cast("double")) & (F.abs(x.cast("double")) < float("inf")))
    return vector.isNotNull() & fine


def exact_products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Integer inner products of rows; float64 only where it is exact, Python integers where 64 bits are too few."""
    if not a.size or not b.size:
        return np.zeros((len(a), len(b)), np.int64)
    most = float(np.abs(a.astype(float)).max()) * float(np.abs(b.astype(float)).max()) * a.shape[1]
    if most < 2**52:
        return (a.astype(float) @ b.T.astype(float)).astype(np.int64)
    if most < 2**62:
        return a @ b.T
    return np.clip(a.astype(object) @ b.T.astype(object), LEAST, -LEAST - 1).astype(np.int64)


def best(query_ids: np.ndarray, ids: np.ndarray, scores: np.ndarray, may: np.ndarray, k: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Per query with any: its k highest scores among the allowed, ties to smaller ids."""
    for i in np.flatnonzero(may.any(1)):
        own = np.flatnonzero(may[i])
        s = scores[i, own]
        if len(own) > k:
            own = own[s >= np.partition(s, len(s) - k)[len(s) - k]]
            s = scores[i, own]
        order = np.lexsort((ids[own], -s))[:k] if s.min() > LEAST else np.lexsort((ids[own], -s.astype(float)))[:k]
        yield int(query_ids[i]), ids[own[order]], s[order]


def _padded(rows: np.ndarray, dims: int) -> np.ndarray:
    return rows if rows.shape[1] == dims else np.pad(rows, ((0, 0), (0, dims - rows.shape[1])))


def _packed(rows: np.ndarray) -> bytes:
    """The rows in the fewest bytes a component that hold them all."""
    low, high = int(rows.min(initial=0)), int(rows.max(initial=0))
    width = next(w for w in (1, 2, 4, 8) if -(1 << 8 * w - 1) <= low and high < 1 << 8 * w - 1)
    return rows.astype(f"<i{width}").tobytes()


def _matrix(raw: bytes, ids: bytes, dims: int) -> np.ndarray:
    n = len(ids) // 8
    return np.frombuffer(raw, f"<i{len(raw) // (n * dims)}").reshape(n, dims).astype(np.int64)


def _rows(lists: pa.Array, dims: int) -> np.ndarray:
    sizes = lists.value_lengths().to_numpy()
    out = np.zeros((len(lists), dims), np.int64)
    out[np.arange(dims)[None, :] < sizes[:, None]] = lists.flatten().to_numpy()
    return out


def rotation(sample: np.ndarray) -> np.ndarray:
    """Right singular vectors, those of large values first."""
    _, vectors = np.linalg.eigh(sample.T.astype(float) @ sample.astype(float))
    return vectors[:, ::-1]


def pack(vectors: DataFrame, dims: int, bands: int) -> DataFrame:
    """BLOCK rows of vectors (vec_id, v, norm), in bands of falling length."""
    order = (F.col("norm").desc(), F.col("vec_id"))
    ranged = vectors.repartitionByRange(bands, *order).withColumn("band", F.spark_partition_id()).sortWithinPartitions(*order)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, BLOCK_ROWS):
                some = batch.slice(at, BLOCK_ROWS)
                yield pa.RecordBatch.from_pydict({"band": pa.array([some.column(3)[0].as_py()], pa.int32()), "longest": [some.column(2)[0].as_py()], "dims": pa.array([dims], pa.int32()), "ids": [some.column(0).to_numpy().astype("<i8").tobytes()], "ints": [_packed(_rows(some.column(1), dims))]})

    return ranged.select("vec_id", "v", "norm", "band").mapInArrow(run, BLOCK)


def top_inner_products(vectors: DataFrame, is_query: Column, k: int = 5, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score of each query's k best candidates."""
    spark = vectors.sparkSession
    ship(spark)
    clean = vectors.filter(F.col(id_col).isNotNull() & usable(F.col(vector_col)))
    length = F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x))
    clean = clean.select(F.col(id_col).cast("long").alias("vec_id"), integers(F.col(vector_col)).alias("v"), is_query.alias("asked")).withColumn("norm", length)
    n, dims, askers = clean.agg(F.count(F.lit(1)), F.coalesce(F.max(F.size("v")), F.lit(0)), F.count_if("asked")).first()
    schema = "query_id long, rank int, vec_id long, score long"
    if not n:
        return spark.createDataFrame([], schema)
    dims = max(dims, 1)
    slots = 1 << 20
    sampled = clean.filter(F.pmod(F.xxhash64("vec_id"), F.lit(slots)) < max(1, int(slots * min(1.0, SAMPLE_ROWS / n)))).select("v").limit(SAMPLE_ROWS).toArrow()
    turn = rotation(_rows(sampled["v"].combine_chunks(), dims)) if len(sampled) else np.eye(dims)

    bands = min(-(-n // BAND_ROWS), max(BANDS, 2 * n // max(1, askers)))
    blocks = materialize(pack(clean.select("vec_id", "v", "norm"), dims, bands), "topk-blocks")
    reach_of = {r.band: r.longest for r in blocks.groupBy("band").agg(F.max("longest").alias("longest")).collect()}
    first = min(reach_of, key=lambda b: (-reach_of[b], b))
    head = blocks.filter((F.col("band") == first) & (F.col("longest") == reach_of[first])).first()  # sorting whole blocks would send one of each task
    head_ids, head_rows = np.frombuffer(head.ids, "<i8"), _matrix(head.ints, head.ids, head.dims)

    def first_scores(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, rows = batch.column(0).to_numpy(), _rows(batch.column(1), dims)
            scores, may = exact_products(rows, head_rows), ids[:, None] != head_ids[None, :]
            reach = np.full(len(ids), LEAST)
            enough = may.sum(1) >= k
            if enough.any():
                allowed = np.where(may, scores, LEAST)[enough]
                reach[enough] = np.partition(allowed, allowed.shape[1] - k, axis=1)[:, -k]
            norms = np.maximum(batch.column(2).to_numpy(), 1e-9)
            ratio = np.where(reach > LEAST, reach / norms * (1 - 1e-9 * np.sign(reach)), -np.inf)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(reach), pa.array(ratio)], ["vec_id", "v", "reach", "ratio"])

    asked = clean.filter("asked").groupBy("vec_id").agg(F.min(F.struct("v", "norm")).alias("q")).select("vec_id", "q.v", "q.norm")
    asked = materialize(asked.mapInArrow(first_scores, "vec_id long, v array<bigint>, reach long, ratio double"), "topk-queries")

    def pack_queries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, QUERY_ROWS):
                some = batch.slice(at, QUERY_ROWS)
                ids = some.column(0).to_numpy().astype("<i8")
                yield pa.RecordBatch.from_pydict({"block": [int(ids[0])], "ratio": [min(some.column(3).to_pylist())], "dims": pa.array([dims], pa.int32()), "ids": [ids.tobytes()], "ints": [_packed(_rows(some.column(1), dims))], "reach": [some.column(2).to_numpy().astype("<i8").tobytes()]})

    parts = max(1, n // 50 // QUERY_ROWS // 4)
    question = asked.repartitionByRange(parts, "ratio", "vec_id").sortWithinPartitions("ratio", "vec_id").mapInArrow(pack_queries, QUERIES)
    longest = spark.createDataFrame([(b, float(x)) for b, x in reach_of.items()], "band int, reaches double")
    # Blocks are far larger in memory than the planner expects: only the list of bands may be broadcast.
    question = question.join(F.broadcast(longest), F.col("reaches") >= F.col("ratio"))
    pairs = question.select("band", "block", F.col("ids").alias("q_ids"), F.col("ints").alias("q_ints"), "reach").join(blocks.hint("merge"), "band")

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        head_turn, rest_turn = turn[:, :HEAD_DIMS], turn[:, HEAD_DIMS:]
        for batch in batches:
            out: list[tuple[int, int, int]] = []
            for q_ids, q_ints, reach, ids, ints in zip(*(batch.column(c).to_pylist() for c in ("q_ids", "q_ints", "reach", "ids", "ints")), strict=True):
                q, c = _matrix(q_ints, q_ids, dims), _matrix(ints, ids, dims)
                q_ids, reach, ids = (np.frombuffer(raw, "<i8") for raw in (q_ids, reach, ids))
                qf, cf = q.astype(float), c.astype(float)
                bound = (qf @ head_turn) @ (cf @ head_turn).T + np.outer(np.linalg.norm(qf @ rest_turn, axis=1), np.linalg.norm(cf @ rest_turn, axis=1))
                slack = 1e-9 * np.outer(np.linalg.norm(qf, axis=1), np.linalg.norm(cf, axis=1)) + 1e-6
                may = (bound + slack >= reach[:, None].astype(float)) & (q_ids[:, None] != ids[None, :])
                columns = np.flatnonzero(may.any(0))
                if len(columns):
                    rows = np.flatnonzero(may.any(1))
                    scores = exact_products(q[rows], c[columns])
                    some = may[np.ix_(rows, columns)] & (scores >= reach[rows][:, None])
                    for query, found, s in best(q_ids[rows], ids[columns], scores, some, k):
                        out += zip([query] * len(found), found.tolist(), s.tolist(), strict=True)
            query, found, s = zip(*out, strict=True) if out else ((), (), ())
            yield pa.RecordBatch.from_arrays([pa.array(query, pa.int64()), pa.array(found, pa.int64()), pa.array(s, pa.int64())], ["query_id", "vec_id", "score"])

    scored = pairs.mapInArrow(score, "query_id long, vec_id long, score long")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id"))
    return scored.withColumn("rank", rank.cast("int")).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op9_top_products(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_inner_products(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


OP9_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS e
  FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(list_zip(q.e, c.e), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id)
SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score
FROM s QUALIFY rank <= 5
"""
