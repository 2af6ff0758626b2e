"""Toxicity by a factorization machine over hashed terms.

A text's terms are its runs of letters, lower-cased and hashed into 2^22 buckets; presence counts. A
factorization machine has a linear weight for every bucket of a bounded sample of labelled rows, plus an inner
product of factors for every pair that a text holds, so a pair can count where neither term does. It is fitted in two
rounds: the buckets that surely tell the labels apart (chi-square) first, which gives a start; then all buckets from
there, by sparse updates. The second round takes smaller steps (CAUTION) for buckets without evidence of their own,
which holds back chance, but leaves none out.

Bounds: SAMPLE_ROWS labelled rows at most (by a hash of the key); the model has FACTORS + 1 numbers for each
bucket of the sample, of which there are 2^22 at most. One task holds the sample and fits; the driver gets the model only. Labels, language, source and key are never inputs of a score.

Defined results: null and empty texts have no terms and get the model's base score; a key with several
labels counts as toxic if any says so; without labels of both kinds every score is the share of toxic
ones (0 without labels); repeated rows are each scored by themselves; other columns are not read.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lean, ship, table

BUCKET_BITS, START_BUCKETS, FACTORS = 22, 2048, 8
SAMPLE_ROWS, STEPS, BATCH, RATE, SHRINK, FEWEST = 20_000, 1500, 256, 0.3, 1e-4, 4
CAUTION, SHRINK_USED = 0.2, 1e-5
MEMO_ENTRIES = 200_000
#: Lower-cases ASCII letters; everything else in ASCII separates. Other bytes stay, so accented words stay whole.
FOLD = bytes(b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def terms(raw: bytes) -> set[bytes]:
    return set(raw.translate(FOLD).split())


def bucket(term: bytes) -> int:
    return zlib.crc32(term) & (1 << BUCKET_BITS) - 1


def is_held_out(key: Column) -> Column:
    return F.coalesce(F.crc32(key.cast("string").cast("binary")), F.lit(0)) % 5 == 0


class Places:
    """The position of each bucket of a model."""

    def __init__(self, buckets: np.ndarray):
        self.buckets = buckets.astype(np.int32)

    def table(self) -> np.ndarray:
        """By bucket, -1 where the model doesn't have it."""
        out = np.full(1 << BUCKET_BITS, -1, np.int32)
        out[self.buckets] = np.arange(len(self.buckets))
        return out

    def __contains__(self, b: int) -> bool:
        i = int(np.searchsorted(self.buckets, b))
        return i < len(self.buckets) and self.buckets[i] == b

    def __getitem__(self, b: int) -> int:
        if b not in self:
            raise KeyError(b)
        return int(np.searchsorted(self.buckets, b))


class Machine:
    """buckets: ascending."""

    def __init__(self, buckets: np.ndarray, bias: float, weights: np.ndarray, factors: np.ndarray):
        self.place = Places(buckets)
        self.bias, self.weights, self.factors = bias, weights, factors

    def arrays(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return self.place.buckets, self.weights.astype(np.float32), self.factors.astype(np.float32)

    @classmethod
    def of(cls, row) -> Machine:
        """From the row that a fitting task returns."""
        buckets, weights, factors = (np.frombuffer(row[c], kind) for c, kind in (("buckets", np.int32), ("weights", np.float32), ("factors", np.float32)))
        return cls(buckets, row["bias"], weights, factors.reshape(-1, FACTORS))

    def score(self, at: list[int]) -> float:
        z = self.bias
        if at:
            v = self.factors[at]
            z += self.weights[at].sum() + 0.5 * ((v.sum(0) ** 2).sum() - (v**2).sum())
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, float(z)))))


def fit(labels: np.ndarray, lists: list[np.ndarray], seed: int = 7) -> Machine:
    """labels: 0 or 1 for each list of distinct buckets."""
    sizes = np.array([len(x) for x in lists], np.int64)
    return fit_packed(labels, np.concatenate(lists).astype(np.int32) if len(lists) else np.zeros(0, np.int32), sizes, seed)


def start(labels: np.ndarray, columns: np.ndarray, rows: np.ndarray, m: int, seed: int) -> tuple[float, np.ndarray, np.ndarray]:
    """Bias, weights and factors fitted on m buckets only; columns and rows (ascending): where they occur."""
    n, toxic = len(labels), labels.sum()
    starts = np.searchsorted(rows, np.arange(n + 1))
    rng = np.random.default_rng(seed)
    bias, w, v = math.log(toxic / (n - toxic)), np.zeros(m), rng.normal(0, 0.05, (m, FACTORS))
    gb, gw, gv = 1e-2, np.full(m, 1e-2), np.full((m, FACTORS), 1e-2)
    for _ in range(-(-STEPS * BATCH // n)):
        order = rng.permutation(n)
        for k in range(0, n, BATCH):
            chosen = order[k : k + BATCH]
            x = np.zeros((len(chosen), m))
            for i, d in enumerate(chosen):
                x[i, columns[starts[d] : starts[d + 1]]] = 1
            sums = x @ v
            z = bias + x @ w + 0.5 * ((sums**2).sum(1) - (x @ v**2).sum(1))
            off = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - labels[chosen]
            db, dw = off.sum(), x.T @ off + SHRINK * n / BATCH * w
            dv = x.T @ (off[:, None] * sums) - v * (x.T @ off)[:, None] + SHRINK * n / BATCH * v
            gb, gw, gv = gb + db**2, gw + dw**2, gv + dv**2
            bias, w, v = bias - RATE * db / math.sqrt(gb), w - RATE * dw / np.sqrt(gw), v - RATE * dv / np.sqrt(gv)
    return bias, w, v


def fit_packed(labels: np.ndarray, flat: np.ndarray, sizes: np.ndarray, seed: int = 7) -> Machine:
    """The same from all lists one after the other and their sizes."""
    n, toxic = len(labels), int(labels.sum())
    if not n or toxic in (0, n):
        return Machine(np.zeros(0, int), -30.0 if not toxic else 30.0, np.zeros(0), np.zeros((0, FACTORS)))
    held = np.zeros(1 << BUCKET_BITS, bool)
    held[flat] = True
    seen = np.flatnonzero(held).astype(np.int32)
    places = Places(seen).table()
    starts = np.cumsum(sizes) - sizes

    owner = np.repeat(np.arange(n, dtype=np.int32), sizes)
    m = len(seen)
    a, both = np.bincount(places[flat], labels[owner], m), np.bincount(places[flat], minlength=m).astype(float)
    gain = n / (toxic * (n - toxic)) * (a * (n - toxic) - (both - a) * toxic) ** 2 / np.maximum(both * (n - both), 1.0)
    sure = 2 * math.log(max(m, 1) / 0.05)  # about a test at 0.05 over all buckets
    pace = (RATE * (CAUTION + (1 - CAUTION) * np.minimum(1, gain / sure))).astype(np.float32)
    gain[both < FEWEST] = 0
    strong = np.sort(np.argsort(-gain, kind="stable")[: min(START_BUCKETS, max(int((gain >= sure).sum()), 16))])
    strong = strong[gain[strong] > 0]
    rank = np.full(m, -1, np.int32)
    rank[strong] = np.arange(len(strong))
    columns = rank[places[flat]]
    keep = columns >= 0
    bias, first_w, first_v = start(labels, columns[keep], owner[keep], len(strong), seed)
    del owner, columns, keep

    rng = np.random.default_rng(seed)
    w, v = np.zeros(m, np.float32), rng.normal(0, 0.01, (m, FACTORS)).astype(np.float32)
    w[strong], v[strong] = first_w, first_v
    gb, gw, gv = 1e-2, np.full(m, 1e-2, np.float32), np.full((m, FACTORS), 1e-2, np.float32)
    for _ in range(-(-STEPS * BATCH // n)):
        order = rng.permutation(n)
        for k in range(0, n, BATCH):
            chosen = order[k : k + BATCH]
            size = sizes[chosen]
            filled, begins = size > 0, (np.cumsum(size) - size)[size > 0]

            def by_row(x: np.ndarray, filled=filled, begins=begins) -> np.ndarray:
                out = np.zeros((len(filled), *x.shape[1:]), np.float32)
                if len(begins):
                    out[filled] = np.add.reduceat(x, begins)
                return out

            at = places[flat[np.repeat(starts[chosen] - (np.cumsum(size) - size), size) + np.arange(size.sum())]]
            own = v[at]
            sums = by_row(own)
            z = bias + by_row(w[at]) + 0.5 * ((sums**2).sum(1) - by_row((own**2).sum(1)))
            off = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - labels[chosen]).astype(np.float32)
            db = float(off.sum())
            gb += db**2
            bias -= RATE * db / math.sqrt(gb)
            if not len(at):
                continue
            by_term = np.argsort(at, kind="stable")
            at, row = at[by_term], np.repeat(np.arange(len(chosen)), size)[by_term]
            begins = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
            used, times = at[begins], np.diff(np.append(begins, len(at))).astype(np.float32)
            ow, ov = w[used], v[used]
            slope = np.add.reduceat(off[row], begins)
            dw = slope + SHRINK_USED * times * ow
            dv = np.add.reduceat((off[:, None] * sums)[row], begins) + (SHRINK_USED * times - slope)[:, None] * ov
            gw[used] += dw**2
            gv[used] += dv**2
            w[used], v[used] = ow - pace[used] * dw / np.sqrt(gw[used]), ov - pace[used, None] * dv / np.sqrt(gv[used])
    return Machine(seen, bias, w, v)


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample_rows: int = SAMPLE_ROWS) -> Machine:
    """Fits on rows that are not held out."""
    ship(docs.sparkSession)
    known = labels.filter(~is_held_out(F.col(id_col)) & F.col(id_col).isNotNull() & F.col("toxic").isNotNull())
    known = known.groupBy(F.col(id_col).alias("label_key")).agg(F.max("toxic").cast("int").alias("y"))
    total = known.count()
    slots = 1 << 20
    if total > sample_rows:
        known = known.filter(F.pmod(F.xxhash64("label_key"), F.lit(slots)) < int(slots * sample_rows / total))
    rows = known.join(docs.select(F.col(id_col).alias("doc_key"), F.col(text_col).cast("binary").alias("body")), F.col("label_key") == F.col("doc_key"))

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = [sorted({bucket(t) for t in terms(b or b"")}) for b in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(lists, pa.list_(pa.int32()))], ["k", "y", "at"])

    def fitted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        y, flat, sizes = [], [np.zeros(0, np.int32)], []
        for batch in batches:
            y += batch.column(1).to_pylist()
            flat.append(batch.column(2).flatten().to_numpy())
            sizes += pc.list_value_length(batch.column(2)).to_pylist()
        m = fit_packed(np.array(y, float), np.concatenate(flat).astype(np.int32), np.array(sizes, np.int64))
        yield pa.RecordBatch.from_arrays([pa.array([float(m.bias)]), *(pa.array([x.tobytes()], pa.binary()) for x in m.arrays())], ["bias", "buckets", "weights", "factors"])

    kind = docs.schema[id_col].dataType.simpleString()
    sample = rows.select("label_key", "y", "body").mapInArrow(lean(hashed), f"k {kind}, y int, at array<int>")
    # The sample is bounded, so one task can hold it; in the key's order, so that the model doesn't depend on the partitions.
    found = sample.repartition(1).sortWithinPartitions("k", "y", "at").mapInArrow(lean(fitted), "bias double, buckets binary, weights binary, factors binary").collect()
    return Machine.of(found[0]) if found else fit_packed(np.zeros(0), np.zeros(0, np.int32), np.zeros(0, np.int64))


def score(docs: DataFrame, machine: Machine, id_col: str = "doc_id", text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """id_col (and the columns in keep), held_out, score and predicted for each row."""
    ship(docs.sparkSession)

    columns = list(dict.fromkeys([id_col, *(keep or [])]))
    sent = list(dict.fromkeys([*columns, text_col]))
    text_at = sent.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo: dict[bytes, int] = {}  # term -> position of its bucket, -1: not in the sample
        place = machine.place.table()
        for batch in batches:
            out = []
            for raw in batch.column(text_at).cast(pa.binary()).to_pylist():
                own = terms(raw or b"")
                for t in own.difference(memo):
                    memo[t] = int(place[bucket(t)])
                at = {memo[t] for t in own}
                at.discard(-1)
                out.append(machine.score(sorted(at)))
                if len(memo) > MEMO_ENTRIES:
                    memo.clear()
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(columns)], pa.array(out, pa.float64())], [*batch.schema.names[: len(columns)], "score"])

    rows = docs.select(*(F.col(c).alias(f"c{i}") for i, c in enumerate(sent)))
    schema = ", ".join(f"c{i} {docs.schema[c].dataType.simpleString()}" for i, c in enumerate(columns)) + ", score double"
    out = rows.mapInArrow(lean(run), schema)
    return out.select(*(F.col(f"c{i}").alias(c) for i, c in enumerate(columns)), is_held_out(F.col("c0")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return score(docs, train(docs, table(spark, sf_dir, "labels")))
