"""BPE encoding and decoding with our own merge loop.

Encoding keeps the symbols of a pre-token in a doubly linked list and the ranks of mergeable
neighbours in a priority queue; entries whose pair has changed since are skipped. Decoding looks
each id up and joins the vocabulary strings (by one blank: the file names no decoder).

Defined results: null texts are empty; empty texts give no ids and the hash of the empty string;
strings of special tokens inside a text give their ids; repeated rows are encoded each by itself;
an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache
from heapq import heapify, heappop, heappush

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lean, ship, table
from .wordbpe import vocabulary_path, word_vocabulary

MEMO_ENTRIES = 300_000


def merge_symbols(ids: list[int], ranks: dict[int, tuple[int, int]]) -> list[int]:
    """Applies the lowest-ranked merge again and again. ranks: left << 20 | right -> (rank, merged id)."""
    n = len(ids)
    if n < 2:
        return ids
    symbol, after, before = list(ids), list(range(1, n + 1)), list(range(-1, n - 1))
    find = ranks.get
    queue = []
    left = symbol[0]
    for i in range(n - 1):
        right = symbol[i + 1]
        if hit := find(left << 20 | right):
            queue.append((hit[0], i, hit[1]))
        left = right
    heapify(queue)
    while queue:
        rank, i, merged = heappop(queue)
        j = after[i]
        if symbol[i] < 0 or j >= n or (hit := find(symbol[i] << 20 | symbol[j])) is None or hit[0] != rank:
            continue  # stale: a neighbour was merged meanwhile
        symbol[i], symbol[j] = merged, -1
        after[i] = k = after[j]
        if k < n:
            before[k] = i
            if hit := find(merged << 20 | symbol[k]):
                heappush(queue, (hit[0], i, hit[1]))
        if (h := before[i]) >= 0 and (hit := find(symbol[h] << 20 | merged)):
            heappush(queue, (hit[0], h, hit[1]))
    return [s for s in symbol if s >= 0]


class Codec:
    """Encodes and decodes texts; a bounded memo keeps the ids and strings of whole pre-tokens."""

    def __init__(self, path: str):
        self.words = word_vocabulary(path)
        model = self.words.spec["model"]
        self.id_of: dict[str, int] = model["vocab"]
        self.suffix: str = model.get("end_of_word_suffix") or ""
        self.string_of = {i: s for s, i in self.id_of.items()} | {i: s for s, i in self.words.special.items()}
        self.ranks: dict[int, tuple[int, int]] = {}
        for rank, pair in enumerate(model["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.ranks[self.id_of[a] << 20 | self.id_of[b]] = (rank, self.id_of[a + b])
        self.id_text: dict[str, str] = {}
        self.word_text: dict[str, str] = {}

    def encode_word(self, pretoken: str) -> list[int]:
        written = self.words.written(pretoken)
        symbols = [*written[:-1], written[-1] + self.suffix]
        return merge_symbols([self.id_of[s] for s in symbols], self.ranks)

    def encode(self, text: str) -> list[int]:
        out: list[int] = []
        for k, part in enumerate(self.words.parts(text)):
            if k % 2:
                out.append(self.words.special[part])
            else:
                for w in self.words.pretokens(part):
                    out += self.encode_word(w)
        return out

    def decode(self, ids: list[int]) -> str:
        return " ".join(map(self.string_of.__getitem__, ids))

    def as_texts(self, text: str) -> tuple[str, str]:
        """The decimal ids and the decoded strings of a text, each joined by blanks."""
        pieces: list[str] = []
        special = self.words.special
        for k, part in enumerate(self.words.parts(text)):
            pieces += [part] if k % 2 else self.words.pretokens(part)
        ids, strings = self.id_text, self.word_text
        for w in set(pieces).difference(ids):
            got = [special[w]] if w in special else self.encode_word(w)
            ids[w] = " ".join(map(str, got))
            strings[w] = self.decode(got)
        out = " ".join(map(ids.__getitem__, pieces)), " ".join(map(strings.__getitem__, pieces))
        if len(ids) > MEMO_ENTRIES:
            ids.clear()
            strings.clear()
        return out


@lru_cache(maxsize=2)
def codec(path: str) -> Codec:
    return Codec(path)


def encode_decode(docs: DataFrame, path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col, n_tokens, ids_sha256, decoded_sha256 for each row."""
    ship(docs.sparkSession)
    path = path or vocabulary_path("word_bpe_49k.json")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for batch in batches:
            n, a, b = [], [], []
            for t in batch.column(1).to_pylist():
                ids, strings = c.as_texts(t or "")
                n.append(ids.count(" ") + 1 if ids else 0)
                a.append(hashlib.sha256(ids.encode()).hexdigest())
                b.append(hashlib.sha256(strings.encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())], ["key", "n_tokens", "ids_sha256", "decoded_sha256"])

    kind = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(F.col(id_col).alias("key"), F.col(text_col).alias("body"))
    return rows.mapInArrow(lean(run), f"key {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string").withColumnRenamed("key", id_col)


def token_ids(docs: DataFrame, path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col and ids (array of int) for each row: the encoder's real output."""
    ship(docs.sparkSession)
    path = path or vocabulary_path("word_bpe_49k.json")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([c.encode(t or "") for t in batch.column(1).to_pylist()], pa.list_(pa.int32()))], ["key", "ids"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("key"), F.col(text_col).alias("body")).mapInArrow(lean(run), f"key {kind}, ids array<int>").withColumnRenamed("key", id_col)


def op5_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_decode(table(spark, sf_dir, "documents"))
