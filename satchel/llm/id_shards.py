"""Token ids in sorted-string-table shards, and lookups in them.

A shard holds (key, ids) entries in key order. Entries lie in blocks of about BLOCK_BYTES; inside
a block a key stores only what differs from the key before it. After the blocks come a sparse
index (first key, place, entries and tokens before each block), a Bloom filter of all keys and a
footer of fixed size. A lookup asks the filter, searches the index by halving and reads one block.

Keys are eight bytes that sort as signed integers, behind a byte that puts null first. Ids take two
bytes each where the vocabulary has at most 65,536 entries, else four.

Defined results: null texts are empty, so only the end id is written; rows with equal keys all stay,
ordered by a hash of the text; a null key comes first; an empty table gives no rows; other columns
are not read. Files are written once per task attempt under names of their own, so a task that runs
again never touches what another wrote, and only the attempt that Spark counts is listed.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from bisect import bisect_right
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import scratch_dir, ship, shuffle_width, table
from .wordbpe import PLAIN, byte_symbols, vocabulary_path

BLOCK_BYTES = 64 * 1024
BITS_PER_KEY, HASHES = 10, 7
MAGIC = b"SSTIDS01"
FOOTER = struct.Struct("<QQQQQQBB6x8s")  # index at, index bytes, filter at, filter bytes, entries, tokens, id width, hashes, magic


class ByteTokenizer:
    """Byte-level BPE of a tokenizers JSON file. Plain Latin texts use its ranks directly, others the library."""

    def __init__(self, path: str):
        import json

        import tiktoken
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        byte_of = {s: b for b, s in enumerate(byte_symbols())}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        ranks = {bytes(map(byte_of.__getitem__, s)): i for s, i in spec["model"]["vocab"].items() if s not in self.special}
        import public_tokenizers

        self.quick = tiktoken.Encoding("shards", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.size = max(max(ranks.values()), *self.special.values()) + 1

    def encode(self, text: str) -> list[int]:
        if "<|" not in text and PLAIN.fullmatch(text):
            return self.quick.encode_ordinary(text)
        return self.library.encode(text, add_special_tokens=False).ids


@lru_cache(maxsize=2)
def byte_tokenizer(path: str) -> ByteTokenizer:
    return ByteTokenizer(path)


def key_bytes(key: int | None) -> bytes:
    return b"\0" if key is None else b"\1" + struct.pack(">Q", key + (1 << 63))


def key_value(raw: bytes) -> int | None:
    return None if raw == b"\0" else struct.unpack(">Q", raw[1:])[0] - (1 << 63)


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _read_varint(raw: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        b = raw[at]
        at += 1
        n |= (b & 127) << shift
        if b < 128:
            return n, at
        shift += 7


def _probes(key: bytes, bits: int, hashes: int) -> list[int]:
    import hashlib

    a, b = struct.unpack("<QQ", hashlib.blake2b(key, digest_size=16).digest())
    return [(a + i * (b | 1)) % bits for i in range(hashes)]


class ShardWriter:
    """Appends entries in key order to an open binary file."""

    def __init__(self, out, width: int):
        self.out, self.width, self.kind = out, width, "<u2" if width == 2 else "<u4"
        self.at = self.entries = self.tokens = self.filled = 0
        self.parts: list[bytes] = []
        self.index: list[tuple[bytes, int, int, int]] = []
        self.last = self.first = None
        self.before = (0, 0)
        self.keys: list[bytes] = []

    def add(self, key: int | None, ids: list[int]) -> None:
        raw, value = key_bytes(key), np.asarray(ids, self.kind).tobytes()
        if self.last is None:
            self.first, self.before, shared = raw, (self.entries, self.tokens), 0
        else:
            shared = next((i for i, (x, y) in enumerate(zip(raw, self.last)) if x != y), min(len(raw), len(self.last)))
        head = _varint(shared) + _varint(len(raw) - shared) + _varint(len(value)) + raw[shared:]
        self.parts += [head, value]
        self.filled += len(head) + len(value)
        self.last = raw
        self.keys.append(raw)
        self.entries += 1
        self.tokens += len(ids)
        if self.filled >= BLOCK_BYTES:
            self.end_block()

    def end_block(self) -> None:
        if self.parts:
            body = b"".join(self.parts)
            block = body + struct.pack("<I", zlib.crc32(body))
            self.out.write(block)
            self.index.append((self.first, self.at, len(block), *self.before))
            self.at += len(block)
        self.parts, self.filled, self.last = [], 0, None

    def close(self) -> None:
        self.end_block()
        index = b"".join(_varint(len(k)) + k + struct.pack("<QQQQ", *rest) for k, *rest in self.index)
        bits = max(64, len(self.keys) * BITS_PER_KEY)
        bloom = bytearray(-(-bits // 8))
        for k in self.keys:
            for p in _probes(k, bits, HASHES):
                bloom[p >> 3] |= 1 << (p & 7)
        self.out.write(index)
        self.out.write(struct.pack("<Q", bits) + bytes(bloom))
        self.out.write(FOOTER.pack(self.at, len(index), self.at + len(index), 8 + len(bloom), self.entries, self.tokens, self.width, HASHES, MAGIC))


class Shard:
    """Reads one shard from a random-access file."""

    def __init__(self, file):
        self.file = file
        size = file.size()
        (at, n, self.bloom_at, self.bloom_n, self.entries, self.tokens, self.width, self.hashes, magic) = FOOTER.unpack(self._read(size - FOOTER.size, FOOTER.size))
        if magic != MAGIC:
            raise ValueError("not a shard of token ids")
        raw, i, self.index = self._read(at, n), 0, []
        while i < n:
            k, i = _read_varint(raw, i)
            self.index.append((raw[i : i + k], *struct.unpack_from("<QQQQ", raw, i + k)))
            i += k + 32
        self.bloom = None

    def _read(self, at: int, n: int) -> bytes:
        self.file.seek(at)
        return self.file.read(n)

    def block(self, i: int) -> Iterator[tuple[bytes, np.ndarray]]:
        raw = self._read(self.index[i][1], self.index[i][2])
        if zlib.crc32(raw[:-4]) != struct.unpack("<I", raw[-4:])[0]:
            raise ValueError("a damaged block")
        at, end, key = 0, len(raw) - 4, b""
        while at < end:
            shared, at = _read_varint(raw, at)
            own, at = _read_varint(raw, at)
            n, at = _read_varint(raw, at)
            key = key[:shared] + raw[at : at + own]
            at += own
            yield key, np.frombuffer(raw, "<u2" if self.width == 2 else "<u4", n // self.width, at)
            at += n

    def scan(self) -> Iterator[tuple[int | None, np.ndarray]]:
        for i in range(len(self.index)):
            for key, ids in self.block(i):
                yield key_value(key), ids

    def may_hold(self, key: bytes) -> bool:
        if self.bloom is None:
            self.bloom = self._read(self.bloom_at, self.bloom_n)
        bits = struct.unpack_from("<Q", self.bloom)[0]
        return all(self.bloom[8 + (p >> 3)] >> (p & 7) & 1 for p in _probes(key, bits, self.hashes))

    def get(self, key: int | None) -> list[np.ndarray]:
        """The ids of every entry with this key; usually one, none if absent."""
        raw = key_bytes(key)
        if not self.may_hold(raw):
            return []
        firsts = [x[0] for x in self.index]
        i, out = bisect_right(firsts, raw) - 1, []
        while i > 0 and firsts[i] == raw:  # equal keys may have begun in the block before
            i -= 1
        for j in range(max(i, 0), len(firsts)):
            if firsts[j] > raw:
                break
            out += [ids for k, ids in self.block(j) if k == raw]
        return out


def open_shard(uri: str) -> Shard:
    from pyarrow import fs

    where, path = fs.FileSystem.from_uri(uri)
    return Shard(where.open_input_file(path))


def write_shards(docs: DataFrame, folder: str, path: str | None = None, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Writes shards in ascending key order into folder; returns their list: shard, uri, n_docs, n_tokens, start.

    The list has one row per shard, so the driver holds as many rows as there are shuffle partitions.
    """
    spark = docs.sparkSession
    ship(spark)
    path = path or vocabulary_path("byte_bpe_50k.json")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        tokenizer, context, out = byte_tokenizer(path), TaskContext.get(), None
        where, base = fs.FileSystem.from_uri(folder)
        name = f"shard-{context.partitionId():06d}-{context.taskAttemptId()}-{uuid.uuid4().hex[:8]}.sst"
        for batch in batches:
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if out is None:
                    where.create_dir(base, recursive=True)
                    out = where.open_output_stream(f"{base}/{name}")
                    writer = ShardWriter(out, 2 if max(tokenizer.size, end_id + 1) <= 1 << 16 else 4)
                writer.add(key, [*tokenizer.encode(text or ""), end_id])
        if out is not None:
            writer.close()
            out.close()
            yield pa.RecordBatch.from_pydict({"shard": [context.partitionId()], "uri": [f"{folder}/{name}"], "n_docs": [writer.entries], "n_tokens": [writer.tokens]}, schema=pa.schema([("shard", pa.int32()), ("uri", pa.string()), ("n_docs", pa.int64()), ("n_tokens", pa.int64())]))

    rows = docs.select(F.col(id_col).cast("long").alias("key"), F.col(text_col).alias("body"))
    order = (F.col("key").asc_nulls_first(), F.col("tie"))  # the range sample sends these to the driver, so no text is among them
    ordered = rows.withColumn("tie", F.xxhash64("body")).repartitionByRange(shuffle_width(spark), *order).sortWithinPartitions(*order)
    written = sorted(ordered.mapInArrow(write, "shard int, uri string, n_docs long, n_tokens long").collect())
    start, listed = 0, []
    for shard, uri, n_docs, n_tokens in written:
        listed.append((shard, uri, n_docs, n_tokens, start))
        start += n_tokens
    return spark.createDataFrame(listed, "shard int, uri string, n_docs long, n_tokens long, start long")


def read_shards(shards: DataFrame, id_col: str = "doc_id", with_ids: bool = False) -> DataFrame:
    """Per entry: id_col, start, n_tokens, ids_crc32 (of the ids as little-endian 32-bit integers), and the ids if asked for."""
    ship(shards.sparkSession)
    fields = [("key", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())] + [("ids", pa.list_(pa.int32()))] * with_ids
    schema = pa.schema(fields)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for uri, start in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                shard = open_shard(uri)
                for i in range(len(shard.index)):
                    rows = []
                    for key, ids in shard.block(i):
                        rows.append((key_value(key), start, len(ids), zlib.crc32(ids.astype("<u4").tobytes()), *[ids.astype("i4")] * with_ids))
                        start += len(ids)
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

    spread = shards.select("uri", "start").repartition(shuffle_width(shards.sparkSession), "uri")
    return spread.mapInArrow(read, "key long, start long, n_tokens long, ids_crc32 long" + ", ids array<int>" * with_ids).withColumnRenamed("key", id_col)


def lookup(shards: DataFrame, keys: list[int]) -> dict[int, list[int]]:
    """Ids of a few keys, by filter, index and one block per shard; for tests and ad hoc reads."""
    found: dict[int, list[int]] = {}
    for row in shards.select("uri").toLocalIterator():
        shard = open_shard(row.uri)
        found |= {k: hits[0].tolist() for k in keys if (hits := shard.get(k))}
    return found


def op10_id_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_shards(write_shards(table(spark, sf_dir, "documents"), scratch_dir(spark, "id-shards")))
