"""Token counts without ids: pieces are counted once per distinct pre-token and summed by frequency.

A block of documents (a few MB) is cut into pre-tokens; the block's distinct pre-tokens not yet
known are counted together, and the block's per-document frequencies are joined to those counts.
Known counts stay in a bounded memo of the worker, so a frequent pre-token is counted once there.

Why the join is inside the block: a corpus-wide join has one row per document and distinct word
(about two thirds of all words), which shuffles more than the corpus itself.

Defined results: null and empty texts have 0 bytes and 0 tokens; repeated rows are counted each
by itself; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from operator import mul

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ship, table
from .wordbpe import vocabulary_path, word_vocabulary

BLOCK_CHARS = 4_000_000
MEMO_ENTRIES = 400_000
_memo: dict[str, int] = {}


def _lengths(vocabulary, words: list[str]) -> list[int]:
    return [len(e.ids) for e in vocabulary.merges_only.encode_batch_fast([vocabulary.written(w) for w in words], add_special_tokens=False)]


def _block_counts(vocabulary, texts: list[str]) -> list[int]:
    special = vocabulary.special
    frequencies, extra = [], []
    for text in texts:
        parts = vocabulary.parts(text)
        seen: Counter[str] = Counter()
        for p in parts[::2]:
            seen.update(vocabulary.pretokens(p))
        frequencies.append(seen)
        extra.append(sum(p in special for p in parts[1::2]))
    new = list({w for f in frequencies for w in f if w not in _memo})
    _memo.update(zip(new, _lengths(vocabulary, new), strict=True))
    found = _memo.__getitem__
    out = [n + sum(map(mul, f.values(), map(found, f))) for f, n in zip(frequencies, extra, strict=True)]
    if len(_memo) > MEMO_ENTRIES:
        _memo.clear()
    return out


def token_counts(docs: DataFrame, path: str | None = None, id_col: str = "doc_id", text_col: str = "text", limit: int = 2048) -> DataFrame:
    """id_col, n_bytes, n_tokens, over_limit for each row, by a word BPE vocabulary file (tokenizers JSON)."""
    ship(docs.sparkSession)
    path = path or vocabulary_path("word_bpe_49k.json")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = word_vocabulary(path)
        for batch in batches:
            texts = [t or "" for t in batch.column(1).to_pylist()]
            n_tokens, block, size = [], [], 0
            for t in texts:
                block.append(t)
                size += len(t)
                if size >= BLOCK_CHARS:
                    n_tokens += _block_counts(vocabulary, block)
                    block, size = [], 0
            n_tokens += _block_counts(vocabulary, block)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(n_tokens, pa.int64())], ["key", "n_bytes", "n_tokens"])

    kind = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(F.col(id_col).alias("key"), F.col(text_col).alias("body"), F.coalesce(F.octet_length(text_col), F.lit(0)).cast("long").alias("n_bytes"))
    out = rows.mapInArrow(count, f"key {kind}, n_bytes long, n_tokens long")
    return out.select(F.col("key").alias(id_col), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(table(spark, sf_dir, "documents"))
