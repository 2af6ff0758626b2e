"""Documents whose word-shingle sets have a Jaccard similarity of at least T, and their connected groups.

Sets of different texts can only reach T if their symmetric difference is small, so the universe of shingles
is hashed into segments: as a pair differs in few tokens, some segment must hold the same tokens in both sets
(or differ in one, where segments are allocated a deletion). Per band of set sizes the allocation with the
lower estimated cost is used: many small segments that must be equal, or few larger ones that may miss one
token and are also indexed without each of their tokens. Shingles that many documents hold (passages, licence
lines) have segments of their own, which come last. A set indexes its first segments until enough non-empty
ones are there for the pigeonhole to hold, so popular segments serve only sets that have little else; sets that
run out of segments meet in a list of their own.

Steps: (1) sets get a 128-bit fingerprint; equal sets are one from here on. (2) Signatures go, packed, to
hash buckets; sets that share one form a list, and equal lists of all buckets come to one place. (3) In every list sizes and parity sketches rule out what can't be
similar; the rest is held against the smallest set (by fingerprint), or else against the nearest few, exactly,
over whole texts. (4) Then every pair of a list that isn't ruled out and doesn't hang together through links
found so far is compared, so a pair is skipped only where it can't change a component. (5) Links give components.
(6) Links exist only inside a component, so there every pair of neighbouring size is compared, block by block inside
tasks, and each document's links are counted, equal texts through the size of their class. Pairs are never sent.

Words are runs between blanks, A-Z lower-cased, and hashed eight bytes at a time, all words of a text at once; texts shorter than a shingle are one shingle. Fingerprints
of shingles have 64 bits when sets are counted and indexed; pairs are verified on the words themselves.

Defined results: null texts and texts without words have 0 shingles and links and are their own component; rows with a
null key are counted, and their component and links are null (nor are they links of others); rows with equal keys are joined with whatever any of them
links to; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import hashlib
import struct
from collections import OrderedDict
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lean, materialize, ship, shuffle_width, table

WORDS, T_NUM, T_DEN = 5, 4, 5
FLUSH_ENTRIES, BUCKET_ENTRIES, FEW_IDS, FOREST_EDGES, TRIES = 750_000, 1_500_000, 500_000, 500_000, 2
#: Of a block of sets that are compared with each other; a pair of blocks is one task's work at a time.
BLOCK_TOKENS, BLOCK_SETS = 65_536, 256
#: Bytes of a word that are hashed 8 at a time; blanks and lower case for that, and masks of the first 0 to 8 bytes.
LONG_WORD = 64
FOLD = bytes(32 if b == 32 or 9 <= b <= 13 else b + 32 if 65 <= b <= 90 else b for b in range(256))
HEADS = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)
#: Places where lists are looked at (the same number up to 2,000 buckets), and how many of them lists with the same smallest set are dealt to.
HOMES, SPREAD = 256, 2
#: A shingle is popular if a block of about BLOCK_HASHES holds it in OFTEN sets; the POPULAR most frequent ones count.
#: This allocates segments and changes cost only.
BLOCK_HASHES, OFTEN, POPULAR = 2_000_000, 5, 100_000
U = np.uint64
C1, C2, C3 = U(0x9E3779B97F4A7C15), U(0xBF58476D1CE4E5B9), U(0x94D049BB133111EB)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (splitmix)."""
    y = x >> U(30)
    y ^= x
    y *= C2
    y ^= y >> U(27)
    y *= C3
    y ^= y >> U(31)
    return y


def distinct(x: np.ndarray) -> np.ndarray:
    """Sorted distinct values."""
    x = np.sort(x)
    return x[np.concatenate(([True], x[1:] != x[:-1]))] if len(x) else x


def words_of(raw: bytes) -> list[bytes]:
    return raw.lower().split()


def word_hashes(raw: bytes) -> np.ndarray:
    """A 64-bit hash of each word, for all words at once: 8 bytes by 8 bytes, words of more than LONG_WORD by blake2b."""
    text = np.frombuffer(b" " + raw.translate(FOLD) + b" " * 8, np.uint8)
    filled = text != 32
    edges = np.flatnonzero(filled[1:] != filled[:-1]) + 1
    starts, ends = edges[::2], edges[1::2]
    lengths = ends - starts
    eights = np.ndarray((len(text) - 7,), "<u8", text, strides=(1,))  # the 8 bytes from each place
    out = mix((eights[starts] & HEADS[np.minimum(lengths, 8)]) + lengths.astype(U) * C1)
    which, at = np.flatnonzero(lengths > 8), 8
    while len(which) and at < LONG_WORD:
        out[which] = mix(out[which] * C1 + (eights[starts[which] + at] & HEADS[np.minimum(lengths[which] - at, 8)]))
        at += 8
        which = which[lengths[which] > at]
    for i in which:
        out[i] = int.from_bytes(hashlib.blake2b(text[starts[i] : ends[i]], digest_size=8).digest(), "little")
    return out


def shingle_hashes(raw: bytes) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's shingles."""
    h = word_hashes(raw)
    n = len(h)
    if not n:
        return h
    if n < WORDS:
        out = np.array([n], U)
        for i in range(n):
            out = mix(out * C1 + h[i : i + 1])
        return out
    out = h[: n - WORDS + 1].copy()
    for i in range(1, WORDS):
        out = mix(out * C1 + h[i : n - WORDS + 1 + i])
    return distinct(out)


def shingle_set(raw: bytes) -> set:
    """The set itself, of word tuples."""
    w = words_of(raw)
    if len(w) < WORDS:
        return {tuple(w)} if w else set()
    return set(zip(*(w[i:] for i in range(WORDS)), strict=False))


def similar(a: set, b: set) -> bool:
    """|a & b| / |a | b| >= T, without forming the union."""
    if not a or not b or T_DEN * min(len(a), len(b)) < T_NUM * max(len(a), len(b)):
        return False
    both = len(a & b)
    return T_DEN * both >= T_NUM * (len(a) + len(b) - both)


def most_apart(a: int, b: int) -> int:
    """The largest symmetric difference of similar sets of these sizes."""
    return (T_DEN - T_NUM) * (a + b) // (T_DEN + T_NUM)


@lru_cache(maxsize=1)
def band_edges() -> list[int]:
    """Largest size of each band; a set's partners lie in its own band and the one above or below."""
    edges, low = [0], 1
    while edges[-1] < 1 << 40:
        edges.append(max(low, low * T_DEN // T_NUM))
        low = edges[-1] + 1
    return edges


@lru_cache(maxsize=4096)
def allocation(band: int) -> tuple[int, bool]:
    """Segments of a band and whether they may miss one token, by estimated cost: signatures plus collisions of thin segments.

    Segments that must be equal count one each, those that may miss a token two; both get spare ones for empties.
    """
    size = band_edges()[band]
    apart = most_apart(size, size)
    plans = []
    for deletion in (False, True):
        need = apart // 2 + 1 if deletion else apart + 1
        m = need if need == 1 else need + 1 + int(need * (0.15 if not deletion else 0.05))
        load = 0.8 * size / m
        thin = np.exp(-load) * (1 + load)
        signatures = m + size * deletion
        plans.append((signatures * (1 + 2 * thin) + 30 * (m * np.exp(-load) > m - need), deletion, m))
    _, deletion, m = min(plans)
    return m, deletion


def signatures(h: np.ndarray, popular: np.ndarray | None = None) -> np.ndarray:
    """Of a set given by its hashes: what it is indexed under, in its own band and where larger partners are.

    popular: sorted hashes of popular shingles, the same for all sets.
    """
    s = len(h)
    late = None
    if popular is not None and len(popular):
        late = popular[np.minimum(np.searchsorted(popular, h), len(popular) - 1)] == h
    own = int(np.searchsorted(band_edges(), s))
    out = []
    for band in (own, own + 1):
        top, low = band_edges()[band], band_edges()[band - 1] + 1
        if low * T_NUM > s * T_DEN:
            continue
        apart = most_apart(s, min(top, s * T_DEN // T_NUM))
        if not apart:
            continue  # only equal sets
        m, deletion = allocation(band)
        salt = U(band * int(C1) & (1 << 64) - 1)
        token = mix(h ^ salt)
        segment = ((token >> U(32)) * U(m)) >> U(32)
        if late is not None:
            segment = segment + late.astype(U) * U(m)
        order = np.argsort(segment.astype(np.uint16) if 2 * m < 1 << 16 else segment, kind="stable")  # 16 bits are sorted by digits
        segment, token = segment[order], mix(token[order] + C3)
        starts = np.flatnonzero(np.concatenate(([True], segment[1:] != segment[:-1])))
        sums, names = np.add.reduceat(token, starts), segment[starts]
        lengths = np.diff(np.append(starts, s))
        if deletion:
            good = np.cumsum(lengths >= 2)
            need = apart // 2 + 1
            upto = int(np.searchsorted(good, need)) + 1
            enough = good[-1] >= need
            n = min(upto, len(starts))
            end = starts[n] if n < len(starts) else s
            which = np.repeat(np.arange(n), lengths[:n])
            wide = lengths[which] >= 2
            less = sums[which] - token[:end]
            found = np.concatenate((mix(sums[:n] + names[:n] * C2 + salt), mix(less + names[which] * C2 + salt)[wide]))
        else:
            enough = len(starts) > apart
            found = mix(sums[: apart + 1] + names[: apart + 1] * C2 + salt)
        out.append(found)
        if not enough:
            out.append(mix(np.array([salt ^ C3], U)))
    return distinct(np.concatenate(out)) if out else np.zeros(0, U)


def fingerprint(h: np.ndarray) -> tuple[int, int]:
    return struct.unpack("<qq", hashlib.blake2b(h.tobytes(), digest_size=16).digest())


def shingle_sets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """key, n_shingles, the fingerprint (hi, lo) and the sketch of each row's set, null for an empty one.

    Further rows, with often and times and nothing else, have each block's popular shingles.
    """

    schema = pa.schema([("key", pa.int64()), ("n_shingles", pa.int64()), ("hi", pa.int64()), ("lo", pa.int64()), ("sketch", pa.binary()), ("often", pa.list_(pa.int64())), ("times", pa.list_(pa.int64()))])

    def counted(block: dict[tuple, np.ndarray]) -> pa.RecordBatch:
        """A row of shingles that many sets of the block hold."""
        found, times = np.unique(np.concatenate(list(block.values())), return_counts=True) if block else (np.zeros(0, U), np.zeros(0, int))
        many = times >= OFTEN
        return pa.RecordBatch.from_pylist([{"often": found[many].view(np.int64).tolist(), "times": times[many].tolist()}], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block: dict[tuple, np.ndarray] = {}
        held = 0
        for batch in batches:
            rows = []
            for key, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                h = shingle_hashes(raw or b"")
                a, b = mark = fingerprint(h) if len(h) else (None, None)
                rows.append((key, len(h), a, b, parity_sketch(h).tobytes() if len(h) else None))
                if len(h) and mark not in block:
                    block[mark] = h
                    held += len(h)
                    if held >= BLOCK_HASHES:
                        yield counted(block)
                        block, held = {}, 0
            columns = list(zip(*rows, strict=True)) if rows else [()] * 5
            columns += [[None] * len(rows)] * 2
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)
        yield counted(block)

    rows = docs.select(F.col(id_col).cast("long").alias("key"), F.col(text_col).cast("binary").alias("body"))
    return rows.mapInArrow(lean(run), "key long, n_shingles long, hi long, lo long, sketch binary, often array<bigint>, times array<bigint>")


def popular_shingles(sets: DataFrame) -> np.ndarray:
    """Sorted hashes of at most POPULAR shingles, by the blocks' counts over all documents."""
    pairs = sets.filter("often is not null").select(F.explode(F.arrays_zip("often", "times")).alias("x")).select("x.often", "x.times")
    best = pairs.groupBy("often").agg(F.sum("times").alias("times")).orderBy(F.col("times").desc(), "often").limit(POPULAR)
    return np.sort(best.select("often").toArrow()["often"].to_numpy().astype(np.int64).view(U))


def signature_buckets(docs: DataFrame, buckets: int, popular: np.ndarray, id_col: str, text_col: str) -> DataFrame:
    """Packed (signature, set) pairs by bucket; a task sends each pair once per flush."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sigs: list[np.ndarray] = []
        sets: list[np.ndarray] = []
        held, seen = 0, set()

        def flush() -> Iterator[pa.RecordBatch]:
            nonlocal held
            if held:
                s, f = np.concatenate(sigs), np.concatenate(sets)
                order = np.argsort(s)
                s, f = s[order], f[order]
                bucket = ((s >> U(32)) * U(buckets)) >> U(32)
                cuts = np.flatnonzero(np.concatenate(([True], bucket[1:] != bucket[:-1])))
                ends = np.append(cuts[1:], len(s))
                for at in range(0, len(cuts), 64):
                    part = list(zip(cuts[at : at + 64], ends[at : at + 64], strict=True))
                    yield pa.RecordBatch.from_arrays([pa.array([int(bucket[a]) for a, _ in part], pa.int64()), pa.array([s[a:b].tobytes() for a, b in part], pa.binary()), pa.array([f[a:b].tobytes() for a, b in part], pa.binary())], ["bucket", "sigs", "sets"])
            sigs.clear()
            sets.clear()
            seen.clear()
            held = 0

        for batch in batches:
            for raw in batch.column(0).to_pylist():
                h = shingle_hashes(raw or b"")
                if not len(h):
                    continue
                lo = fingerprint(h)[1]
                if lo in seen:
                    continue
                seen.add(lo)
                found = signatures(h, popular)
                sigs.append(found)
                sets.append(np.full(len(found), lo, np.int64))
                held += len(found)
                if held >= FLUSH_ENTRIES:
                    yield from flush()
        yield from flush()

    rows = docs.filter(F.col(id_col).isNotNull()).select(F.col(text_col).cast("binary").alias("body"))
    return rows.mapInArrow(lean(run), "bucket long, sigs binary, sets binary")


def lists_of(sig: np.ndarray, lo: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct lists (of at least two sets) of equal signatures: their lengths, and their sets one after another."""
    order = np.argsort(sig)
    sorted_ = sig[order]
    same = sorted_[1:] == sorted_[:-1]
    order = order[np.concatenate((same, [False])) | np.concatenate(([False], same))]  # the others are alone
    del sorted_, same
    if not len(order):
        return np.zeros(0, np.int64), lo[:0]
    sig, lo = sig[order], lo[order]
    order = np.lexsort((lo, sig))
    sig, lo = sig[order], lo[order]
    fresh = np.concatenate(([True], (sig[1:] != sig[:-1]) | (lo[1:] != lo[:-1])))
    sig, lo = sig[fresh], lo[fresh]
    starts = np.flatnonzero(np.concatenate(([True], sig[1:] != sig[:-1])))
    lengths = np.diff(np.append(starts, len(sig)))
    many = lengths > 1
    starts, lengths = starts[many], lengths[many]
    if not len(starts):
        return lengths, lo[:0]
    keep = np.repeat(starts - np.concatenate(([0], np.cumsum(lengths)[:-1])), lengths) + np.arange(lengths.sum())
    lo = lo[keep]
    return distinct_lists(lengths, lo)


def contents(lengths: np.ndarray, lo: np.ndarray) -> np.ndarray:
    """A hash of each list's sets."""
    return np.add.reduceat(mix(lo.astype(U)), np.cumsum(lengths) - lengths) * C1 + lengths.astype(U)


def gathered(lengths: np.ndarray, lo: np.ndarray, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Some of the lists, in the order asked for."""
    starts, some = (np.cumsum(lengths) - lengths)[which], lengths[which]
    return some, lo[np.repeat(starts - (np.cumsum(some) - some), some) + np.arange(some.sum())]


def distinct_lists(lengths: np.ndarray, lo: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each list once: many segments give the same."""
    return gathered(lengths, lo, np.sort(np.unique(contents(lengths, lo), return_index=True)[1]))


def home_of(lengths: np.ndarray, lo: np.ndarray, homes: int) -> np.ndarray:
    """Where a list is looked at: equal lists at one place, those with the same smallest set at SPREAD places."""
    head = mix(lo[np.cumsum(lengths) - lengths].astype(U) + C2)
    return ((head >> U(32)) + (mix(contents(lengths, lo)) >> U(32)) % U(SPREAD)) % U(homes)


def shared_lists(packed: DataFrame, partitions: int, homes: int) -> DataFrame:
    """part, lens, sets: the distinct lists of all buckets, packed by their home. A task works through its buckets, and then its homes, one by one.

    Sets that are alike share most of their segments, so each bucket has their list. It is kept once, so how many places a set
    comes to depends on what it is like, not on the number of buckets.
    """

    def bucketed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, sigs, sets = None, [], []

        def lists() -> Iterator[pa.RecordBatch]:
            if not sigs:
                return
            lengths, lo = lists_of(np.concatenate(sigs), np.concatenate(sets))
            sigs.clear()
            sets.clear()
            if len(lengths):
                home = home_of(lengths, lo, homes)
                order = np.argsort(home, kind="stable")
                home, (lengths, lo) = home[order], gathered(lengths, lo, order)
                cuts = np.flatnonzero(np.concatenate(([True], home[1:] != home[:-1])))
                ends, upto = np.append(cuts[1:], len(home)), np.concatenate(([0], np.cumsum(lengths)))
                yield packed_lists([(int(home[a]), lengths[a:b], lo[upto[a] : upto[b]]) for a, b in zip(cuts, ends, strict=True)])

        for batch in batches:
            for bucket, s, o in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2), strict=True):
                if bucket != now:
                    yield from lists()
                    now = bucket
                sigs.append(np.frombuffer(s.as_buffer(), U))
                sets.append(np.frombuffer(o.as_buffer(), np.int64))
        yield from lists()

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, lens, sets = None, [], []

        def lists() -> Iterator[pa.RecordBatch]:
            if lens:
                out = distinct_lists(np.concatenate(lens), np.concatenate(sets))
                lens.clear()
                sets.clear()
                yield packed_lists([(part, *out)])

        for batch in batches:
            for home, n, o in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2), strict=True):
                if home != part:
                    yield from lists()
                    part = home
                lens.append(np.frombuffer(n.as_buffer(), np.int64))
                sets.append(np.frombuffer(o.as_buffer(), np.int64))
        yield from lists()

    found = packed.repartition(partitions, "bucket").sortWithinPartitions("bucket").mapInArrow(lean(bucketed), "part long, lens binary, sets binary")
    return found.repartition(partitions, "part").sortWithinPartitions("part").mapInArrow(lean(merged), "part long, lens binary, sets binary")


def packed_lists(rows: list[tuple[int, np.ndarray, np.ndarray]]) -> pa.RecordBatch:
    columns = list(zip(*((part, lengths.astype(np.int64).tobytes(), lo.astype(np.int64).tobytes()) for part, lengths, lo in rows), strict=True))
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.binary(), pa.binary()), strict=True)], ["part", "lens", "sets"])


def parity_sketch(h: np.ndarray) -> np.ndarray:
    """Whether an odd number of tokens falls on each of about as many bits as the set has tokens, as 64-bit words.

    Every token in which two sets differ flips one bit at most, so sketches never differ in more bits than the sets in tokens.
    """
    bits = 64
    while bits < len(h):
        bits *= 2
    at = (mix(h ^ C3) & U(bits - 1)).astype(np.int64)
    return np.packbits(np.bincount(at, minlength=bits).astype(np.uint8) & 1, bitorder="little").view("<u8")


def folded(sketch: np.ndarray, words: int) -> np.ndarray:
    """A sketch of fewer bits: halves laid over each other."""
    while len(sketch) > words:
        sketch = sketch[: len(sketch) // 2] ^ sketch[len(sketch) // 2 :]
    return sketch


def list_members(lists: DataFrame) -> DataFrame:
    """part, lo: the sets in the lists of each part, each once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, sets in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                lo = np.unique(np.frombuffer(sets, np.int64))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(lo), part)), pa.array(lo)], ["part", "lo"])

    return lists.select("part", "sets").mapInArrow(lean(run), "part long, lo long")


class Sketches:
    """Sizes and sketches of some sets; may_link() says which pairs could be similar, and never misses one."""

    def __init__(self, rows: list[dict]):
        self.at = {r["lo"]: i for i, r in enumerate(rows)}
        self.n = np.array([r["n"] for r in rows], np.int64)
        self.sketch = [np.frombuffer(r["sketch"], "<u8") for r in rows]
        self.short: dict[tuple[int, int], np.ndarray] = {}

    def table(self, own: list[int]) -> np.ndarray:
        words = min(len(self.sketch[i]) for i in own)
        out = np.empty((len(own), words), np.uint64)
        for k, i in enumerate(own):
            x = self.sketch[i]
            if len(x) != words:
                if (i, words) not in self.short:
                    self.short[i, words] = folded(x, words)
                x = self.short[i, words]
            out[k] = x
        return out

    def may_link(self, n: np.ndarray, table: np.ndarray, i: int, others: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which of the others may be similar to i, and in how many bits they differ."""
        apart = np.bitwise_count(table[others] ^ table[i]).sum(1, dtype=np.int64)
        a, b = np.minimum(n[others], n[i]), np.maximum(n[others], n[i])
        return (T_DEN * a >= T_NUM * b) & ((T_DEN + T_NUM) * apart <= (T_DEN - T_NUM) * (a + b)), apart


def first_pairs(own: np.ndarray, known: Sketches, found: set[tuple[int, int]]) -> np.ndarray:
    """Adds pairs of a list (ascending) that probably tie together all that belongs together: the first set with all
    that may be similar to it, each other set with the TRIES of those that seem nearest to it, then the same among
    the others. Returns the sets that may be similar to any other.
    """
    index = [known.at[x] for x in own.tolist()]
    table, n = known.table(index), known.n[index]
    rest, paired = np.arange(len(own)), np.zeros(len(own), bool)
    while len(rest) > 1:
        head, others = rest[0], rest[1:]
        may, _ = known.may_link(n, table, head, others)
        near, rest = others[may], others[~may]
        if not len(near):
            continue
        paired[head] = paired[near] = True
        found.update((int(own[head]), int(own[j])) for j in near)
        for j in rest:
            may, apart = known.may_link(n, table, j, near)
            paired[j] |= bool(may.any())
            for k in near[may][np.argsort(apart[may], kind="stable")[:TRIES]]:
                found.add((int(min(own[j], own[k])), int(max(own[j], own[k]))))
    return own[paired]


def remaining_pairs(own: np.ndarray, known: Sketches, group: np.ndarray) -> Iterator[tuple[int, int]]:
    """All pairs of a list that may be similar and don't hang together yet. group: of each set of known."""
    index = [known.at[x] for x in own.tolist()]
    ties = group[index]
    names, counts = np.unique(ties, return_counts=True)
    if len(names) == 1:
        return
    table, n = known.table(index), known.n[index]
    outside = np.flatnonzero(ties != names[np.argmax(counts)])
    late = np.zeros(len(own), bool)
    for j in outside:
        late[j] = True  # pairs of two such sets come up once
        others = np.flatnonzero((ties != ties[j]) & ~late)
        may, _ = known.may_link(n, table, j, others)
        for k in others[may]:
            yield int(min(own[j], own[k])), int(max(own[j], own[k]))


def candidates(lists: DataFrame, members: DataFrame, parts: int, last: bool = False) -> DataFrame:
    """part, a, b of pairs to compare; in the first round also part, lens, sets of what the last round must look at again.

    members: part, lo, n, sketch, and in the last round tie: the group each set is in so far. Ranged by part, so each
    part's members and then its lists come to one task, one part after the other.
    """
    tie = F.col("tie") if last else F.lit(None).cast("long").alias("tie")
    none = lambda kind, name: F.lit(None).cast(kind).alias(name)
    one = members.select("part", "lo", "n", "sketch", tie, none("binary", "lens"), none("binary", "sets"))
    two = lists.select("part", none("long", "lo"), none("long", "n"), none("binary", "sketch"), none("long", "tie"), "lens", "sets")
    rows = one.unionByName(two).repartitionByRange(parts, "part").sortWithinPartitions("part", F.col("lens").isNotNull())
    schema = pa.schema([("part", pa.int64()), ("a", pa.int64()), ("b", pa.int64()), ("lens", pa.binary()), ("sets", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, known = None, []
        for batch in batches:
            for r in batch.to_pylist():
                if r["part"] != part:
                    part, known = r["part"], []
                if r["lens"] is None:
                    known.append(r)
                    continue
                sketches, lo = Sketches(known), np.frombuffer(r["sets"], np.int64)
                group = np.array([x["tie"] for x in known], np.int64) if last else None
                found, again, at = set(), {}, 0
                for k in np.frombuffer(r["lens"], np.int64):
                    own = lo[at : at + k]
                    at += k
                    if last:
                        found.update(remaining_pairs(own, sketches, group))
                    elif len(left := first_pairs(own, sketches, found)) > 2:
                        again[left.tobytes()] = len(left)
                pairs = sorted(found)
                for i in range(0, len(pairs), 100_000):
                    a, b = zip(*pairs[i : i + 100_000], strict=True)
                    nothing = pa.nulls(len(a), pa.binary())
                    yield pa.RecordBatch.from_arrays([pa.array([part] * len(a), pa.int64()), pa.array(a, pa.int64()), pa.array(b, pa.int64()), nothing, nothing], schema=schema)
                if again:
                    yield pa.RecordBatch.from_pylist([{"part": part, "lens": np.array(list(again.values()), np.int64).tobytes(), "sets": b"".join(again)}], schema=schema)

    return rows.mapInArrow(lean(run), "part long, a long, b long, lens binary, sets binary")


def verified(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """pairs (a, b) with key_a, key_b and linked, by the exact similarity of whole texts. texts: lo, key, body."""
    one = texts.select(F.col("lo").alias("a"), F.col("key").alias("key_a"), F.col("body").alias("body_a"))
    two = texts.select(F.col("lo").alias("b"), F.col("key").alias("key_b"), F.col("body").alias("body_b"))
    joined = pairs.join(one, "a").join(two, "b").select("a", "b", "key_a", "key_b", "body_a", "body_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        recent: OrderedDict[int, set] = OrderedDict()

        def known(key: int, body: bytes) -> set:
            if key in recent:
                recent.move_to_end(key)
            else:
                recent[key] = shingle_set(body)
                if len(recent) > 48:
                    recent.popitem(last=False)
            return recent[key]

        for batch in batches:
            key_a, key_b, body_a, body_b = (batch.column(i).to_pylist() for i in (2, 3, 4, 5))
            linked = [similar(known(i, x), known(j, y)) for i, j, x, y in zip(key_a, key_b, body_a, body_b, strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], pa.array(linked, pa.bool_())], ["a", "b", "key_a", "key_b", "linked"])

    return joined.mapInArrow(lean(run), "a long, b long, key_a long, key_b long, linked boolean")


def forest(links: DataFrame) -> DataFrame:
    """links without edges that close a circle inside a block of at most FOREST_EDGES: the same components."""
    blocks = -(-links.count() // FOREST_EDGES)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        above: dict[int, int] = {}

        def top(x: int) -> int:
            while (y := above.setdefault(x, x)) != x:
                above[x] = x = above[y]
            return x

        for batch in batches:
            for u, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                a, b = top(u), top(v)
                above[max(a, b)] = min(a, b)
        pairs = [(x, top(x)) for x in list(above)]
        u, v = zip(*[p for p in pairs if p[0] != p[1]], strict=True) if any(x != y for x, y in pairs) else ((), ())
        yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])

    return links.repartition(max(1, blocks)).mapInArrow(lean(run), "u long, v long")


def components(links: DataFrame, rounds: int = 50) -> DataFrame:
    """node, component (the smallest node it hangs together with) for every node of links (u, v) but the smallest ones themselves.

    Alternates two steps that keep components and shorten paths: larger neighbours move to a node's smallest
    neighbour, then all smaller ones do. Ends when nothing changes, or raises after as many rounds; each round is a table in the shared folder.
    """
    edges = materialize(links.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "links")
    for _ in range(rounds):
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy(F.col("u").alias("x")).agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.filter("v > u").join(least, F.col("u") == F.col("x")).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        small_min = large.groupBy(F.col("u").alias("x")).agg(F.min("v").alias("m"))
        small = large.join(small_min, F.col("u") == F.col("x"))
        moved = small.filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(small.select("u", F.col("m").alias("v"))).distinct()
        after = materialize(moved, "links")
        settled = after.exceptAll(edges).isEmpty() and edges.exceptAll(after).isEmpty()
        edges = after
        if settled:
            return edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
    raise RuntimeError(f"components still change after {rounds} rounds")


def with_blocks(members: DataFrame) -> DataFrame:
    """members (lo, n, copies, component) once for each pair of blocks it is in: component, band, x, over, y and side.

    A component's sets are dealt by size band and hash into blocks of about BLOCK_TOKENS tokens and BLOCK_SETS sets. Similar
    sets lie in the same or neighbouring bands, so block x of a band meets every block y of it from x on, and every block y
    of the band above (over). side: 0 for a member of block x, 1 for one of block y.
    """
    edges = ", ".join(f"{e}L" for e in band_edges())
    placed = members.withColumn("band", F.expr(f"size(filter(array({edges}), e -> e < n))"))
    size = F.greatest(F.ceil(F.sum("n") / BLOCK_TOKENS), F.ceil(F.count(F.lit(1)) / BLOCK_SETS)).cast("int")
    blocks = placed.groupBy("component", "band").agg(size.alias("own"))
    at = lambda name, step: blocks.select("component", (F.col("band") + step).alias("band"), F.col("own").alias(name))
    blocks = blocks.join(at("below", 1), ["component", "band"], "left").join(at("above", -1), ["component", "band"], "left")
    rows = placed.join(blocks, ["component", "band"]).withColumn("at", F.pmod(F.xxhash64("lo"), F.col("own")).cast("int"))
    meet = lambda upto, body: f"IF({upto} > 0, transform(sequence(0, {upto} - 1), i -> {body}), array())"
    place = lambda band, x, over, y, side: f"named_struct('band', {band}, 'x', {x}, 'over', {over}, 'y', {y}, 'side', {side})"
    own = meet("own", f"IF(i >= at, {place('band', 'at', 'band', 'i', 0)}, {place('band', 'i', 'band', 'at', 1)})")
    up = meet("coalesce(above, 0)", place("band", "at", "band + 1", "i", 0))
    down = meet("coalesce(below, 0)", place("band - 1", "i", "band", "at", 1))
    return rows.withColumn("place", F.explode(F.expr(f"concat({own}, {up}, {down})"))).select("component", "place.*", "lo", "copies")


def linked_counts(own: list[set], copies: list[int], sides: list[int] | None) -> np.ndarray:
    """For each set, the copies of those similar to it. sides: only pairs of different sides count; None: all pairs.

    Exact: shingles are numbered, those of one set only left out, and intersections counted on bit rows.
    """
    number: dict[tuple, int] = {}
    columns = [np.fromiter((number.setdefault(t, len(number)) for t in x), np.int64, len(x)) for x in own]
    flat = np.concatenate(columns)
    often = np.bincount(flat, minlength=len(number)) > 1
    place = np.cumsum(often) - 1
    bits = np.zeros((len(own), -(-int(often.sum()) // 64) * 64), bool)
    for i, c in enumerate(columns):
        bits[i, place[c[often[c]]]] = True
    rows = np.packbits(bits, axis=1).view(np.uint64)
    del bits
    n, many, out = np.array([len(x) for x in own]), np.array(copies, np.int64), np.zeros(len(own), np.int64)
    side = np.array(sides if sides is not None else [0] * len(own))
    for i in range(len(own) - 1):
        others = np.arange(i + 1, len(own))
        if sides is not None:
            others = others[side[others] != side[i]]
        others = others[(T_DEN * np.minimum(n[others], n[i]) >= T_NUM * np.maximum(n[others], n[i]))]
        both = np.bitwise_count(rows[others] & rows[i]).sum(1, dtype=np.int64)
        hit = others[T_DEN * both >= T_NUM * (n[others] + n[i] - both)]
        out[i] += many[hit].sum()
        out[hit] += many[i]
    return out


def counted_links(placed: DataFrame, texts: DataFrame, parts: int) -> DataFrame:
    """lo and others (copies of the similar sets), a row for each pair of blocks that a set is in; pairs themselves are never sent."""
    key = ["component", "band", "x", "over", "y"]
    rows = placed.join(texts.select("lo", "body"), "lo").select(*key, "side", "lo", "copies", "body")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []

        def counted() -> Iterator[pa.RecordBatch]:
            if len(held) > 1:
                same = now[1:3] == now[3:5]
                out = linked_counts([shingle_set(r[3]) for r in held], [r[2] for r in held], None if same else [r[0] for r in held])
                found = np.flatnonzero(out)
                yield pa.RecordBatch.from_arrays([pa.array([held[i][1] for i in found], pa.int64()), pa.array(out[found], pa.int64())], ["lo", "others"])
            held.clear()

        for batch in batches:
            columns = [c.to_pylist() for c in batch.columns]
            for k, r in zip(zip(*columns[:5], strict=True), zip(*columns[5:], strict=True), strict=True):
                if k != now:
                    yield from counted()
                    now = k
                held.append(r)
        yield from counted()

    return rows.repartition(parts, *key).sortWithinPartitions(*key, "side", "lo").mapInArrow(lean(run), "lo long, others long")


def _narrow(df: DataFrame, rows: int) -> DataFrame:
    """df broadcast if it has few enough rows of fixed width, else as it is."""
    return F.broadcast(df) if rows <= FEW_IDS else df


def _texts(docs: DataFrame, pairs: DataFrame, firsts: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """lo, key, body of the sets in pairs: one document each."""
    wanted = materialize(pairs.select(F.explode(F.array("a", "b")).alias("lo")).distinct().join(firsts, "lo").select(F.col("first").alias("key"), "lo"), "shingle-wanted")
    keys = wanted.select(F.col("key").alias("k")).distinct()
    body = docs.select(F.col(id_col).cast("long").alias("key"), F.col(text_col).cast("binary").alias("body"))
    texts = body.join(_narrow(keys, wanted.count()), F.col("key") == F.col("k"), "left_semi")

    def stamped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            marks = [fingerprint(h)[1] if len(h := shingle_hashes(x or b"")) else None for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(marks, pa.int64())], ["key", "body", "lo"])

    # A key may stand for several texts where keys repeat; the fingerprint tells which is meant.
    chosen = wanted.select(F.col("key").alias("k"), F.col("lo").alias("l"))
    marked = texts.mapInArrow(lean(stamped), "key long, body binary, lo long").join(chosen, (F.col("key") == F.col("k")) & (F.col("lo") == F.col("l")), "left_semi")
    return materialize(marked.dropDuplicates(["key", "lo"]), "shingle-texts")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col, n_shingles, n_links, component_id for each row. n_links: other rows with a key whose sets are similar, equal ones among them."""
    spark = docs.sparkSession
    ship(spark)
    found = materialize(shingle_sets(docs, id_col, text_col), "shingle-sets")
    popular = popular_shingles(found)
    sets = found.filter("often is null").drop("often", "times")
    usable = sets.filter("key is not null and hi is not null")
    firsts = materialize(usable.groupBy("hi", "lo").agg(F.min("key").alias("first"), F.max("n_shingles").alias("n"), F.count(F.lit(1)).alias("copies")), "shingle-firsts")
    total = firsts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    partitions = max(spark.sparkContext.defaultParallelism, -(-int(total * 0.55) // BUCKET_ENTRIES))
    homes = max(HOMES, partitions // 8)
    lists = materialize(shared_lists(signature_buckets(docs, partitions, popular, id_col, text_col), partitions, homes), "shingle-lists")
    sketches = sets.join(firsts.select(F.col("first").alias("key"), "hi", "lo"), ["key", "hi", "lo"]).select("lo", F.col("n_shingles").alias("n"), "sketch").dropDuplicates(["lo"])
    members = materialize(list_members(lists).join(sketches, "lo"), "shingle-members")
    first = materialize(candidates(lists, members, partitions), "shingle-pairs")
    pairs = materialize(first.filter("a is not null").select("a", "b").distinct(), "shingle-pairs")
    texts = _texts(docs, pairs, firsts, id_col, text_col)
    one = materialize(verified(pairs, texts), "shingle-verified")

    again = first.filter("a is null").select("part", "lens", "sets")
    ties = components(forest(one.filter("linked").select(F.col("a").alias("u"), F.col("b").alias("v"))))
    tied = list_members(again).join(sketches, "lo").join(ties, F.col("lo") == F.col("node"), "left").withColumn("tie", F.coalesce("component", "lo"))
    more = candidates(again, materialize(tied, "shingle-members"), partitions, last=True).select("a", "b").distinct()
    more = materialize(more.join(one.select("a", "b"), ["a", "b"], "left_anti"), "shingle-pairs")
    late = _texts(docs, more, firsts, id_col, text_col)
    two = materialize(verified(more, late), "shingle-verified")
    linked = one.union(two).filter("linked")

    # What hangs together is known; now every pair inside a group is compared, to count its links. Two sets alone are done.
    tree = forest(linked.select(F.col("a").alias("u"), F.col("b").alias("v")))
    stars = components(tree)  # has no row for the smallest of a group
    heads = stars.select(F.col("component").alias("node"), "component").distinct()
    hung = stars.unionByName(heads).join(firsts.select("lo", "n", "copies").dropDuplicates(["lo"]), F.col("node") == F.col("lo")).select("lo", "n", "copies", "component")
    sized = materialize(hung.join(hung.groupBy("component").agg(F.count(F.lit(1)).alias("sets"), F.sum("copies").alias("all")), "component"), "shingle-groups")
    total = sized.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    width = max(shuffle_width(spark), -(-int(total) // (4 * BLOCK_TOKENS)))
    bodies = texts.unionByName(late).dropDuplicates(["lo"])
    counted = counted_links(with_blocks(sized.filter("sets > 2")), bodies, width)
    alone = sized.filter("sets = 2").select("lo", (F.col("all") - F.col("copies")).alias("others"))
    others = counted.unionByName(alone).groupBy("lo").agg(F.sum("others").alias("others"))

    links = forest(linked.select(F.col("key_a").alias("u"), F.col("key_b").alias("v")))

    # Keys that repeat with different texts tie their sets together.
    same = usable.join(firsts.select("hi", "lo", "first"), ["hi", "lo"]).filter("key <> first").select(F.col("key").alias("u"), F.col("first").alias("v"))
    repeats = usable.select("key", "hi", "lo").distinct().groupBy("key").count().filter("count > 1").select(F.col("key").alias("k"))
    tied = same.join(repeats, F.col("u") == F.col("k"), "left_semi")
    groups = components(links.union(tied))

    out = sets.join(firsts.select("hi", "lo", "first", "copies"), ["hi", "lo"], "left").join(others, "lo", "left")
    out = out.withColumn("own", F.least(F.col("key"), F.col("first"))).join(groups, F.col("own") == F.col("node"), "left")
    whole = F.when(F.col("key").isNotNull(), F.coalesce("component", "own", "key"))
    n_links = F.when(F.col("key").isNotNull(), F.coalesce(F.col("copies") - 1, F.lit(0)) + F.coalesce("others", F.lit(0)))
    return out.select(F.col("key").alias(id_col), "n_shingles", n_links.alias("n_links"), whole.alias("component_id"))


def one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with one row of each component: that with the smallest key; rows without a key stay, of rows with equal keys one stays."""
    found = near_duplicates(docs, id_col, text_col)
    gone = materialize(found.filter(F.col(id_col) != F.col("component_id")).select(F.col(id_col).alias("gone")).distinct(), "shingle-gone")
    left = docs.join(_narrow(gone, gone.count()), F.col(id_col) == F.col("gone"), "left_anti")
    again = materialize(left.groupBy(F.col(id_col).alias("again")).count().filter("count > 1 and again is not null").select("again"), "shingle-again")
    n = again.count()
    if not n:
        return left
    single = left.join(_narrow(again, n), F.col(id_col) == F.col("again"), "left_anti")
    return single.unionByName(left.join(_narrow(again, n), F.col(id_col) == F.col("again"), "left_semi").dropDuplicates([id_col]))


def op6_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
