"""Offline partitionings: tuples of similar values in groups of at most tau, each with its centroid.

A level is a small table of groups that were still too large or too wide, with their cut points; a tuple's path
through the levels gives its group. Each level costs one aggregation over the tuples that are still in play, whose ids, scaled
values and groups are written anew (those of the level before are deleted). Once no group that is cut has more than LOCAL_ROWS tuples,
each goes to one task that makes all levels below it. At the end the relation is written once, clustered by group.

Values are whole numbers (round(x * 10^digits)), so centroids, cuts and ties do not depend on the order of sums. A
value at or above the centroid, rounded up, goes to the upper side. Groups of equal tuples can't be cut, so they are sliced
by a hash of the tuple id. Nulls count as 0.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace
from decimal import Decimal

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..scratch import discard, scratch_path, stored

BROADCAST_GROUPS = 200_000
#: Groups of at most as many tuples are cut to the end inside a task, in relations that have at least LOCAL_LEAST tuples.
LOCAL_ROWS, LOCAL_LEAST = 1_000_000, 10_000
ROOT = "r"
#: Bits of a value that are summed apart from those above.
HALF = 31
#: While groups are made, their names are numbers: bits for the side of the parent (or its slice), for the level and for the part of its statistics.
#: Of more attributes than side bits the names are paths from the beginning.
SIDE_BITS, LEVEL_BITS, PART_BITS = 20, 7, 12


@dataclass(frozen=True)
class Absolute:
    """Every tuple within omega of its group's centroid in each attribute."""

    omega: float


@dataclass(frozen=True)
class Relative:
    """Within gamma times the centroid's absolute value."""

    gamma: float


def radius_for(eps: float, sense: str) -> Relative:
    """The relative radius behind a bound of (1 - eps)^6 or (1 + eps)^6."""
    return Relative(eps if sense == "max" else eps / (1 + eps))


@dataclass
class Partitioning:
    """df: the relation with tid and gid. groups: gid, n, radius and avg_/min_/max_ of each attribute. nodes: the whole tree."""

    df: DataFrame
    groups: DataFrame
    nodes: DataFrame
    attrs: list[str]
    tau: int
    radius: Absolute | Relative | None
    digits: int
    metrics: dict[str, float] = field(default_factory=dict)

    def save(self, path: str) -> None:
        for name in ("df", "groups", "nodes"):
            getattr(self, name).write.parquet(f"{path}/{name}")
        kind, value = (type(self.radius).__name__, list(vars(self.radius).values())[0]) if self.radius else ("none", 0.0)
        self.df.sparkSession.createDataFrame([(self.attrs, self.tau, kind, float(value), self.digits)], "attrs array<string>, tau long, radius string, size double, digits int").write.parquet(f"{path}/meta")

    @staticmethod
    def load(spark, path: str) -> Partitioning:
        m = spark.read.parquet(f"{path}/meta").first()
        radius = {"Absolute": Absolute, "Relative": Relative}.get(m.radius, lambda _: None)(m.size)
        return Partitioning(*(spark.read.parquet(f"{path}/{x}") for x in ("df", "groups", "nodes")), list(m.attrs), m.tau, radius, m.digits)

    def sample(self, fraction: float, seed: int = 0) -> Partitioning:
        """The same groups over a hash sample of the tuples; smaller fractions are subsets of larger ones."""
        rows = self.df.filter(F.pmod(F.xxhash64("tid", F.lit(seed)), F.lit(1_000_000)) < int(fraction * 1_000_000))
        groups = group_statistics(rows, self.attrs, self.digits)
        return replace(self, df=rows, groups=groups)

    def cut(self, radius: Absolute | Relative | None, tau: int | None = None) -> Partitioning:
        """The coarsest groups of the stored tree that satisfy a radius and size, chosen at query time."""
        fine = ~_violates(self.attrs, tau or self.tau, radius, self.digits)
        good = self.nodes.filter(fine | F.col("leaf")).select("gid")
        parents = F.transform(F.sequence(F.lit(1), F.size(F.split("gid", "/")) - 1), lambda k: F.array_join(F.slice(F.split("gid", "/"), 1, k), "/"))
        under = good.filter(F.size(F.split("gid", "/")) > 1).select("gid", F.explode(parents).alias("above")).join(good.select(F.col("gid").alias("above")), "above").select("gid").distinct()
        chosen = good.join(under, "gid", "left_anti").select(F.col("gid").alias("top"))
        paths = self.groups.select("gid", F.explode(F.transform(F.sequence(F.lit(1), F.size(F.split("gid", "/"))), lambda k: F.array_join(F.slice(F.split("gid", "/"), 1, k), "/"))).alias("top"))
        moved = paths.join(chosen, "top").select(F.col("gid").alias("old"), "top")
        return self.remapped(moved, tau or self.tau, radius)

    def remapped(self, moved: DataFrame, tau: int | None = None, radius=None) -> Partitioning:
        """moved: old, top. Groups that aren't listed stay."""
        n = moved.count()
        side = F.broadcast(moved) if n <= BROADCAST_GROUPS else moved
        rows = self.df.join(side, self.df["gid"] == F.col("old"), "left").withColumn("gid", F.coalesce("top", "gid")).drop("old", "top")
        return replace(self, df=rows, groups=stored(group_statistics(rows, self.attrs, self.digits), "groups"), tau=tau or self.tau, radius=radius)

    def merge(self) -> Partitioning:
        """Pairs of neighbouring groups (in path order) become one; repeated, this ends in the original relation."""
        from pyspark.sql import Window

        ordered = self.groups.select("gid", ((F.row_number().over(Window.orderBy("gid")) - 1) / 2).cast("long").alias("pair"))
        return self.remapped(ordered.select(F.col("gid").alias("old"), F.concat(F.lit("m"), F.lpad(F.col("pair").cast("string"), 12, "0")).alias("top")), self.tau * 2)

    def refine(self, tau: int) -> Partitioning:
        return quad_partition(self.df.drop("gid"), self.attrs, tau, self.radius, self.digits)

    def drop_attributes(self, gone: set[str]) -> Partitioning:
        rest = [a for a in self.attrs if a not in gone]
        return quad_partition(self.df.drop("gid"), rest or self.attrs[:1], self.tau, self.radius, self.digits)


def scaled(attr: str, digits: int) -> Column:
    return F.coalesce(F.round(F.col(attr).cast("double") * 10**digits).cast("long"), F.lit(0).cast("long"))


def _statistics(narrow: DataFrame, attrs: list[str]) -> DataFrame:
    """Per gid: n, and s (the sum), lo, hi, cut (the centroid rounded up) of each attribute; map-side partial sums.

    Sums are exact: upper and lower parts of the values are added as whole numbers of 64 bits, which costs far less than decimals a row.
    """
    aggs = [F.count(F.lit(1)).alias("n")]
    for i in range(len(attrs)):
        v = F.col(f"v{i}")
        aggs += [F.sum(F.shiftright(v, HALF)).alias(f"up{i}"), F.sum(v.bitwiseAND(F.lit((1 << HALF) - 1))).alias(f"low{i}"), F.min(v).alias(f"lo{i}"), F.max(v).alias(f"hi{i}")]
    out = narrow.groupBy("gid").agg(*aggs)
    for i in range(len(attrs)):
        out = out.withColumn(f"s{i}", (F.col(f"up{i}").cast("decimal(20,0)") * F.lit(1 << HALF).cast("decimal(10,0)") + F.col(f"low{i}").cast("decimal(20,0)")).cast("decimal(30,0)"))
        s, n = F.col(f"s{i}"), F.col("n")
        floor_ = F.expr(f"CAST(s{i} DIV n AS BIGINT)")  # towards zero
        left = s - floor_.cast("decimal(20,0)") * n.cast("decimal(20,0)")
        out = out.withColumn(f"cut{i}", floor_ + F.when(left > 0, 1).otherwise(0)).drop(f"up{i}", f"low{i}")
    return out


def _described(stats: DataFrame, attrs: list[str], digits: int) -> DataFrame:
    unit = float(10**digits)
    out = stats
    spans = []
    for i, a in enumerate(attrs):
        avg = F.col(f"s{i}").cast("double") / F.col("n") / unit
        out = out.withColumns({f"avg_{a}": avg, f"min_{a}": F.col(f"lo{i}") / unit, f"max_{a}": F.col(f"hi{i}") / unit})
        spans.append(F.greatest(F.col(f"max_{a}") - F.col(f"avg_{a}"), F.col(f"avg_{a}") - F.col(f"min_{a}")))
    return out.withColumn("radius", F.greatest(*spans) if len(spans) > 1 else spans[0])


def group_statistics(rows: DataFrame, attrs: list[str], digits: int = 6) -> DataFrame:
    """The representative relation of a relation with gid: one aggregation."""
    narrow = rows.select("gid", *(scaled(a, digits).alias(f"v{i}") for i, a in enumerate(attrs)))
    keep = ["gid", "n", "radius", *(f"{s}_{a}" for a in attrs for s in ("avg", "min", "max"))]
    return _described(_statistics(narrow, attrs), attrs, digits).select(*keep)


def _violates(attrs: list[str], tau: int, radius, digits: int) -> Column:
    out = F.col("n") > tau
    if isinstance(radius, Absolute):
        out = out | (F.col("radius") > radius.omega)
    if isinstance(radius, Relative):
        for a in attrs:
            far = F.greatest(F.col(f"max_{a}") - F.col(f"avg_{a}"), F.col(f"avg_{a}") - F.col(f"min_{a}"))
            out = out | (far > (radius.gamma + 1e-9) * F.abs(F.col(f"avg_{a}")))
    return out


def _used(attrs: list[str], split: str, tau: int, level: int) -> list[Column]:
    """Per attribute: whether a violating group is cut in it."""
    varies = [F.col(f"hi{i}") > F.col(f"lo{i}") for i in range(len(attrs))]
    if split == "all":
        return varies
    if split == "cycle":  # one attribute a level, the next that varies
        order = [(level + i) % len(attrs) for i in range(len(attrs))]
        first = F.coalesce(*(F.when(varies[i], F.lit(i)) for i in order))
        return [first == i for i in range(len(attrs))]
    spread = [F.when(varies[i], (F.col(f"max_{a}") - F.col(f"min_{a}")) / F.greatest(F.abs(F.col(f"avg_{a}")), F.lit(1e-9))).otherwise(F.lit(0.0)) for i, a in enumerate(attrs)]
    ranked = F.array_sort(F.array(*(F.struct((-s).alias("s"), F.lit(i).alias("i")) for i, s in enumerate(spread))))
    many = F.greatest(F.lit(1), F.ceil(F.log2(F.greatest(F.col("n") / tau, F.lit(2.0)))).cast("int"))
    chosen = F.transform(F.slice(ranked, F.lit(1), many), lambda s: s["i"])
    return [varies[i] & F.array_contains(chosen, i) for i in range(len(attrs))]


def _child(k: int, numbers: bool) -> Column:
    """The name of the group below cut_gid that a tuple falls into."""
    slice_ = F.pmod(F.xxhash64("tid", "cut_depth"), F.col("slices"))
    if numbers:
        sides = F.lit(0).cast("long")
        for i in range(k):
            sides = sides + F.when(F.col(f"u{i}") & (F.col(f"v{i}") >= F.col(f"cut{i}")), F.lit(1 << i)).otherwise(F.lit(0)).cast("long")
        return F.shiftleft("cut_rank", SIDE_BITS) + F.when(F.col("slices") > 0, slice_).otherwise(sides)
    bits = F.concat(*(F.when(~F.col(f"u{i}"), "-").when(F.col(f"v{i}") >= F.col(f"cut{i}"), "1").otherwise("0") for i in range(k)))
    return F.concat_ws("/", "gid", F.when(F.col("slices") > 0, F.concat(F.lit("s"), slice_.cast("string"))).otherwise(bits))


def _step(rows: DataFrame, cuts: DataFrame, many: int, k: int, numbers: bool, inner: bool) -> DataFrame:
    """One level down, for tuples of groups that are cut; inner drops the others. The cuts of all levels are one table, so a chain of steps broadcasts it once."""
    side = F.broadcast(cuts) if many <= BROADCAST_GROUPS else cuts
    joined = rows.join(side, rows["gid"] == F.col("cut_gid"), "inner" if inner else "left")
    name = _child(k, numbers)
    moved = name if inner else F.when(F.col("cut_gid").isNotNull(), name).otherwise(F.col("gid"))
    return joined.withColumn("gid", moved).drop(*cuts.columns)


def _path(stats: DataFrame, cuts: DataFrame | None, many: int, k: int) -> DataFrame:
    """stats with the path of each numbered group: its parent's path and the side or slice."""
    if cuts is None:
        return stats.withColumn("path", F.lit(ROOT))
    parents = cuts.select(F.col("cut_rank").alias("above"), F.col("cut_path").alias("from"), F.col("slices").alias("cut_in"), *(F.col(f"u{i}").alias(f"by{i}") for i in range(k)))
    parents = F.broadcast(parents) if many <= BROADCAST_GROUPS else parents
    code = F.col("gid").bitwiseAND(F.lit((1 << SIDE_BITS) - 1))
    bits = F.concat(*(F.when(~F.col(f"by{i}"), "-").when(code.bitwiseAND(F.lit(1 << i)) != 0, "1").otherwise("0") for i in range(k)))
    last = F.when(F.col("cut_in") > 0, F.concat(F.lit("s"), code.cast("string"))).otherwise(bits)
    return stats.join(parents, F.shiftright("gid", SIDE_BITS) == F.col("above")).withColumn("path", F.concat_ws("/", "from", last)).drop(*parents.columns)


def _local_rules(k: int, tau: int, radius: Absolute | Relative | None, digits: int, split: str) -> tuple[Callable, Callable]:
    """plan and sides: the rules of _violates, _used and _child outside Spark, on whole numbers and the same double operations.

    plan(level, n, sums, lo, hi): None for a group that stays, else whether each attribute is cut, and the number of slices.
    sides(depth, slices, used, cuts, tids, values): the side or slice of each tuple.
    """
    unit, most = float(10**digits), 1 << SIDE_BITS
    omega = radius.omega if isinstance(radius, Absolute) else None
    gamma = radius.gamma + 1e-9 if isinstance(radius, Relative) else None
    p1, p2, p3, p4, p5 = (np.uint64(p) for p in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))

    def plan(level: int, n: int, sums: list[int], lo: list[int], hi: list[int]) -> tuple[list[bool], int] | None:
        varies = [hi[i] > lo[i] for i in range(k)]
        bad = n > tau
        if not bad and (omega is not None or gamma is not None):
            for i in range(k):
                avg = float(sums[i]) / n / unit
                far = max(hi[i] / unit - avg, avg - lo[i] / unit)
                bad = bad or (far > omega if omega is not None else far > gamma * abs(avg))
        if not bad or (n <= tau and not any(varies)):
            return None
        if not any(varies):
            return varies, min(most, math.ceil(1.25 * n / tau) + 1)
        if split == "cycle":
            first = next(i for i in ((level + j) % k for j in range(k)) if varies[i])
            varies = [i == first for i in range(k)]
        return varies, 0

    def turned(x: np.ndarray, by: int) -> np.ndarray:
        return (x << np.uint64(by)) | (x >> np.uint64(64 - by))

    def mixed(h: np.ndarray) -> np.ndarray:
        h = (h ^ (h >> np.uint64(33))) * p2
        h = (h ^ (h >> np.uint64(29))) * p3
        return h ^ (h >> np.uint64(32))

    def hashed(tids: np.ndarray, depth: np.ndarray) -> np.ndarray:
        """Spark's xxhash64 of a long and an int."""
        h = (np.uint64(42 + 8) + p5) ^ (turned(tids.astype(np.int64).view(np.uint64) * p2, 31) * p1)
        h = mixed(turned(h, 27) * p1 + p4)
        h = (h + p5 + np.uint64(4)) ^ (depth.astype(np.uint64) * p1)
        return mixed(turned(h, 23) * p2 + p3).view(np.int64)

    def sides(depth: np.ndarray, slices: np.ndarray, used: np.ndarray, cuts: np.ndarray, tids: np.ndarray, values: list[np.ndarray]) -> np.ndarray:
        out = np.zeros(len(tids), np.int64)
        for i in range(k):
            out += (used[..., i] & (values[i] >= cuts[..., i])).astype(np.int64) << i
        at = np.flatnonzero(np.broadcast_to(slices > 0, out.shape))
        if len(at):
            out[at] = np.mod(hashed(tids[at], np.broadcast_to(depth, out.shape)[at]), np.broadcast_to(slices, out.shape)[at])
        return out

    return plan, sides


def _finished(active: DataFrame, found: DataFrame, k: int, level: int, max_levels: int, rules: tuple[Callable, Callable]) -> DataFrame:
    """All groups below those found (whose level is given), each made inside one task: path, level, n, s, lo, hi, cut."""
    plan, sides = rules
    kinds = {"gid": pa.int64(), "suffix": pa.string(), "level": pa.int32(), "n": pa.int64()} | {f"{c}{i}": pa.decimal128(30, 0) if c == "s" else pa.int64() for c in ("s", "lo", "hi", "cut") for i in range(k)}

    def named(code: int, used: list[bool], slices: int) -> str:
        return f"/s{code}" if slices else "/" + "".join("-" if not u else "1" if code >> i & 1 else "0" for i, u in enumerate(used))

    def below(gid: int, depth: int, tids: np.ndarray, values: list[np.ndarray]) -> Iterator[tuple]:
        todo = [("", level, tids, values)]
        while todo:
            path, at, tids, values = todo.pop()
            n = len(tids)
            sums = [(int((v >> 31).sum()) << 31) + int((v & ((1 << 31) - 1)).sum()) for v in values]
            lo, hi = [int(v.min()) for v in values], [int(v.max()) for v in values]
            cuts = [-(-x // n) for x in sums]
            if path:
                yield (gid, path, at, n, *map(Decimal, sums), *lo, *hi, *cuts)
            how = plan(at, n, sums, lo, hi)
            if how is None or at + 1 >= max_levels:
                continue
            used, slices = how
            codes = sides(np.array(depth + len(path)), np.array(slices), np.array(used), np.array(cuts), tids, values)
            order = np.argsort(codes, kind="stable")
            starts = np.flatnonzero(np.diff(codes[order], prepend=-1))
            for rows in np.split(order, starts[1:]):
                todo.append((path + named(int(codes[rows[0]]), used, slices), at + 1, tids[rows], [v[rows] for v in values]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def made() -> Iterator[pa.RecordBatch]:
            if held:
                t = pa.Table.from_batches(held)
                rows = list(below(held[0]["gid"][0].as_py(), held[0]["cut_depth"][0].as_py(), t["tid"].to_numpy(), [t[f"v{i}"].to_numpy() for i in range(k)]))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, x) for c, x in zip(zip(*rows, strict=True), kinds.values(), strict=True)], list(kinds))

        for batch in batches:
            gids = batch["gid"].to_numpy()
            starts = [0, *(np.flatnonzero(np.diff(gids)) + 1).tolist(), len(gids)]
            for a, b in zip(starts, starts[1:], strict=False):
                if a < b:
                    if held and held[0]["gid"][0].as_py() != gids[a]:
                        yield from made()
                        held = []
                    held.append(batch.slice(a, b - a))
        yield from made()

    roots = found.select("cut_gid", "cut_depth")
    rows = active.join(F.broadcast(roots), active["gid"] == F.col("cut_gid")).select("gid", "cut_depth", "tid", *(f"v{i}" for i in range(k)))
    parts = max(1, int(active.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    schema = "gid long, suffix string, level int, n long, " + ", ".join(f"{c}{i} {'decimal(30,0)' if c == 's' else 'long'}" for c in ("s", "lo", "hi", "cut") for i in range(k))
    made = rows.repartition(parts, "gid").sortWithinPartitions("gid").mapInArrow(run, schema)
    paths = F.broadcast(found.select("cut_gid", "cut_path"))
    return made.join(paths, F.col("gid") == F.col("cut_gid")).withColumn("path", F.concat("cut_path", "suffix")).drop("gid", "suffix", "cut_gid", "cut_path")


def _leaf_numbers(tree: list, k: int, rules: tuple[Callable, Callable]) -> tuple[Callable, dict[str, int]]:
    """tree: rows of path, level, n, leaf, s, lo, hi and cut. A function of tuple ids and values that gives the number of each tuple's group; and numbers and sizes by path."""
    plan, sides = rules
    at = {r["path"]: j for j, r in enumerate(tree)}
    used, cuts = np.zeros((len(tree), k), bool), np.zeros((len(tree), k), np.int64)
    slices, depth, inner = np.zeros(len(tree), np.int64), np.array([len(r["path"]) for r in tree]), np.zeros(len(tree), bool)
    for j, r in enumerate(tree):
        if not r["leaf"]:
            own, slices[j] = plan(r["level"], r["n"], [int(r[f"s{i}"]) for i in range(k)], [r[f"lo{i}"] for i in range(k)], [r[f"hi{i}"] for i in range(k)])
            used[j], cuts[j], inner[j] = own, [r[f"cut{i}"] for i in range(k)], True
    edges = []
    for path, j in at.items():
        above, _, last = path.rpartition("/")
        if above:
            edges.append((at[above] << SIDE_BITS | (int(last[1:]) if last[0] == "s" else sum(1 << i for i, c in enumerate(last) if c == "1")), j))
    edges.sort()
    keys, ends = (np.array([e[x] for e in edges], np.int64) for x in (0, 1))
    root, bits = at[ROOT], SIDE_BITS

    def numbers(tid: pd.Series, *values: pd.Series) -> pd.Series:
        tids, vs = tid.to_numpy(), [v.to_numpy() for v in values]
        out, moving = np.full(len(tids), root), np.arange(len(tids))
        while True:
            moving = moving[inner[out[moving]]]
            if not len(moving):
                return pd.Series(out)
            g = out[moving]
            codes = sides(depth[g], slices[g], used[g], cuts[g], tids[moving], [v[moving] for v in vs])
            out[moving] = ends[np.searchsorted(keys, (g << bits) | codes)]

    return numbers, {r["path"]: (j, r["n"]) for j, r in enumerate(tree) if not inner[j]}


def _places(leaves: dict[str, tuple[int, int]], parts: int) -> list[tuple[int, str, int, int]]:
    """Number, path, first part and number of parts of each group: parts of about the same size, in path order. Sizes are known, so nothing is sampled."""
    share, before, out = sum(n for _, n in leaves.values()) / parts, 0, []
    for path, (j, n) in sorted(leaves.items()):
        first, last = min(parts - 1, int(before / share)), min(parts - 1, int((before + n - 1) / share))
        out.append((j, path, first, last - first + 1 if n > share else 1))
        before += n
    return out


def quad_partition(df: DataFrame, attrs: list[str], tau: int | float, radius: Absolute | Relative | None = None, digits: int = 6, split: str = "all", max_levels: int = 64) -> Partitioning:
    """split: all (every attribute at its centroid), adaptive (only as many of the widest as the size needs), cycle (one at a time)."""
    begin = time.perf_counter()
    spark, k = df.sparkSession, len(attrs)
    numbers = k <= SIDE_BITS
    if isinstance(tau, float) and tau < 1:
        tau = max(1, math.ceil(tau * df.count()))
    tau = int(tau)
    values = [scaled(a, digits).alias(f"v{i}") for i, a in enumerate(attrs)]
    root = F.lit(0).cast("long") if numbers else F.lit(ROOT)
    narrow = stored(df.select("tid", *values), "partition-values").withColumn("gid", root)
    folder, cuts, above = scratch_path(spark, "partition-cuts"), None, 0
    nodes: list[DataFrame] = []
    leaves = 0
    bad = _violates(attrs, tau, radius, digits)
    equal = None
    for i in range(k):
        one = F.col(f"hi{i}") == F.col(f"lo{i}")
        equal = one if equal is None else equal & one
    splits = bad & ~(equal & (F.col("n") <= tau))
    slices = F.when(equal, F.least(F.lit(1 << SIDE_BITS), F.ceil(1.25 * F.col("n") / tau).cast("long") + 1)).otherwise(F.lit(0).cast("long"))
    rules = _local_rules(k, tau, radius, digits, split) if numbers and split in ("all", "cycle") and dict(df.dtypes)["tid"] == "bigint" else None
    below, total = None, 0
    place = F.monotonically_increasing_id()  # number of the part above 33 bits, of the row below
    active = narrow
    for level in range(max_levels):
        if cuts is not None:  # written at each level, so no plan grows with the levels
            before, active = active, stored(_step(active, cuts, above, k, numbers, inner=True), "partition-active")
            if level > 1:
                discard(before)
        stats = _described(_statistics(active, attrs), attrs, digits)
        stats = _path(stats, cuts, above, k) if numbers else stats.withColumn("path", F.col("gid"))
        rank = F.shiftleft(F.shiftleft(place.bitwiseAND(F.lit((1 << 33) - 1)), PART_BITS) + F.shiftright(place, 33), LEVEL_BITS) + F.lit(level + 1)
        stats = stored(stats.coalesce(1 << PART_BITS).withColumns({"level": F.lit(level), "rank": rank}), "partition-level")
        nodes.append(stats.withColumn("leaf", ~splits))
        count = stats.agg(F.count(F.lit(1)).alias("n"), F.count_if(splits).alias("many"), F.max(F.when(splits, F.col("n"))).alias("most")).first()
        leaves += count.n - count.many
        if not count.many:
            break
        used = _used(attrs, split, tau, level)
        found = stats.filter(splits).select(F.col("gid").alias("cut_gid"), F.col("rank").alias("cut_rank"), F.col("path").alias("cut_path"), F.length("path").alias("cut_depth"), slices.alias("slices"), *(f"cut{i}" for i in range(k)), *(u.alias(f"u{i}") for i, u in enumerate(used)))
        total = total or count.most
        if rules and total >= LOCAL_LEAST and count.most <= LOCAL_ROWS and above + count.many <= BROADCAST_GROUPS:
            rest = stored(_described(_finished(active, found, k, level, max_levels, rules), attrs, digits), "partition-below")
            size = rest.agg(F.count(F.lit(1)).alias("n"), F.count_if(splits & (F.col("level") == max_levels - 1)).alias("deep"), F.max("level").alias("last")).first()
            if size.deep:
                raise ValueError(f"groups are still too large after {max_levels} levels")
            if above + count.n + size.n <= BROADCAST_GROUPS:
                below = rest.withColumn("leaf", ~splits)
                break
            rules = None  # too many groups for every task to know, so they are made level by level
        found.write.mode("append").parquet(folder)
        cuts, above = spark.read.schema(found.schema).parquet(folder), above + count.many
    else:
        raise ValueError(f"groups are still too large after {max_levels} levels")
    if active is not narrow:
        discard(active)
    rows = df.select("*", *values).withColumn("gid", root)
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    keep = ["gid", "n", "radius", *(f"{s}_{a}" for a in attrs for s in ("avg", "min", "max"))]
    if below is not None:
        columns = ["path", *keep[1:], "level", "leaf", *(f"{c}{i}" for c in ("s", "lo", "hi", "cut") for i in range(k))]
        nodes = [x.select(*columns) for x in (*nodes, below)]
    tree = nodes[0]
    for x in nodes[1:]:
        tree = tree.unionByName(x)
    if below is not None:
        number, leaves_at = _leaf_numbers(tree.select("path", "level", "n", "leaf", *columns[-4 * k :]).collect(), k, rules)
        names = F.broadcast(spark.createDataFrame(_places(leaves_at, parts), "cut_gid long, cut_path string, first int, wide int"))
        rows = rows.withColumn("gid", F.pandas_udf(number, "long")("tid", *(f"v{i}" for i in range(k))))
        rows = rows.join(names, F.col("gid") == F.col("cut_gid")).withColumn("gid", F.col("cut_path"))
        to = F.col("first") + F.pmod(F.xxhash64("tid"), F.col("wide")).cast("int")
        rows = rows.withColumn("to", to).drop("cut_gid", "cut_path", "first", "wide").repartitionById(parts, F.col("to")).drop("to")
    else:
        for _ in range(len(nodes) - 1):
            rows = _step(rows, cuts, above, k, numbers, inner=False)
    if numbers and below is None:
        names = tree.filter("leaf").select(F.col("gid").alias("cut_gid"), F.col("path").alias("cut_path"))
        names = F.broadcast(names) if leaves <= BROADCAST_GROUPS else names
        rows = rows.join(names, F.col("gid") == F.col("cut_gid")).withColumn("gid", F.col("cut_path")).drop("cut_gid", "cut_path")
    rows = rows.drop(*(f"v{i}" for i in range(k)))
    if below is None:
        rows = rows.repartitionByRange(parts, "gid", "tid")
    rows = stored(rows.sortWithinPartitions("gid", "tid"), "partition")
    tree = tree.withColumn("gid", F.col("path")).select(*keep, "level", "leaf")
    spent = time.perf_counter() - begin
    return Partitioning(rows, tree.filter("leaf").select(*keep), tree, list(attrs), tau, radius, digits, {"seconds": spent, "levels": len(nodes) if below is None else size.last + 1, "jobs": 4 * len(nodes) + 2})


def kd_partition(df: DataFrame, attrs: list[str], tau: int | float, radius=None, digits: int = 6) -> Partitioning:
    """Two sides a level, attributes in turn."""
    return quad_partition(df, attrs, tau, radius, digits, split="cycle")


def omega_for(groups: DataFrame, attrs: list[str], eps: float, sense: str) -> float:
    """The smallest gamma * |centroid value| over groups and attributes: an absolute radius for the bound (0 if a centroid has a 0)."""
    gamma = radius_for(eps, sense).gamma
    least = F.least(*(F.min(F.abs(F.col(f"avg_{a}"))) for a in attrs)) if len(attrs) > 1 else F.min(F.abs(F.col(f"avg_{attrs[0]}")))
    return gamma * groups.agg(least.alias("w")).first()["w"]


def partition_report(part: Partitioning, tau: int | None = None, radius=None) -> DataFrame:
    """Groups, the largest, and the shares that break size and radius."""
    size = F.avg((F.col("n") > (tau or part.tau)).cast("double"))
    wide = F.avg(_violates(part.attrs, 1 << 62, radius or part.radius, part.digits).cast("double"))
    return part.groups.agg(F.count(F.lit(1)).alias("groups"), F.max("n").alias("largest"), size.alias("over_tau"), wide.alias("over_radius"))


def attribute_sets(query_attrs: list[set[str]], df: DataFrame) -> dict[str, list[str]]:
    """Partitioning attributes to choose from: one query's, the workload's, all numeric ones."""
    numeric = [f.name for f in df.schema.fields if f.dataType.typeName() in ("integer", "long", "double", "float", "short", "byte") and f.name not in ("tid", "gid")]
    out = {f"q{i}": [a for a in numeric if a in s] for i, s in enumerate(query_attrs)}
    union = set().union(*query_attrs) if query_attrs else set()
    return out | {"workload": [a for a in numeric if a in union], "numeric": numeric}


def coverage(part_attrs: list[str], query_attrs: set[str]) -> float:
    return len(part_attrs) / max(1, len(query_attrs))
