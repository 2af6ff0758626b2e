"""Quality rules whose cutoffs keep the share of falsely rejected documents under a stated risk.

Each rule scores a document (higher is worse). A fixed path of LEVELS steps tightens the cutoffs of all rules together,
from ones that hardly any text exceeds. Labelled documents of good quality form the holdout of their stratum (the
language). Step by step, the exact binomial test must reject "all rules together falsely reject more than the risk"; the
first failure ends the stratum's path, so the tests inside a stratum need no correction (fixed sequence) and the whole
risk is spent on what the rules reject together, not divided among them. The error level is divided by the number of
strata (Bonferroni), so with probability 1 - error all strata keep their false rejections under the risk. Strata with
too few labels for a test are pooled into one, whose cutoffs hold for all of them together; where even that has too few,
nothing is rejected beyond the base rules. Which strata are pooled follows from the numbers of labels alone.

Defined results: null and empty texts have no words and fail the base rule; a null language is a
stratum of its own; several labels of a document count once, as good only if all are; an empty
table gives no rows; repeated rows are each judged by themselves; other columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize, ship, table

SYMBOLS = "#*$%&|<>"
FIELDS = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words")
#: Per rule the cutoffs on the path, from loose to tight; a document fails if its score is above the accepted one.
LEVELS = 36
GRIDS = {
    "symbols": [2 * 0.86**i for i in range(LEVELS)],
    "dup_lines": [1 - 0.026 * (i + 1) for i in range(LEVELS)],
    "repeats": [0.2 - 0.005 * i for i in range(LEVELS)],
    "long_words": [40 * 0.95**i for i in range(LEVELS)],
    "short_words": [1 - 0.0215 * i for i in range(LEVELS)],
}
RISK, ERROR = 0.02, 0.05


def rule_score(rule: str) -> Column:
    n = F.greatest(F.col("n_words"), F.lit(1))
    return {
        "symbols": F.col("n_symbols") / n,
        "dup_lines": F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1)),
        "repeats": F.col("n_repeat_words") / n,
        "long_words": F.col("word_chars") / n,
        "short_words": F.when(F.col("word_chars") > 0, n / F.col("word_chars")).otherwise(0.0),
    }[rule]


def text_features(raw: bytes) -> tuple[int, int, int, int, int, int]:
    """FIELDS of a text in UTF-8. Bytes split exactly at the blanks that separate words."""
    words = raw.split()
    n = len(words)
    body = b"".join(words)
    chars = len(body.decode())
    symbols = len(body) - len(body.translate(None, SYMBOLS.encode()))
    lines = [x for x in raw.split(b"\n") if x and not x.isspace()]
    repeated = 0
    if n > 5:
        grams = list(zip(words, words[1:], words[2:], words[3:], words[4:]))
        if len(set(grams)) < len(grams):
            first: dict[tuple, int] = {}
            twice = bytearray(len(grams))
            for i, g in enumerate(grams):
                j = first.setdefault(g, i)
                if j != i:
                    twice[i] = twice[j] = 1
            end = 0  # words up to here are counted
            for i in range(len(grams)):
                if twice[i]:
                    repeated += i + 5 - max(i, end)
                    end = i + 5
    return n, chars, symbols, len(lines), len(lines) - len(set(lines)), repeated


def quality_features(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum_col: str = "lang") -> DataFrame:
    """id_col, stratum and FIELDS for each row, over the whole text."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [text_features(t or b"") for t in batch.column(2).to_pylist()]
            columns = zip(*rows, strict=True) if rows else [[]] * len(FIELDS)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c, pa.int64()) for c in columns)], ["key", "stratum", *FIELDS])

    kind = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(F.col(id_col).alias("key"), F.col(stratum_col).cast("string").alias("stratum"), F.col(text_col).cast("binary").alias("body"))
    return rows.mapInArrow(run, f"key {kind}, stratum string, " + ", ".join(f"{f} long" for f in FIELDS)).withColumnRenamed("key", id_col)


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def binomial_at_most(k: int, n: int, p: float, enough: float = 1.0) -> float:
    """P(X <= k) for X ~ Binomial(n, p); stops once the sum is above enough."""
    if k >= n:
        return 1.0
    total, log_p, log_q = 0.0, math.log(p), math.log1p(-p)
    for i in range(k + 1):
        total += math.exp(math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * log_p + (n - i) * log_q)
        if total > enough:
            break
    return min(total, 1.0)


def fewest_labels(risk: float, level: float) -> int:
    """With fewer good labels not even zero false rejections prove anything."""
    return math.ceil(math.log(level) / math.log1p(-risk))


def strata_apart(sizes: list[int], risk: float, error: float) -> int:
    """How many of the strata (good labels each, most first) have enough for tests of their own beside one pooled stratum."""
    own = 0
    while own < len(sizes) and sizes[own] >= fewest_labels(risk, error / (own + 2)):
        own += 1
    return own


def accepted_level(rejected: list[int], n: int, risk: float, level: float) -> int | None:
    """The last step of the path before the first whose number of false rejections doesn't prove the risk is kept."""
    last = None
    for i, k in enumerate(rejected):
        if n == 0 or binomial_at_most(k, n, risk, level) > level:
            break
        last = i
    return last


def accepted_cutoffs(features: DataFrame, labels: DataFrame, risk: float = RISK, error: float = ERROR, id_col: str = "doc_id") -> DataFrame:
    """cut_stratum, pooled and one cutoff per rule: a row for each stratum with tests of its own, and one (pooled) for all others.

    Strata without a row reject nothing. Only strata with enough good labels reach the driver, so their number is at most
    the labels divided by that.
    """
    spark = features.sparkSession
    good = labels.groupBy(F.col(id_col).alias("label_key")).agg(F.min("quality").alias("good")).filter("good = 1")
    held = features.filter(~base_failed()).join(good, F.col(id_col) == F.col("label_key"), "left_semi")
    fails = [reduce(Column.__or__, (rule_score(r) > grid[i] for r, grid in GRIDS.items())) for i in range(LEVELS)]
    steps = [F.sum(f.cast("long")).alias(f"k{i}") for i, f in enumerate(fails)]
    by_stratum = materialize(held.groupBy("stratum").agg(F.count(F.lit(1)).alias("n"), *steps), "quality-strata")
    few = fewest_labels(risk, error / 2)
    large = sorted(by_stratum.filter(F.col("n") >= few).collect(), key=lambda r: (-r["n"], r["stratum"] is not None, r["stratum"] or ""))
    own = large[: strata_apart([r["n"] for r in large], risk, error)]
    names = [r["stratum"] for r in own]
    apart = reduce(Column.__or__, (F.col("stratum").eqNullSafe(F.lit(x)) for x in names), F.lit(False))
    rest = by_stratum.filter(~apart).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), *(F.coalesce(F.sum(f"k{i}"), F.lit(0)).alias(f"k{i}") for i in range(LEVELS))).first()
    out = []
    for row, pooled in [*((r, False) for r in own), (rest, True)]:
        last = accepted_level([row[f"k{i}"] for i in range(LEVELS)], row["n"], risk, error / (len(own) + 1))
        if last is not None or not pooled:
            out.append((None if pooled else row["stratum"], pooled, *(None if last is None else GRIDS[r][last] for r in GRIDS)))
    return spark.createDataFrame(out, "cut_stratum string, pooled boolean, " + ", ".join(f"cut_{r} double" for r in GRIDS))


def judged(features: DataFrame, cutoffs: DataFrame) -> DataFrame:
    """features with base_failed and kept. cutoffs is bounded by the strata that have enough labels."""
    rest = cutoffs.filter("pooled").first()
    joined = features.join(F.broadcast(cutoffs.filter("not pooled")), F.col("stratum").eqNullSafe(F.col("cut_stratum")), "left")
    cut = lambda r: F.when(F.col("pooled").isNull(), F.lit(rest[f"cut_{r}"] if rest else None).cast("double")).otherwise(F.col(f"cut_{r}"))
    fails = reduce(Column.__or__, (F.coalesce(rule_score(r) > cut(r), F.lit(False)) for r in GRIDS))
    return joined.withColumns({"base_failed": base_failed(), "kept": ~base_failed() & ~fails})


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    features = materialize(quality_features(table(spark, sf_dir, "documents")), "quality-features")
    cutoffs = accepted_cutoffs(features, table(spark, sf_dir, "labels"))
    return judged(features, cutoffs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
