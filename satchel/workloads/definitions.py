"""The workloads on the given tables: W1-W7 on the pre-join, V1-V7 on documents, events and embeddings, X on small examples."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.build import Builder, avg_, count_, package_of, sum_
from ..lang.ast import PackageQuery
from ..plans.coefficients import with_tid
from ..scratch import stored
from ..sources.joins import LINE_KEY, non_null, prejoin, table

LINE_ATTRS = ["l_quantity", "l_tax", "l_extendedprice", "l_discount", "o_totalprice", "p_size", "s_acctbal", "p_retailprice"]
_kept: dict[tuple[str, str, str], DataFrame] = {}


def _once(spark: SparkSession, sf_dir: str, name: str, make: Callable[[], DataFrame]) -> DataFrame:
    """Relations that many queries share are written once a session."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _kept:
        _kept[key] = make()
    return _kept[key]


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pre-join where line attributes are known, narrowed to what the workloads use, with tid in key order."""

    def make() -> DataFrame:
        wide = non_null(prejoin(spark, sf_dir), [*LINE_KEY, *LINE_ATTRS])
        return with_tid(wide.select(*dict.fromkeys([*LINE_KEY, *LINE_ATTRS]), "l_returnflag", "l_linestatus"), LINE_KEY)

    return _once(spark, sf_dir, "lines", make)


def features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of every document's characters, words, lines, digits, capitals and marks, with its labels (0 where unlabelled)."""

    def make() -> DataFrame:
        docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
        n = lambda pattern: F.coalesce(F.regexp_count("text", F.lit(pattern)), F.lit(0)).cast("long")
        counted = docs.select("doc_id", "lang", "source", "n_chars", n("[^ \\t\\n\\r]+").alias("n_words"), (n("\\n") + 1).alias("n_lines"), n("[0-9]").alias("n_digits"), n("[A-Z]").alias("n_upper"), n("[.,;:!?]").alias("n_punct"))
        return with_tid(counted.join(labels, "doc_id", "left").na.fill(0, ["quality", "toxic"]), ["doc_id"])

    return _once(spark, sf_dir, "features", make)


def flat_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    def make() -> DataFrame:
        return with_tid(table(spark, sf_dir, "events").withColumn("k", F.get_json_object("props", "$.k").cast("int")).na.drop(subset=["k", "value"]), ["event_id"])

    return _once(spark, sf_dir, "events", make)


def flat_embeddings(spark: SparkSession, sf_dir: str, dims: int = 8) -> DataFrame:
    def make() -> DataFrame:
        e = [F.element_at("embedding", i + 1).cast("double").alias(f"e{i + 1}") for i in range(dims)]
        return with_tid(table(spark, sf_dir, "embeddings").select("vec_id", "label", *e), ["vec_id"])

    return _once(spark, sf_dir, f"embeddings{dims}", make)


def parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _once(spark, sf_dir, "parts", lambda: with_tid(table(spark, sf_dir, "part"), ["p_partkey"]))


def first_lines(spark: SparkSession, sf_dir: str, n: int = 100) -> DataFrame:
    """The first rows in key order, for baselines that can't take more."""
    return _once(spark, sf_dir, f"first{n}", lambda: stored(lines(spark, sf_dir).orderBy("tid").limit(n), "first-lines"))


@dataclass(frozen=True)
class Workload:
    name: str
    relation: Callable[[SparkSession, str], DataFrame]
    build: Callable[[Builder], Builder]
    attrs: tuple[str, ...]
    digits: int = 2
    size: tuple[int, int] = (10, 20)

    def query(self, df: DataFrame, repeat: int | None = 0) -> PackageQuery:
        return self.build(package_of(df).repeat(repeat)).query


def _band(expr: str, lo: float, hi: float):
    return sum_(expr).between(lo, hi)


WORKLOADS = {
    w.name: w
    for w in (
        Workload("w1", lines, lambda b: b.such_that((count_() == 20) & (sum_("l_quantity") <= 500) & _band("l_tax", 0.6, 1.0)).maximize(sum_("l_extendedprice")), ("l_quantity", "l_tax", "l_extendedprice"), size=(20, 20)),
        Workload("w2", lines, lambda b: b.such_that(count_().between(10, 15) & (sum_("p_size") >= 300) & (sum_("s_acctbal") >= 40000)).minimize(sum_("p_retailprice")), ("p_size", "s_acctbal", "p_retailprice"), size=(10, 15)),
        Workload("w3", lines, lambda b: b.such_that((count_() == 10) & (sum_("o_totalprice") <= 2.2e6) & _band("l_discount", 0.3, 0.6)).maximize(sum_("l_extendedprice * (1 - l_discount)")), ("o_totalprice", "l_discount", "l_extendedprice"), size=(10, 10)),
        Workload("w4", lines, lambda b: b.such_that(count_().between(10, 30) & _band("l_quantity", 300, 600)).minimize(sum_("o_totalprice")), ("l_quantity", "o_totalprice"), size=(10, 30)),
        Workload("w5", parts, lambda b: b.such_that(count_().between(5, 12) & _band("p_size", 150, 220)).maximize(sum_("p_retailprice")), ("p_size", "p_retailprice"), size=(5, 12)),
        Workload("w6", lines, lambda b: b.such_that((count_() == 25) & (sum_("l_quantity") <= 600) & avg_("l_discount").between(0.05, 0.07)).maximize(sum_("l_extendedprice * l_discount")), ("l_quantity", "l_discount", "l_extendedprice"), size=(25, 25)),
        Workload("w7", lines, lambda b: b.such_that(count_().between(12, 20) & (count_(where="l_returnflag = 'R'") >= count_(where="l_linestatus = 'F'")) & _band("l_quantity", 250, 420)).minimize(sum_("l_extendedprice")), ("l_quantity", "l_extendedprice"), size=(12, 20)),
        Workload("v1", features, lambda b: b.such_that((count_() == 10) & _band("n_chars", 15000, 30000)).maximize(sum_("n_words")), ("n_chars", "n_words"), 0, (10, 10)),
        Workload("v2", features, lambda b: b.such_that(count_().between(20, 40) & (sum_("n_words") <= 8000) & (sum_("n_digits") <= 300) & (sum_("n_lines") >= 100)).minimize(sum_("n_upper")), ("n_words", "n_digits", "n_lines", "n_upper"), 0, (20, 40)),
        Workload("v3", flat_events, lambda b: b.such_that((count_() == 50) & _band("value", 2499.95, 2500.05) & (count_(where="event_type = 'error'") <= count_(where="event_type = 'click'"))).maximize(sum_("k")), ("value", "k"), 4, (50, 50)),
        Workload("v4", features, lambda b: b.such_that(count_().between(15, 25) & (avg_("n_chars") <= 2500) & (count_(where="lang = 'fr'") >= 3)).maximize(sum_("n_punct")), ("n_chars", "n_punct"), 0, (15, 25)),
        Workload("v5", features, lambda b: b.such_that(count_().between(15, 25) & _band("n_chars", 30000, 60000) & (sum_("toxic") <= 1)).maximize(sum_("n_words")), ("n_chars", "toxic", "n_words"), 0, (15, 25)),
        Workload("v6", flat_embeddings, lambda b: b.such_that((count_() == 12) & _band("e1", -0.2, 0.2) & _band("e2", -0.2, 0.2) & _band("e3", -0.2, 0.2) & _band("e4", -0.2, 0.2)).maximize(sum_("e5")), ("e1", "e2", "e3", "e4", "e5"), 6, (12, 12)),
        Workload("v7", features, lambda b: b.repeat(0).such_that(sum_("n_chars") <= 50000).maximize(sum_("n_words")), ("n_chars", "n_words"), 0, (5, 20)),
    )
}


def meal(df: DataFrame, repeat: int | None = 0, condition=None) -> PackageQuery:
    """X1: three promotional parts of bounded size, as cheap as possible."""
    condition = condition if condition is not None else (count_() == 3) & sum_("p_size").between(60, 75)
    return package_of(df).repeat(repeat).where("p_type = 'PROMO'").such_that(condition).minimize(sum_("p_retailprice")).query
