"""A corpus pipeline: toxicity, near duplicates, private data, mixing, encoding.

Each stage takes (spark, docs, sf_dir), works on all its predecessor kept and is written as Parquet before the
next one reads it. All but the last return the columns of documents; the last returns the ids' digests.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from satchel.llm import bpe_codec, jaccard, mixing, pii, toxicity
from satchel.llm.common import materialize, relieve_driver, relieving_executors, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def relieved(stage: Stage) -> Stage:
    """Executors and the driver give back what the stages before left free, and then what planning and fitting this one did."""

    @wraps(stage)
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        relieve_driver(spark)
        with relieving_executors(spark):
            out = stage(spark, docs, sf_dir)
        relieve_driver(spark)
        return out

    return run_stage


@relieved
def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the model, fitted on the labels, doesn't call toxic."""
    machine = toxicity.train(docs, table(spark, sf_dir, "labels"))
    scored = toxicity.score(docs, machine, keep=COLUMNS)
    return scored.filter("predicted = 0").select(*COLUMNS)


@relieved
def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group of near duplicates."""
    return jaccard.one_of_each(docs).select(*COLUMNS)


@relieved
def redact_private_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, private spans replaced by their kind; n_chars follows the text."""
    out = pii.redact(docs)
    return out.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text").cast("long"))).select(*COLUMNS)


@relieved
def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it."""
    return mixing.mix_documents(docs).select(*COLUMNS)


@relieved
def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Per row: doc_id, n_tokens and digests of ids and decoded text."""
    return bpe_codec.encode_decode(docs)


STAGES: list[tuple[str, Stage]] = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("private_data", redact_private_data),
    ("mixing", mix_sources),
    ("encoding", encode),
]

#: Learned decisions and similarity groups have no SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
