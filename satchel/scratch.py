"""Scratch tables in the shared folder, so no step depends on one executor's disk."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_made: list[tuple[SparkSession, str]] = []


def scratch_path(spark: SparkSession, name: str) -> str:
    """A fresh folder in spark.checkpoint.dir; a temporary one only where that is unset and the master is local."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = Path(tempfile.gettempdir(), "satchel-scratch").as_uri()
    path = f"{base.rstrip('/')}/satchel/{name}-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path


@atexit.register
def _forget() -> None:
    for spark, path in _made:
        try:
            at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
        except Exception:  # noqa: BLE001  the session ended first
            return


def stored(df: DataFrame, name: str) -> DataFrame:
    """Writes df and reads it back."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Deletes a table that stored() returned and nothing reads any more."""
    spark = df.sparkSession
    paths = spark.sparkContext._jvm.org.apache.hadoop.fs
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        at = paths.Path(folder)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def stored_bytes(df: DataFrame) -> int:
    """Bytes of the files behind a table that stored() returned."""
    spark = df.sparkSession
    conf, paths = spark.sparkContext._jsc.hadoopConfiguration(), spark.sparkContext._jvm.org.apache.hadoop.fs
    folders = {f.rsplit("/", 1)[0] for f in df.inputFiles()}
    return sum(paths.Path(f).getFileSystem(conf).getContentSummary(paths.Path(f)).getLength() for f in folders)
