"""Shared plumbing: scratch tables in the shared folder, worker imports, column hygiene."""

from __future__ import annotations

import atexit
import ctypes
import gc
import os
import re
import sys
import tempfile
import time
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from pathlib import Path

import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROOT = Path(__file__).resolve().parents[2]
#: White space that separates words, as a Java and Python character class body.
BLANKS = r"\x20\x09-\x0D"
_made: list[tuple[SparkSession, str]] = []


def scratch_dir(spark: SparkSession, name: str) -> str:
    """A fresh folder in spark.checkpoint.dir; a temporary one only where that is unset and the master is local."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = Path(tempfile.gettempdir(), "satchel-scratch").as_uri()
    path = f"{base.rstrip('/')}/satchel/{name}-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path


def forget(spark: SparkSession, path: str) -> None:
    """Removes a scratch folder through Hadoop's file system."""
    jvm, hadoop = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(hadoop).delete(at, True)


@atexit.register
def _forget_all() -> None:
    for spark, path in _made:
        try:
            if spark.sparkContext._jsc is not None:
                forget(spark, path)
        except Exception:  # noqa: BLE001  the session ended first
            return


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Writes df to the shared folder and reads it back: lineage ends there, and a lost executor costs no rerun."""
    spark = df.sparkSession
    path = scratch_dir(spark, name)
    df.write.parquet(path)
    relieve_driver(spark, RELIEF_SECONDS)
    if _relieving:
        relieve_executors(spark, EXECUTOR_RELIEF_SECONDS)
    return spark.read.schema(df.schema).parquet(path)


#: Rows of documents that a Python worker gets at once; texts can be long.
ARROW_ROWS, ARROW_BYTES = 2000, 8 << 20


def ship(spark: SparkSession) -> None:
    """Lets Python workers import this package when it is not on their path already, and keeps their batches small."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(ARROW_ROWS))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(ARROW_BYTES))
    root = str(ROOT)
    known = [os.path.abspath(p) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p]
    if root in known or os.getcwd() == root or any("site-packages" in p and root.startswith(p) for p in sys.path):
        return
    if root not in getattr(spark.sparkContext, "_satchel_shipped", ()):
        import zipfile

        target = Path(tempfile.mkdtemp(), "satchel_src.zip")
        with zipfile.ZipFile(target, "w") as z:
            for f in sorted((ROOT / "satchel").rglob("*.py")):
                z.write(f, f.relative_to(ROOT))
        spark.sparkContext.addPyFile(str(target))
        spark.sparkContext._satchel_shipped = (root,)


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """For mapInArrow: when a task ends, its worker gives the memory back that it no longer uses, as workers live on."""

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        give_back()

    return wrapped


def give_back() -> None:
    """Free memory goes from this process to the system."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    _trim()


def _trim() -> None:
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        return


#: Between two reliefs of the driver while tables are written one after the other.
RELIEF_SECONDS = 2.0
_relieved = float("-inf")


def relieve_driver(spark: SparkSession, at_least: float = 0.0) -> str:
    """Free memory of the driver goes to the system, unless that was done within at_least seconds. Returns what the JVM says.

    The JVM has hundreds of threads after a few dozen joins, broadcasts and shuffles. Each allocates natively from an arena
    that keeps what is freed, and a full heap isn't shrunk before a collection; both add up over a session of many jobs.
    """
    global _relieved
    if time.monotonic() - _relieved < at_least:
        return ""
    pa.default_memory_pool().release_unused()
    _trim()
    jvm, new = spark.sparkContext._jvm, spark.sparkContext._gateway.new_array
    jvm.System.gc()
    try:
        # The server's class is not public, so its method is found by the interface.
        lang, kinds, args = jvm.java.lang, new(jvm.java.lang.Class, 4), new(jvm.java.lang.Object, 4)
        for i, name in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
            kinds[i] = lang.Class.forName(name)
        args[0], args[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        invoke = lang.Class.forName("javax.management.MBeanServer").getMethod("invoke", kinds)
        said = str(invoke.invoke(lang.management.ManagementFactory.getPlatformMBeanServer(), args)).strip()
    except Py4JError:  # a JVM without this command
        said = ""
    _relieved = time.monotonic()
    return said


#: The same for executors, while a pipeline relieves them.
EXECUTOR_RELIEF_SECONDS = 10.0
_executors_relieved = float("-inf")
_relieving = 0


def relieve_executors(spark: SparkSession, at_least: float = 0.0) -> int:
    """Each executor's JVM collects its heap and gives what is free to the system, unless that was done within at_least seconds. Returns in how many tasks.

    A heap stays as large as the widest job of the session made it, while workers beside it keep their vocabularies and
    memos; only a full collection shrinks it. A task for each core reaches every executor that is idle. With a local
    master there is only the driver's JVM.
    """
    global _executors_relieved
    if time.monotonic() - _executors_relieved < at_least or re.match(r"local(\[|$)", spark.sparkContext.master):
        return 0
    n = spark.sparkContext.defaultParallelism
    done = len(spark.range(0, n, 1, n).select(F.expr("reflect('java.lang.System', 'gc')")).collect())
    _executors_relieved = time.monotonic()
    return done


@contextmanager
def relieving_executors(spark: SparkSession) -> Iterator[None]:
    """Executors give free memory back at the beginning, after tables that are written inside, and at the end."""
    global _relieving
    relieve_executors(spark)
    _relieving += 1
    try:
        yield
    finally:
        _relieving -= 1
    relieve_executors(spark)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
