"""One local session for all tests; inputs are the driver's tables where they exist."""

from __future__ import annotations

import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parents[1]
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = os.pathsep.join([str(ROOT), os.environ.get("PYTHONPATH", "")])

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from pyspark.sql import SparkSession

    shared = tmp_path_factory.mktemp("shared").as_uri()
    session = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", shared)
        .config("spark.driver.memory", "3g")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def sf() -> str:
    if not Path(SF).exists():
        pytest.skip("the driver's tables are absent")
    return SF


def duck(sf_dir: str):
    import duckdb

    c = duckdb.connect()
    for f in Path(sf_dir).glob("*.parquet"):
        source = f if f.is_file() else f / "*.parquet"
        c.execute(f"CREATE VIEW {f.stem} AS SELECT * FROM read_parquet('{source}')")
    return c


def rows(df) -> list[tuple]:
    return sorted(map(tuple, df.select(sorted(df.columns)).collect()), key=repr)


def agrees(spark, sf_dir: str, f, sql: str) -> None:
    df = f(spark, sf_dir)
    names = ", ".join(f'"{c}"' for c in sorted(df.columns))
    want = sorted(duck(sf_dir).sql(f"SELECT {names} FROM ({sql})").fetchall(), key=repr)
    assert rows(df) == want
