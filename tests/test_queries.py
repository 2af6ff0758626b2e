"""Registered queries against their SQL, streams against batches."""

from __future__ import annotations

import time

import pytest
from conftest import agrees
from pyspark.sql import functions as F

from satchel.functions.build import count_, package_of, sum_
from satchel.partition.quad import quad_partition
from satchel.plans.coefficients import with_tid
from satchel.sources.joins import join_tradeoff, table
from satchel.streaming.windows import LateRows, maintained_statistics, overfull, windowed_packages
from satchel.workloads import registry


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_sql(spark, sf, name):
    agrees(spark, sf, registry.queries()[name], registry.oracle_sql()[name])


def test_entry(spark, sf):
    import __spark_entry__ as e

    assert registry.flagship(spark, sf).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())


def test_stream_is_batch(spark, sf, tmp_path):
    events = table(spark, sf, "events")
    q = package_of(events).repeat(0).such_that(count_() == 3).maximize(sum_("value")).query
    last = events.agg(F.max("ts")).first()[0]
    batch = {r.window_start: r.objective for r in windowed_packages(events, q, "ts", "event_id").collect()}
    path = str(tmp_path / "events")
    events.repartition(1).write.parquet(path)
    stream = spark.readStream.schema(events.schema).parquet(path)
    out = windowed_packages(stream, package_of(stream).repeat(0).such_that(count_() == 3).maximize(sum_("value")).query, "ts", "event_id")
    job = out.writeStream.format("memory").queryName("windows").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    job.awaitTermination()
    got = {r.window_start: r.objective for r in spark.table("windows").collect()}
    assert got and all(batch[k] == v for k, v in got.items())
    assert len(got) >= len([k for k in batch if k < last]) - 3


def test_late_rows_are_counted(spark, tmp_path):
    path = tmp_path / "late"
    rows = lambda *hours: spark.createDataFrame([(i, h, 1.0) for i, h in enumerate(hours)], "event_id long, h int, value double").selectExpr("event_id", "timestamp'2024-01-01 00:00:00' + make_interval(0, 0, 0, 0, h) AS ts", "value").coalesce(1)
    rows(1, 2, 200).write.parquet(str(path))
    stream = spark.readStream.schema("event_id long, ts timestamp, value double").parquet(str(path))
    out = windowed_packages(stream, package_of(stream).repeat(0).such_that(count_() == 1).maximize(sum_("value")).query, "ts", "event_id")
    listener = LateRows()
    spark.streams.addListener(listener)
    try:
        for more in (None, (3, 201), (4, 30, 202)):
            if more:
                rows(*more).write.mode("append").parquet(str(path))
            job = out.writeStream.format("noop").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
            job.awaitTermination()
        end = time.monotonic() + 30
        while listener.dropped.get(str(job.id), 0) < 3 and time.monotonic() < end:
            time.sleep(0.2)
        assert listener.dropped[str(job.id)] == 3
    finally:
        spark.streams.removeListener(listener)


def test_join_modes_report_bytes(spark, sf):
    orders, customer = table(spark, sf, "orders"), table(spark, sf, "customer")
    on = orders.o_custkey == customer.c_custkey
    q = package_of(orders.join(customer, on)).repeat(0).such_that(count_() == 5).maximize(sum_("o_totalprice")).query
    size = {mode: n for mode, _, n, _ in join_tradeoff(orders, customer, on, ["o_orderkey", "c_custkey"], q)}
    assert size["materialized"] > size["ids"] > size["pipelined"] == 0


def test_maintained_groups(spark, sf):
    events = with_tid(table(spark, sf, "events").select("event_id", "user_id", "value"), ["event_id"])
    p = quad_partition(events, ["value"], 300)
    more = maintained_statistics(events, p)
    assert more.agg(F.sum("n")).first()[0] == events.count()
    assert overfull(more, p).count() > 0
