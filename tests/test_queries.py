"""Registered queries against the SQL of the second engine, value for value."""

import pytest

import __spark_entry__ as entry

from .conftest import MIDDLE, SMALL

NAMES = [n for n in entry.oracle_sql() if not n.startswith("op") and n != "pipeline"]


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, duck, name):
    df = entry.queries()[name](spark, MIDDLE)
    columns = sorted(df.columns)
    got = sorted((tuple(r) for r in df.select(*columns).collect()), key=str)
    want = sorted(duck.execute("SELECT " + ", ".join(f'"{c}"' for c in columns) + f" FROM ({entry.oracle_sql()[name]})").fetchall(), key=str)
    assert got == want


def test_entry(spark):
    assert "is_anomaly" in entry.queries()["esd_anomalies"](spark, SMALL).columns


def test_stream_windows_equal_batch(spark, tmp_path):
    from pyspark.sql import functions as F

    from tuneloom.sources.tables import events
    from tuneloom.streaming import metrics_stream

    q = metrics_stream.tumbling(metrics_stream.ingest(spark, SMALL)).writeStream.format("memory").queryName("tumbling").option("checkpointLocation", str(tmp_path)).trigger(availableNow=True).start()
    q.awaitTermination(120)
    closed = {(r["ts"], r["event_type"]): r["n"] for r in spark.table("tumbling").collect()}
    batch = events(spark, SMALL).groupBy(F.date_trunc("hour", "ts").alias("ts"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    whole = {(r["ts"], r["event_type"]): r["n"] for r in batch.collect()}
    assert closed and all(whole[k] == n for k, n in closed.items()) and len(whole) - len(closed) < 20
