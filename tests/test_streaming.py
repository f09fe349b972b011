"""Streams against their batch twins on closed windows, late rows, duplicates, catalogue joins, index upkeep, online detection."""

from pyspark.sql import functions as F

from tuneloom.sources.tables import events
from tuneloom.streaming import metrics_stream as ms

from .conftest import SMALL


def _drain(df, name, tmp_path):
    q = df.writeStream.format("memory").queryName(name).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return df.sparkSession.table(name).collect(), q


def _files(spark, tmp_path, schema, *parts):
    """A folder with one file for each part; streams read one file a batch, oldest first."""
    import os

    for i, rows in enumerate(parts):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        for f in os.listdir(tmp_path / "in"):
            if f.endswith(".parquet") and not os.path.exists(tmp_path / f):
                (tmp_path / f).touch()
                os.utime(tmp_path / "in" / f, (1_700_000_000 + i, 1_700_000_000 + i))
    return str(tmp_path / "in")


EVENT = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def _event(i, ts):
    from datetime import datetime

    return (i, datetime.fromisoformat(ts), 1, "view", 1.0, "{}")


def test_sliding_windows_equal_batch(spark, tmp_path):
    got, _ = _drain(ms.tumbling(ms.ingest(spark, SMALL), "6 hours", slide="1 hour"), "sliding", tmp_path)
    whole = events(spark, SMALL).groupBy(F.window("ts", "6 hours", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    want = {(r["start"], r["event_type"]): r["n"] for r in whole.select(F.col("window.start").cast("timestamp").alias("start"), "event_type", "n").collect()}
    assert got and all(want[r["ts"], r["event_type"]] == r["n"] for r in got)


def test_sessions_equal_batch(spark, tmp_path):
    got, _ = _drain(ms.sessions(ms.ingest(spark, SMALL)), "sessions", tmp_path)
    whole = events(spark, SMALL).withColumn("ts", F.col("ts").cast("timestamp")).groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count(F.lit(1)).alias("n"))
    want = {(r["user_id"], r["start"]): r["n"] for r in whole.select("user_id", "session_window.start", "n").collect()}
    assert got and all(want[r["user_id"], r["start"]] == r["n"] for r in got) and len(want) - len(got) < 20


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    # rows are held against the watermark of the batch before, so one batch lies between the jump in time and the late row
    path = _files(spark, tmp_path, EVENT, *([_event(i, ts)] for i, ts in enumerate(("2024-01-01T10:10", "2024-01-01T20:00", "2024-01-01T20:05", "2024-01-01T10:20", "2024-01-02T10:00"))))
    got, q = _drain(ms.tumbling(ms.ingest(spark, path, "*.parquet", per_trigger=1)), "late", tmp_path)
    assert {r["ts"].hour: r["n"] for r in got} == {10: 1, 20: 2}
    assert sum(s.numRowsDroppedByWatermark for p in q.recentProgress for s in p.stateOperators) == 1


def test_duplicates_go_and_catalogue_joins(spark, tmp_path):
    path = _files(spark, tmp_path, EVENT, [_event(1, "2024-01-01T10:00"), _event(1, "2024-01-01T10:00")], [_event(1, "2024-01-01T10:01"), _event(2, "2024-01-01T10:02")])
    catalog = spark.createDataFrame([("view", "seen")], "event_type string, meaning string")
    got, _ = _drain(ms.with_catalog(ms.deduplicated(ms.ingest(spark, path, "*.parquet", per_trigger=1)), catalog, "event_type").select("event_id", "meaning"), "unique", tmp_path)
    assert sorted(map(tuple, got)) == [(1, "seen"), (2, "seen")]


def test_index_keeps_the_newest_row_of_each_key(spark, tmp_path):
    path = _files(spark, tmp_path, "doc_id long, text string", [(1, "old"), (2, "only")], [(1, "new")])
    stream = spark.readStream.schema("doc_id long, text string").option("maxFilesPerTrigger", 1).parquet(path)
    index = str(tmp_path / "index")
    sink = ms.upsert_index(index)
    stream.writeStream.foreachBatch(sink).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination(120)
    latest = {r["doc_id"]: r["text"] for r in ms.read_index(spark, index).collect()}
    assert latest[1] == "new" and latest[2] == "only"


def test_online_detection_finds_the_spike(spark, tmp_path):
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        rows = [("a", i, i % 24 + 0.1 * (i * 7 % 5) + (50.0 if i == 200 else 0.0)) for i in range(240)]
        path = _files(spark, tmp_path, "metric string, ts long, value double", rows[:120], rows[120:])
        stream = spark.readStream.schema("metric string, ts long, value double").option("maxFilesPerTrigger", 1).parquet(path)
        got, _ = _drain(ms.detect_online(stream), "online", tmp_path)
    finally:
        spark.conf.set(key, before)
    assert [(r["metric"], r["ts"]) for r in got] == [("a", 200)]
