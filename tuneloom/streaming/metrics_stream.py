"""Metric streams: ingest, windows, online detection, index upkeep."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructType

from ..operators.esd import esd_steps

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def ingest(spark: SparkSession, path: str, glob: str = "events.parquet", per_trigger: int | None = None) -> DataFrame:
    """events as a stream with a zoned timestamp; watermarks refuse naive ones."""
    r = spark.readStream.schema(EVENTS).option("pathGlobFilter", glob)
    if per_trigger:
        r = r.option("maxFilesPerTrigger", per_trigger)
    return r.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(stream: DataFrame, width: str = "1 hour", delay: str = "1 hour", slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return stream.withWatermark("ts", delay).groupBy(w, "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("value")).select(F.col("window.start").alias("ts"), "event_type", "n", "value")


def sessions(stream: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    g = stream.withWatermark("ts", delay).groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n"))
    return g.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def deduplicated(stream: DataFrame, key: str = "event_id", delay: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def with_catalog(stream: DataFrame, catalog: DataFrame, key: str) -> DataFrame:
    """Stream-static join; the catalogue is read anew for each micro-batch."""
    return stream.join(catalog, key, "left")


def upsert_index(path: str, key: str = "doc_id"):
    """A foreachBatch sink: a batch becomes a folder of its own, written once; read the newest row of each key."""

    def write(batch: DataFrame, epoch: int) -> None:
        batch.withColumn("epoch", F.lit(epoch)).write.mode("overwrite").parquet(f"{path}/batch={epoch}")

    return write


def read_index(spark: SparkSession, path: str, key: str = "doc_id") -> DataFrame:
    df = spark.read.parquet(path)
    newest = df.groupBy(key).agg(F.max("batch").alias("batch"))
    return df.join(newest, [key, "batch"], "left_semi")


class Ring(StatefulProcessor):
    """Keeps the last `size` buckets of a metric and tells whether a new one stands out of those of its phase."""

    size, period, alpha = 240, 24, 0.05

    def init(self, handle: StatefulProcessorHandle) -> None:
        # types as objects: the worker that calls this has no session to parse DDL
        self.ring = handle.getValueState("ring", StructType().add("ts", ArrayType(LongType())).add("value", ArrayType(DoubleType())))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        state = self.ring.get() if self.ring.exists() else ([], [])
        ts, value = list(state[0]), list(state[1])
        out = []
        for pdf in rows:
            for t, v in sorted(zip(pdf["ts"].astype("int64"), pdf["value"])):
                ts.append(int(t))
                value.append(float(v))
                ts, value = ts[-self.size :], value[-self.size :]
                x = np.array(value)
                i = np.arange(len(x)) % self.period
                r = x - np.array([np.median(x[i == p]) for p in range(self.period)])[i] if len(x) >= 2 * self.period else None
                if r is not None:
                    hit = next((s for s in esd_steps(r, bound=1, alpha=self.alpha) if s[0] == len(x) - 1 and s[3]), None)
                    if hit:
                        out.append((key[0], int(t), float(v), float(hit[1])))
        self.ring.update((ts, value))
        if out:
            yield pd.DataFrame(out, columns=["metric", "ts", "value", "score"])

    def close(self) -> None:
        pass


def detect_online(points: DataFrame) -> DataFrame:
    """points: metric, ts (any integer time), value. State is bounded by Ring.size; needs the RocksDB state store."""
    return points.groupBy("metric").transformWithStateInPandas(Ring(), outputStructType="metric string, ts long, value double, score double", outputMode="Append", timeMode="None")
