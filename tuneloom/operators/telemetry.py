"""Metric series: buckets, gaps, scope, episodes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def floor_to(ts: Column, seconds: int) -> Column:
    return F.timestamp_seconds(F.floor(F.unix_micros(ts.cast("timestamp")) / (seconds * 1_000_000)) * seconds)


def bucket(events: DataFrame, ts: str, value: str, keys: list[str], seconds: int, aggs=("count", "sum", "avg", "max")) -> DataFrame:
    """(metric, ts, value): one series for each combination of keys and aggregate. One shuffle, combined before it."""
    make = {"count": F.count(F.col(value)).cast("double"), "sum": F.sum(value), "avg": F.avg(value), "max": F.max(value), "min": F.min(value)}
    wide = events.groupBy(*keys, floor_to(F.col(ts), seconds).alias("ts")).agg(*(make[a].alias(a) for a in aggs))
    stack = F.explode(F.array(*(F.struct(F.lit(a).alias("agg"), F.col(a).cast("double").alias("value")) for a in aggs)))
    return wide.select(*keys, "ts", stack.alias("s")).select(F.concat_ws(":", *(F.col(k).cast("string") for k in keys), "s.agg").alias("metric"), "ts", F.col("s.value").alias("value"))


def densify(points: DataFrame, keys: list[str], seconds: int, start: str | None = None, stop: str | None = None, fill: str = "zero") -> DataFrame:
    """Every step from start to stop (inclusive; by default the first and last of all points) for each series: fill zero, locf,
    linear or null."""
    span = points.agg(F.min("ts").alias("a"), F.max("ts").alias("b"))
    first = F.col("a") if start is None else F.lit(start).cast("timestamp")
    last = F.col("b") if stop is None else F.lit(stop).cast("timestamp")
    grid = points.select(*keys).distinct().crossJoin(F.broadcast(span)).select(*keys, F.explode(F.sequence(first, last, F.expr(f"interval {seconds} seconds"))).alias("ts"))  # span: one row
    df = grid.join(points, [*keys, "ts"], "left")
    if fill == "zero":
        return df.fillna(0.0, ["value"])
    back = Window.partitionBy(*keys).orderBy("ts").rowsBetween(Window.unboundedPreceding, 0)
    if fill == "locf":
        return df.withColumn("value", F.last("value", ignorenulls=True).over(back))
    if fill == "linear":
        ahead = Window.partitionBy(*keys).orderBy("ts").rowsBetween(0, Window.unboundedFollowing)
        known = F.when(F.col("value").isNotNull(), F.struct("ts", "value"))
        df = df.withColumn("a", F.last(known, ignorenulls=True).over(back)).withColumn("b", F.first(known, ignorenulls=True).over(ahead))
        t = lambda c: F.unix_micros(F.col(c)).cast("double")
        slope = (F.col("b.value") - F.col("a.value")) / F.nullif(t("b.ts") - t("a.ts"), F.lit(0.0))
        return df.withColumn("value", F.coalesce("value", F.col("a.value") + slope * (t("ts") - t("a.ts")))).drop("a", "b")
    return df


def scope(points: DataFrame, start=None, stop=None, **equal) -> DataFrame:
    """Plain filters on the raw columns, so that they reach the scan."""
    for column, v in equal.items():
        points = points.filter(F.col(column) == v)
    if start is not None:
        points = points.filter(F.col("ts") >= F.lit(start).cast("timestamp"))
    return points if stop is None else points.filter(F.col("ts") < F.lit(stop).cast("timestamp"))


def episodes(anoms: DataFrame, keys: list[str], max_gap: int) -> DataFrame:
    """Anomalous times no more than max_gap seconds apart form one episode."""
    w = Window.partitionBy(*keys).orderBy("ts")
    fresh = F.coalesce((F.unix_timestamp("ts") - F.unix_timestamp(F.lag("ts").over(w)) > max_gap).cast("int"), F.lit(1))
    return (
        anoms.withColumn("fresh", fresh).withColumn("episode", F.sum("fresh").over(w)).groupBy(*keys, "episode")
        .agg(F.min("ts").alias("start"), F.max("ts").alias("end"), F.count(F.lit(1)).alias("n"), F.max("score").alias("peak"))
    )
