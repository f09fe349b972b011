"""From anomalies to sentences, and the sentences nearest a question."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .vindex import topk_few


def normal_value(points: DataFrame, keys: list[str], q: float = 0.05, exact: bool = True) -> DataFrame:
    """keys + normal. The exact percentile keeps a count for each distinct value; approximate has a bounded error and memory."""
    p = F.percentile("value", F.lit(q)) if exact else F.percentile_approx("value", F.lit(q), F.lit(10_000))
    return points.groupBy(*keys).agg(p.alias("normal"))


def abnormal_value(anoms: DataFrame, keys: list[str]) -> DataFrame:
    """keys + abnormal, score: the value at the anomaly of largest score, the earliest of equals."""
    return anoms.groupBy(*keys).agg(F.max_by("value", F.struct(F.col("score"), -F.unix_micros("ts"))).alias("abnormal"), F.max("score").alias("score"))


def attach_knobs(desc: DataFrame, metric_knobs: DataFrame) -> DataFrame:
    """metric_knobs: metric, knob (a dictionary of some hundred rows). Metrics without an entry get an empty list."""
    lists = metric_knobs.groupBy("metric").agg(F.array_sort(F.collect_set("knob")).alias("knobs"))
    return desc.join(F.broadcast(lists), "metric", "left").withColumn("knobs", F.coalesce("knobs", F.array().cast("array<string>")))


def number(c) -> F.Column:
    """Two decimals, the same text in every engine."""
    return F.round(c, 2).cast("decimal(18,2)").cast("string")


def render(desc: DataFrame) -> DataFrame:
    """desc (metric, explanation, normal, abnormal, knobs) with its sentence in text."""
    head = F.concat(F.lit("Metric "), F.col("metric"), F.lit(" ("), F.col("explanation"), F.lit(") moved from its usual "), number(F.col("normal")), F.lit(" to "), number(F.col("abnormal")))
    tail = F.when(F.size("knobs") > 0, F.concat(F.lit("; related settings: "), F.concat_ws(", ", "knobs"))).otherwise(F.lit(""))
    return desc.withColumn("text", F.concat(head, tail, F.lit(".")))


def select(queries: DataFrame, desc: DataFrame, k: int = 3) -> DataFrame:
    """hits_telemetry (qid, rank, metric, dist, text). queries: qid, vec; desc: metric, vec, knobs, text."""
    ident = F.conv(F.substring(F.md5("metric"), 1, 15), 16, 10).cast("long").alias("doc_id")
    docs = desc.select(ident, F.lit("telemetry").alias("source"), "vec", "knobs")
    hits = topk_few(queries, docs, k)
    names = desc.select(ident, "metric", "text")
    return hits.join(names, "doc_id").select("qid", "rank", "metric", "dist", "text", "knobs")
