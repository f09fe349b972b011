"""Drivers of the comparative experiments. Results come from offline stand-ins; they are not accuracies of language models."""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import corpus, metrics, telemetry, vindex
from ..sources.tables import stored
from . import debugging


def _tag(df: DataFrame, **labels) -> DataFrame:
    for k, v in labels.items():
        df = df.withColumn(k, F.lit(v))
    return df


def _rows(answers: DataFrame) -> DataFrame:
    return answers.select("qid", F.explode("knobs").alias("knob"))


def overall(methods: dict[str, DataFrame], truth: DataFrame) -> DataFrame:
    """(method, questions, precision, recall, f1, success_rate). methods: name -> answers (qid, knobs).

    Answers are stored before they are scored, as each measure reads them."""
    parts = []
    for name, answers in methods.items():
        pred = stored(_rows(answers), "answers")
        scores = metrics.macro(metrics.prf(pred, truth)).crossJoin(metrics.success_rate(pred, truth).select("success_rate"))
        parts.append(_tag(scores, method=name))
    return reduce(DataFrame.unionByName, parts)


def retrieved(questions: DataFrame, docs: DataFrame, heads: dict | None, k: int, base: bool = True) -> dict[str, DataFrame]:
    """variant -> hits, stored. One search for each source serves question-only, manual-only and, ranked anew, no-train; one more
    serves the aligned encoder. base: with the variants that have no heads."""
    docs, out = docs.select("doc_id", "source", "vec", "knobs"), {}
    if base:
        near = stored(vindex.topk_exact(questions.select("qid", "vec"), docs, k, per_source=True, sources={"question", "manual"}), "hits")
        out = {"question-only": near.filter("source = 'question'"), "manual-only": near.filter("source = 'manual'"), "no-train": stored(vindex.ranked(near.drop("rank"), k), "hits")}
    if heads:
        q = debugging.align.apply(questions.select("qid", "vec").withColumn("source", F.lit("question")), heads).drop("source")
        out["aligned"] = stored(vindex.topk_exact(q, debugging.align.apply(docs, heads), k), "hits")
    return out


def recalls(hits: dict[str, DataFrame], truth: DataFrame, ks=(1, 3, 5, 10)) -> DataFrame:
    """(variant, k, recall)."""
    return reduce(DataFrame.unionByName, [_tag(metrics.doc_recall(h, truth, ks), variant=name) for name, h in hits.items()])


def representation(questions: DataFrame, docs: DataFrame, truth: DataFrame, heads: dict | None = None, ks=(1, 3, 5, 10)) -> DataFrame:
    """(variant, k, recall) of question-only, manual-only, no-train, and aligned retrieval."""
    return recalls(retrieved(questions, docs, heads, max(ks)), truth, ks)


def augmentation(fitted: dict[str, dict | None], questions: DataFrame, docs: DataFrame, truth: DataFrame, ks=(1, 3, 5, 10)) -> DataFrame:
    """(augmentation, variant, k, recall): the same retrieval with heads trained on differently augmented data."""
    parts = []
    for name, h in fitted.items():
        variant = "aligned" if h else "no-train"
        hits = retrieved(questions, docs, h, max(ks), base=not h)
        parts.append(_tag(recalls({variant: hits[variant]}, truth, ks), augmentation=name))
    return reduce(DataFrame.unionByName, parts)


def noise(questions: DataFrame, docs: DataFrame, truth: DataFrame, catalog: DataFrame, side: str, ratios=(0.1, 0.2, 0.3, 0.4, 0.5), **how) -> DataFrame:
    """(side, ratio, f1 ...): labels of one source corrupted, the truth never."""
    parts = []
    for r in ratios:
        hurt = corpus.corrupt(docs.filter(F.col("source") == side), "doc_id", "knobs", r, catalog).drop("noisy")
        answers = debugging.debug(questions, hurt.unionByName(docs.filter(F.col("source") != side)), sources=("questions", "manuals"), **how)
        parts.append(_tag(metrics.macro(metrics.prf(_rows(answers), truth)), side=side, ratio=r))
    return reduce(DataFrame.unionByName, parts)


def telemetry_ablation(questions: DataFrame, docs: DataFrame, desc: DataFrame, truth: DataFrame, kinds: DataFrame) -> DataFrame:
    """(method, kind, questions, success_rate) of documents only, telemetry only, and both."""
    flags = {"docs-only": ("questions", "manuals"), "telemetry-only": ("telemetry",), "full": debugging.SOURCES}
    return reduce(DataFrame.unionByName, [_tag(metrics.by_kind(_rows(debugging.debug(questions, docs, desc, sources=s)), truth, kinds), method=m) for m, s in flags.items()])


def runtime(stages: dict[str, Callable[[], DataFrame]], questions: int) -> list[tuple[str, float]]:
    """Mean seconds a question of each stage, each run to its end, and their total."""
    out = []
    for name, stage in stages.items():
        t = time.perf_counter()
        stage().write.format("noop").mode("overwrite").save()
        out.append((name, (time.perf_counter() - t) / max(1, questions)))
    return [*out, ("total", sum(s for _, s in out))]


def scalability(events: DataFrame, ts: str, value: str, keys: list[str], sizes, steps, start: str, stop: str) -> list[tuple[str, int, float]]:
    """(axis, amount, seconds): analysis of the first `amount` metrics, and of all at a step of `amount` seconds."""
    out = []
    for seconds in steps:
        t = time.perf_counter()
        debugging.esd.detect(debugging.stl.decompose_none(telemetry.bucket(events, ts, value, keys, seconds)), ["metric"]).write.format("noop").mode("overwrite").save()
        out.append(("interval", seconds, time.perf_counter() - t))
    points = telemetry.bucket(events, ts, value, keys, steps[0]).persist()
    for m in sizes:
        t = time.perf_counter()
        some = points.select("metric").distinct().orderBy("metric").limit(m)
        debugging.esd.detect(debugging.stl.decompose_none(points.join(F.broadcast(some), "metric")), ["metric"]).write.format("noop").mode("overwrite").save()
        out.append(("metrics", m, time.perf_counter() - t))
    points.unpersist()
    return out


def expert_table(results: DataFrame) -> DataFrame:
    """(strategy, expert, success, minutes)."""
    return results.groupBy("strategy", "expert").agg(F.round(F.avg(F.col("solved").cast("double")), 6).alias("success"), F.round(F.avg("minutes"), 6).alias("minutes"))
