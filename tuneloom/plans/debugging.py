"""The whole method: retrieve, analyse, reason. Ablations are arguments."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import align, describe, esd, stl, vindex
from ..operators.reason import EvidenceVote, voted_values

SOURCES = ("questions", "manuals", "telemetry")


def encode(df: DataFrame, text: str = "text", dim: int = 64) -> DataFrame:
    return df.withColumn("vec", vindex.hashed_vector(F.col(text), dim))


def telemetry_sentences(points: DataFrame, metric_dictionary: DataFrame, period: int = 24, method: str = "stl", **how) -> DataFrame:
    """desc (metric, explanation, normal, abnormal, score, knobs, text) of the series with anomalies.

    points: metric, ts, value; metric_dictionary: metric, explanation, knob. The season of the regression method is one for the whole
    series: a season that may change from cycle to cycle takes a part of each spike over to the days around it, where its
    echo counts as an anomaly (planted series: precision 0.6 instead of 1.0)."""
    parts = {"classical": lambda: stl.decompose_classical(points, ["metric"], period), "stl": lambda: stl.decompose_stl(points, ["metric"], period, s_win="periodic"), "median": lambda: stl.decompose_median(points, ["metric"], period), "none": lambda: stl.decompose_none(points)}[method]()
    anoms = esd.detect(parts, ["metric"], **how).filter("is_anomaly")
    desc = describe.abnormal_value(anoms, ["metric"]).join(describe.normal_value(points, ["metric"]), "metric")
    words = metric_dictionary.select("metric", "explanation").distinct()
    desc = desc.join(F.broadcast(words), "metric", "left").withColumn("explanation", F.coalesce("explanation", F.lit("no explanation")))
    return describe.render(describe.attach_knobs(desc, metric_dictionary.select("metric", "knob")))


def debug(questions: DataFrame, docs: DataFrame, desc: DataFrame | None = None, k: int = 5, top: int = 3, sources=SOURCES, heads: dict | None = None, reasoner: EvidenceVote | None = None, per_source: bool = False) -> DataFrame:
    """answers (qid, knobs). questions: qid, vec; docs: doc_id, source (question / manual), vec, knobs; desc: metric, vec, knobs, text.

    sources: any of questions, manuals, telemetry (a source left out is not read); heads: aligned encoder, None is the base."""
    wanted = {s[:-1] for s in sources if s != "telemetry"}
    if heads:
        docs = align.apply(docs, heads)
        moved = align.apply(questions.withColumn("source", F.lit("question")), heads).drop("source")
    else:
        moved = questions
    search = vindex.topk_exact if per_source else vindex.topk_blocked
    how = {"per_source": True} if per_source else {}
    hits = search(moved.select("qid", "vec"), docs, k, sources=wanted, **how) if wanted else None
    metrics = describe.select(questions.select("qid", "vec"), desc, top) if desc is not None and "telemetry" in sources else None
    reasoner = reasoner or EvidenceVote()
    if hits is None and metrics is None:
        raise ValueError("no source is left")
    return reasoner.answer(hits if hits is not None else metrics, metrics if hits is not None else None)


def debug_values(questions: DataFrame, docs: DataFrame, carriers: DataFrame, desc: DataFrame | None = None, k: int = 5, sources=SOURCES, heads: dict | None = None, **how) -> DataFrame:
    """(qid, place, knob, value): the knobs of debug(), each with the value most of the retrieved documents give it, null without one.

    carriers: doc_id, source, config."""
    answers = debug(questions, docs, desc, k=k, sources=sources, heads=heads, **how)
    vote = answers.select("qid", F.posexplode("knobs").alias("place", "knob")).withColumn("place", F.col("place") + 1)
    q, d = questions, docs
    if heads:
        q, d = align.apply(questions.withColumn("source", F.lit("question")), heads).drop("source"), align.apply(docs, heads)
    hits = vindex.topk_blocked(q.select("qid", "vec"), d, k, sources={s[:-1] for s in sources if s != "telemetry"})
    values = voted_values(vote, hits.join(carriers, ["doc_id", "source"]).select("qid", "rank", "config"))
    return vote.join(values, ["qid", "knob"]).select("qid", "place", "knob", "value")


def fit(dbms: str, knobs: DataFrame, manuals: DataFrame, history: DataFrame, dim: int = 64) -> DataFrame:
    """Documents of one system ready for retrieval: a new system needs its knobs and manual, a history only if there is one."""
    both = manuals.select("doc_id", F.lit("manual").alias("source"), "text", "knobs").unionByName(history.select("doc_id", F.lit("question").alias("source"), "text", "knobs"))
    return encode(both.withColumn("dbms", F.lit(dbms)), dim=dim)
