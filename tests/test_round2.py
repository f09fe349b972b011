"""What round 2's findings asked for: prompts read once, tables read, long jobs in few passes."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from tuneloom.operators import align, baselines, esd, reason, vindex
from tuneloom.plans import experiments, methods, relational, workloads
from tuneloom.sources import tables

from .conftest import SMALL

QUERIES, READ = workloads.QUERIES | relational.QUERIES, tables.read


def test_a_long_prompt_is_read_once(spark):
    catalog = spark.createDataFrame([("alpha", 3), ("beta", 2), ("gamma", 1)], "knob string, df long")
    text = "Beta ten " + "other " * 100_000 + "gamma nine alpha, beta gamma"
    rows = [(1, 1, text, "a"), (1, 0, text, "b"), (2, 1, None, "c"), (3, 0, "", "d")]
    answers = reason.MentionVote(catalog, 2)(spark.createDataFrame(rows, "qid long, phase int, text string, prompt_hash string"))
    plan = answers._jdf.queryExecution().executedPlan().toString()
    assert "Generate" not in plan and "Exchange" not in plan
    got = {r["prompt_hash"]: r["raw"] for r in answers.collect()}
    assert got == {"a": '["gamma","beta"]', "b": '{"beta":"ten","gamma":"nine"}', "c": "[]", "d": "{}"}


def test_many_series_are_tested_together(spark):
    rng = np.random.default_rng(5)
    rows = []
    for m in range(400):
        n = int(rng.choice([1, 2, 3, 5, 13, 40, 99, 100, 260]))
        x = rng.normal(size=n) if m % 3 else rng.integers(0, 3, n).astype(float)
        rows += [(f"m{m}", i, float(v), None if i % 7 == 6 else float(v)) for i, v in enumerate(x)]
    points = spark.createDataFrame(rows, "metric string, s long, value double, resid double").select("metric", F.timestamp_seconds("s").alias("ts"), "value", "resid")
    series = {}
    for m, i, _, r in rows:
        if r is not None:
            series.setdefault(m, []).append((i, r))
    for how in ({}, {"direction": "high"}, {"direction": "low", "stop": "last"}, {"scale": 1.4826}, {"zero": "inf"}, {"center": "mean", "spread": "std"}):
        found = esd.detect(points, ["metric"], **how)
        assert "FlatMapGroupsInPandas" not in found._jdf.queryExecution().executedPlan().toString()
        got = sorted((r["metric"], r["k"], int(r["ts"].timestamp()), r["value"], r["resid"], r["score"], r["lambda"], r["direction"], r["is_anomaly"]) for r in found.collect())
        want = []
        for m, pairs in series.items():
            mid = float(np.median([r for _, r in pairs]))
            for k, (p, c, lam, a) in enumerate(esd.esd_steps([r for _, r in pairs], **how), 1):
                want.append((m, k, pairs[p][0], pairs[p][1], pairs[p][1], c, lam, "high" if pairs[p][1] >= mid else "low", a))
        assert got == sorted(want)


def test_a_long_series_is_refused(spark):
    points = spark.range(100).select(F.lit("m").alias("metric"), F.timestamp_seconds("id").alias("ts"), F.rand(1).alias("value")).withColumn("resid", F.col("value"))
    with pytest.raises(Exception, match="cut it by time"):
        esd.detect(points, ["metric"], max_points=99).collect()
    assert esd.detect(points, ["metric"], max_points=100).count() == 2


@pytest.mark.parametrize("name, table", [("answer_parse", "events"), ("answer_validate", "events"), ("failure_rates", "events"), ("metric_scrape", "events"), ("augment_chain", "part"), ("augment_cot", "part"), ("augment_direct", "part"), ("augment_diversity", "part")])
def test_a_given_table_is_read(spark, monkeypatch, name, table):
    seen = []
    for module in (workloads, relational, tables):
        monkeypatch.setattr(module, "read", lambda s, d, t, *a, **k: seen.append(t) or READ(s, d, t, *a, **k))
    assert QUERIES[name](spark, SMALL).count() > 0
    assert seen == [table] * len(seen) and seen


def test_answers_of_every_form(spark):
    by = {r["f"]: (r["n"], r["good"]) for r in workloads.answer_parse(spark, SMALL).groupBy((F.col("qid") % 9).alias("f")).agg(F.count("*").alias("n"), F.sum(F.col("ok").cast("int")).alias("good")).collect()}
    assert len(by) == 9 and all(good == (n if f in (0, 1, 5, 6, 8) else 0) for f, (n, good) in by.items())
    assert {r["status"] for r in workloads.answer_validate(spark, SMALL).select("status").distinct().collect()} == {"ok", "unknown", "outside"}


def test_each_source_is_searched_once(spark, monkeypatch):
    rng = np.random.default_rng(2)
    rows = [(i, s, [float(x) for x in rng.normal(size=8)], [f"k{i % 3}"]) for i in range(40) for s in ("question", "manual")]
    docs = spark.createDataFrame(rows, "doc_id long, source string, vec array<double>, knobs array<string>")
    calls, search = [], vindex.topk_exact
    count = lambda *a, **k: calls.append(k) or search(*a, **k)
    monkeypatch.setattr(align, "topk_exact", count)
    monkeypatch.setattr(align, "topk_blocked", lambda *a, **k: pytest.fail("a search of its own"))
    queries = align.anchors(docs, "question", 9).unionByName(align.anchors(docs, "manual", 9))
    pairs = align.build_pairs(queries, docs, top_m=10)
    assert len(calls) == 2 and {r["pair_type"] for r in pairs.select("pair_type").distinct().collect()} == {"qm", "qq", "mm"}
    assert "MapInArrow" not in pairs._jdf.queryExecution().executedPlan().toString()
    calls.clear()
    monkeypatch.setattr(vindex, "topk_exact", count)
    monkeypatch.setattr(vindex, "topk_blocked", lambda *a, **k: pytest.fail("a search of its own"))
    heads = {s: align.Head(8, 16, i) for i, s in enumerate(("question", "manual"))}
    asked = docs.filter("source = 'question' and doc_id < 7").select(F.col("doc_id").alias("qid"), "vec")
    hits = experiments.retrieved(asked, docs, heads, 5)
    assert set(hits) == {"question-only", "manual-only", "no-train", "aligned"} and len(calls) == 2
    for name, sources in (("question-only", {"question"}), ("manual-only", {"manual"}), ("no-train", None)):
        want = {(r["qid"], r["rank"], r["doc_id"], r["source"], r["dist"]) for r in search(asked, docs, 5, sources=sources).collect()}
        assert {(r["qid"], r["rank"], r["doc_id"], r["source"], r["dist"]) for r in hits[name].collect()} == want


def test_heads_move_rows_with_a_vector_and_a_head(spark):
    heads = {s: align.Head(2, 4, i) for i, s in enumerate(("question", "manual"))}
    for h in heads.values():
        h.w["b2"] = np.array([0.5, -0.25])
    rows = [(1, "question", [3.0, 4.0]), (2, "manual", None), (3, "other", [3.0, 4.0]), (4, None, [1.0, 0.0]), (5, "manual", [0.0, 2.0])]
    got = {r["id"]: r["vec"] for r in align.apply(spark.createDataFrame(rows, "id long, source string, vec array<double>").coalesce(1), heads).collect()}
    assert got[2] is None and got[3] == [3.0, 4.0] and got[4] == [1.0, 0.0]
    assert np.allclose(got[1], heads["question"](np.array([[0.6, 0.8]]))[0]) and np.allclose(got[5], heads["manual"](np.array([[0.0, 1.0]]))[0])


def test_synthetic_questions_read_no_documents_again(spark, monkeypatch):
    monkeypatch.setattr(workloads, "catalog", lambda *a: pytest.fail("the catalogue is built again"))
    catalog = spark.createDataFrame([("alpha", 3), ("beta", 2)], "knob string, df long")
    docs = spark.createDataFrame([(1, "manual", "alpha keeps slow pages here", ["alpha"]), (2, "manual", "beta holds more rows now", ["beta"]), (3, "question", "alpha", ["alpha"])], "doc_id long, source string, text string, knobs array<string>")
    for method, n in (("cot", 8), ("chain", 8)):
        made = methods.catalog_questions(catalog, docs, method, 2)
        assert made.count() == n and {tuple(r["knobs"]) for r in made.collect()} == {("alpha",), ("beta",)}


def _plain_steps(rows, names, dim, iters, rate, l2):
    x = np.array([[*v, 1.0] for v, _ in rows if v is not None])
    y = np.array([[float(k in (ks or [])) for k in names] for v, ks in rows if v is not None])
    w = np.zeros((len(names), dim + 1))
    for _ in range(iters):
        w = w - rate * ((1 / (1 + np.exp(-x @ w.T)) - y).T @ x / len(x) + l2 * w)
    return w


def test_nested_classifiers_are_those_of_each_part(spark):
    rng, names = np.random.default_rng(4), ["a", "b", "c"]
    made = lambda n: [([float(x) for x in rng.normal(size=5) * (rng.random(5) < 0.6)], [str(k) for k in rng.choice(["a", "b", "c", "d"], 2)]) for _ in range(n)]
    first, second = [*made(2500), (None, ["a"]), ([0.0] * 5, None), ([1.0, 0.0, 0.0, 0.0, 0.0], []), ([0.0, 2.0, 0.0, 0.0, 0.0], [None, "b", "b"])], made(70)
    frame = lambda rows: spark.createDataFrame(rows, "vec array<double>, knobs array<string>").repartition(3)
    how = {"iters": 12, "rate": 1.5, "l2": 1e-3}
    plain, more = baselines.plm_fit_nested([frame(first), frame(second)], names, 5, **how)
    for got, rows in ((plain, first), (more, first + second), (baselines.plm_fit(frame(first), names, 5, **how), first), (baselines.plm_fit_augmented(frame(first), frame(second), names, 5, **how), first + second)):
        assert np.allclose(got.weights, _plain_steps(rows, names, 5, **how), rtol=0, atol=1e-10)
    asked = spark.createDataFrame([(i, v) for i, (v, _) in enumerate(first)], "qid long, vec array<double>")
    found = {(r["model"], r["qid"], r["knob"]): r["p"] for r in baselines.plm_predict_all({"plain": plain, "more": more}, asked, 0.4).collect()}
    want = {(m, i, k): 1 / (1 + np.exp(-(np.dot(c.weights[j, :-1], v) + c.weights[j, -1]))) for m, c in (("plain", plain), ("more", more)) for i, (v, _) in enumerate(first) if v is not None for j, k in enumerate(names)}
    want = {at: round(p, 9) for at, p in want.items() if round(p, 9) > 0.4}
    assert found.keys() == want.keys() and len(want) > 1000 and all(abs(found[at] - p) < 2e-9 for at, p in want.items())
    with pytest.raises(Exception, match="5 places"):
        baselines.plm_fit(spark.createDataFrame([([1.0, 2.0], ["a"])], "vec array<double>, knobs array<string>"), names, 5)
    assert not baselines.plm_fit(frame(first).limit(0), names, 5).weights.any() and baselines.plm_fit(frame(first), [], 5).weights.shape == (0, 6)


def test_two_classifiers_take_their_steps_together(spark):
    spark.sparkContext.setJobGroup("plm", "plm_baselines")
    try:
        rows = methods.plm_baselines(spark, SMALL).collect()
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert [r["method"] for r in rows] == ["plm", "plm with augmentation"]
    assert 60 <= len(spark.sparkContext.statusTracker().getJobIdsForGroup("plm")) < 120  # 60 steps; two fits of their own take 120
