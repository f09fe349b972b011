"""Cases that large tables bring: equal prompts, more questions than a broadcast may hold, many copies of one vector."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from tuneloom.operators import corpus, describe, prompt, reason, vindex
from tuneloom.plans import methods, workloads

from .conftest import SMALL


def test_equal_prompts_of_two_questions_keep_their_records(spark, tmp_path):
    turns = [(c, t, r, x) for c in range(3) for t, r, x in ((0, "user", "why so slow"), (1, "assistant", "set it"))]
    spark.createDataFrame(turns, "conv_id long, turn int, role string, text string").write.parquet(str(tmp_path / "conversations.parquet"))
    got = sorted(map(tuple, methods.reason_replay(spark, str(tmp_path)).collect()))
    assert got == [(0, False, ""), (1000, True, "autocommit"), (2000, True, "binlog_format,max_connections")]


def test_a_prompt_gets_one_answer(spark):
    prompts = prompt.build(spark.createDataFrame([(1, "a"), (2, "a")], "qid long, text string"))
    record = prompts.select("prompt_hash", F.format_string("[\"k%d\"]", "qid").alias("raw"))
    assert [r["raw"] for r in reason.Replay(record)(prompts).collect()] == ['["k1"]'] * 2


def test_more_questions_than_one_broadcast_holds(spark):
    q = spark.range(25_000).select(F.col("id").alias("qid"), F.array(F.lit(1.0), F.col("id") % 7 + 0.5).alias("vec"))
    desc = spark.createDataFrame([("a", [1.0, 0.0], ["x"], "A"), ("b", [0.0, 1.0], ["y"], "B")], "metric string, vec array<double>, knobs array<string>, text string")
    got = describe.select(q, desc, 1).groupBy("metric").count().collect()
    assert {r["metric"]: r["count"] for r in got} == {"a": sum(i % 7 == 0 for i in range(25_000)), "b": sum(i % 7 > 0 for i in range(25_000))}


def _brute(q, d, k, per_source=False):
    """(qid, source or None) -> [(distance, id)] from the definition, one pair at a time."""
    unit = lambda v: np.array(v, float) / np.linalg.norm(v)
    out = {}
    for qid, v in q:
        for i, s, x in d:
            if x is not None and np.any(x):
                out.setdefault((qid, s if per_source else None), []).append((round(float(np.linalg.norm(unit(v) - unit(x))), 6), i))
    return {key: sorted(v)[:k] for key, v in out.items()}


@pytest.mark.parametrize("per_source", [False, True])
def test_search_of_copies_nulls_and_ties(spark, per_source):
    rng = np.random.default_rng(2)
    vec = [rng.normal(size=6) for _ in range(150)] + [np.array([1.0, 2, 0, 0, 0, 0])] * 60 + [rng.integers(-1, 2, 6) for _ in range(60)] + [np.zeros(6)]
    d = [(i * 7 % 1009, "abc"[i % 3], [float(x) for x in v]) for i, v in enumerate(vec)] + [(2000, "a", None)]
    q = [(i, [float(x) for x in v]) for i, v in enumerate(vec[140:230]) if np.any(v)]
    docs = spark.createDataFrame([(i, s, v, [s + str(i)]) for i, s, v in d], "doc_id long, source string, vec array<double>, knobs array<string>").repartition(4)
    got = {}
    for r in vindex.topk_exact(spark.createDataFrame(q, "qid long, vec array<double>"), docs, 4, per_source=per_source).orderBy("rank").collect():
        assert r["knobs"] == [r["source"] + str(r["doc_id"])]
        got.setdefault((r["qid"], r["source"] if per_source else None), []).append((r["dist"], r["doc_id"]))
    assert got == _brute(q, d, 4, per_source)


def test_search_in_several_small_batches(spark):
    rng = np.random.default_rng(4)
    d = [(i, "a", [float(x) for x in v]) for i, v in enumerate(rng.normal(size=(400, 3)).round(1))]
    docs = spark.createDataFrame([(*r, ["k"]) for r in d], "doc_id long, source string, vec array<double>, knobs array<string>").coalesce(1)
    q = [(i, v) for i, _, v in d[:50]]
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 3)
    try:
        rows = vindex.topk_blocked(spark.createDataFrame(q, "qid long, vec array<double>"), docs, 5, block=20, cells=7).orderBy("rank").collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    got = {}
    for r in rows:
        got.setdefault((r["qid"], None), []).append((r["dist"], r["doc_id"]))
    assert got == _brute(q, d, 5)


def test_cells_and_buckets_write_no_pairs(spark):
    rng = np.random.default_rng(6)
    d = [(i, "a", [float(x) for x in v]) for i, v in enumerate(rng.normal(size=(300, 8)))] + [(400, "a", [0.0] * 8), (401, "a", None)]
    docs = spark.createDataFrame([(*r, ["k"]) for r in d], "doc_id long, source string, vec array<double>, knobs array<string>").repartition(3)
    q = [(i, v) for i, _, v in d[:40]]
    asked, want = spark.createDataFrame(q, "qid long, vec array<double>"), _brute(q, d, 3)
    ivf = vindex.IVF(nlist=5, nprobe=5).fit(docs)
    indexed = ivf.index(docs)
    one = vindex.IVF(nlist=5, nprobe=1)
    one.centers = ivf.centers
    cell = {r["doc_id"]: r["cell"] for r in indexed.collect()}
    near = {}
    for qid, v in q:
        near |= _brute([(qid, v)], [r for r in d if r[0] in cell and cell[r[0]] == cell[qid]], 3)
    for hits, found in ((ivf.search(asked, indexed, 3), want), (one.search(asked, indexed, 3), near), (vindex.lsh_search(asked, docs, 3, radius=1.0, bucket=4.0), {key: [x for x in v if x[0] < 1] for key, v in want.items()})):
        assert "Join" not in hits._jdf.queryExecution().optimizedPlan().toString()
        got = {}
        for r in hits.orderBy("rank").collect():
            got.setdefault((r["qid"], None), []).append((r["dist"], r["doc_id"]))
        assert got == found


def test_labels_in_place_equal_labels_by_join(spark):
    df = spark.createDataFrame([(1, "Alpha beta, GAMMA and delta"), (2, "nothing"), (3, None), (4, "beta beta")], "doc_id long, text string")
    catalog = spark.createDataFrame([("alpha", 3), ("beta", 2), ("gamma", 2), ("delta", 9)], "knob string, df long")
    want = {r["doc_id"]: r["knobs"] for r in corpus.label(df, "text", catalog, ["doc_id"], 3).collect()}
    got = corpus.label_rows(df, "text", catalog, 3)
    assert {r["doc_id"]: r["knobs"] for r in got.collect()} == want == {1: ["alpha", "beta", "gamma"], 4: ["beta"]}
    assert "Exchange" not in got._jdf.queryExecution().executedPlan().toString()


def test_corpus_is_read_once(spark):
    questions, docs = methods.main_corpus(spark, SMALL)
    for df in (questions, docs):
        assert "Project" not in df._jdf.queryExecution().optimizedPlan().toString() and df.inputFiles()


def test_expert_summary_reads_a_table(spark):
    df = workloads.expert_summary(spark, SMALL)
    assert [f.rsplit("/", 1)[1] for f in df.inputFiles()] == ["orders.parquet"] and df.count() > 10
