"""Parts of the whole method that SQL does not show."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from tuneloom.operators import align, augment, baselines, corpus, encoders, metrics, reason, telemetry, vindex
from tuneloom.plans import fixtures


@pytest.fixture(scope="module")
def two_sources(spark):
    """Manuals are questions turned round; a knob is a direction."""
    rng = np.random.default_rng(3)
    turn, _ = np.linalg.qr(rng.normal(size=(8, 8)))
    rows = []
    for i in range(48):
        k = i % 4
        v = np.eye(8)[k] + 0.1 * rng.normal(size=8)
        rows += [(i, "question", v.tolist(), [f"k{k}"]), (1000 + i, "manual", (v @ turn).tolist(), [f"k{k}"])]
    return spark.createDataFrame(rows, "doc_id long, source string, vec array<double>, knobs array<string>")


def test_built_pairs_feed_the_trainer(two_sources):
    questions = two_sources.filter("source = 'question' and doc_id < 20").select(F.col("doc_id").alias("qid"), "vec", "knobs")
    docs = two_sources.filter("not (source = 'question' and doc_id < 20)")
    heads, losses = align.train(questions, docs, 8, most=60, epochs=4)
    assert [p for _, p, _ in losses] == ["mm"] * 4 + ["qm"] * 4 + ["qq"] * 4
    pairs = align.build_pairs(align.anchors(two_sources, "question", 40).unionByName(align.anchors(two_sources, "manual", 40)), two_sources)
    seen = pairs.groupBy("pair_type", "q_source", "pos_source", "neg_source").count().collect()
    assert {(r[0], r[1], r[2], r[3]) for r in seen} <= {(t, a, b, c) for t, (a, b, c) in align.TYPES.items()} and len(seen) == 3


def test_untrained_heads_and_null_vectors(spark):
    df = spark.createDataFrame([(1, "question", [3.0, 4.0]), (2, "manual", None), (3, "other", [1.0, 0.0])], "id long, source string, vec array<double>")
    heads = {s: align.Head(2, 4, 1) for s in ("question", "manual")}
    got = {r["id"]: r["vec"] for r in align.apply(df, heads).collect()}
    assert np.allclose(got[1], [0.6, 0.8]) and got[2] is None and got[3] == [1.0, 0.0]


def test_users_generator(spark):
    gen = augment.CallableGenerator(lambda asks: [a.upper() for a in asks], fixtures.FUNCTIONS, fixtures.ISSUES, fixtures.BEHAVIOURS)
    knobs = fixtures.knobs(spark).withColumn("dbms", F.lit("x")).filter(F.col("knob") == "autocommit")
    chain, questions = augment.logic_chain(knobs, gen)
    assert chain.count() == questions.count() == 4 and all(r["text"].startswith("WRITE A USER'S QUESTION") for r in questions.collect())
    assert augment.cot(knobs, gen, 3).count() == augment.direct(knobs, gen, 3).count() == 3


def test_completions_are_asked_once(spark, tmp_path):
    log = tmp_path / "asked"
    log.mkdir()

    def ask(texts):
        import uuid

        (log / uuid.uuid4().hex).write_text("\n".join(texts))
        return ['["autocommit"]'] * len(texts)

    prompts = spark.createDataFrame([(1, 1, "a", "h1"), (2, 1, "b", "h2"), (3, 1, "a", "h1")], "qid long, phase int, text string, prompt_hash string")
    ask_all = reason.External(ask, str(tmp_path / "cache"))
    assert ask_all(prompts.filter("qid = 1")).count() == 1 and ask_all(prompts).count() == 3
    lines = [x for f in log.iterdir() for x in f.read_text().split("\n") if x]
    assert sorted(lines) == ["a", "b"]


def test_decomposed_answers(spark):
    catalog = spark.createDataFrame([("alpha", 3), ("beta", 2), ("gamma", 1)], "knob string, df long")
    q = spark.createDataFrame([(1, "the alpha is slow. the beta is not! gamma too"), (2, "nothing known")], "qid long, text string")
    got = {r["qid"]: (r["ok"], r["knobs"]) for r in baselines.llm_decomposed(q, reason.MentionVote(catalog)).collect()}
    assert got == {1: (True, ["alpha", "beta", "gamma"]), 2: (True, [])}


def test_values_behind_knobs(spark):
    df = spark.createDataFrame([(1, "set alpha four and beta", ["alpha", "beta"]), (2, None, ["alpha"])], "id long, text string, knobs array<string>")
    got = {r["id"]: r["config"] for r in corpus.following_values(df, "text").collect()}
    assert got[1] == {"alpha": "four"} and not got[2]


def test_recall_of_rare_and_frequent_knobs(spark):
    history = spark.createDataFrame([("a",)] * 5 + [("b",)] * 3 + [("c",)], "knob string")
    hits = spark.createDataFrame([(1, 1, ["a"]), (1, 4, ["c"])], "qid long, rank int, knobs array<string>")
    truth = spark.createDataFrame([(1, "a"), (1, "b"), (1, "c")], "qid long, knob string")
    got = {(r["bucket"], r["k"]): r["recall"] for r in metrics.recall_by_frequency(hits, truth, history).collect()}
    assert got[1, 1] == 1.0 and got[2, 10] == 0.0 and (got[3, 3], got[3, 5]) == (0.0, 1.0)


def test_blocks_of_queries_and_ties(spark):
    rng = np.random.default_rng(5)
    rows = [(i, "question", v, ["k"]) for i, v in enumerate([[float(x) for x in rng.integers(-1, 2, 3)] for _ in range(80)])]
    docs = spark.createDataFrame(rows, "doc_id long, source string, vec array<double>, knobs array<string>").repartition(3)
    q = docs.filter("doc_id % 3 = 0").select(F.col("doc_id").alias("qid"), "vec").filter(F.expr("exists(vec, x -> x <> 0)"))
    want = sorted(map(tuple, vindex.topk_exact(q, docs, 4).select("qid", "rank", "doc_id").collect()))
    assert sorted(map(tuple, vindex.topk_blocked(q, docs, 4, block=7, cells=50).select("qid", "rank", "doc_id").collect())) == want


def test_span_of_a_dense_series(spark):
    p = spark.createDataFrame([("m", "2024-01-01 00:00:00", 1.0), ("m", "2024-01-01 03:00:00", 4.0), ("n", "2024-01-01 01:00:00", 2.0)], "metric string, ts string, value double").withColumn("ts", F.col("ts").cast("timestamp"))
    got = telemetry.densify(p, ["metric"], 3600, fill="linear").filter("metric = 'm'").orderBy("ts").collect()
    assert [r["value"] for r in got] == [1.0, 2.0, 3.0, 4.0]
    assert telemetry.densify(p, ["metric"], 3600).count() == 8


def test_encoders_keep_missing_rows(spark):
    df = spark.createDataFrame([(1, "a b"), (2, None)], "doc_id long, text string")
    got = {r["doc_id"]: r["vec"] for r in encoders.CallableEncoder(lambda t: np.ones((len(t), 2))).encode(df).collect()}
    assert got == {1: [1.0, 1.0], 2: None}
    table = spark.createDataFrame([(1, [0.5])], "id long, v array<float>")
    assert {r["doc_id"]: r["vec"] for r in encoders.TableEncoder(table, "id", "v").encode(df).collect()} == {1: [0.5], 2: None}


def test_balance_keeps_the_nearest_of_the_larger_side(spark):
    rng = np.random.default_rng(8)
    sides = []
    for n in (300, 170):
        rows = [(str(rng.integers(3)), int(q), int(d), float(rng.choice([0.25, 0.2501, 0.2502, round(rng.random() * 2, 6)]))) for q, d in zip(rng.permutation(n), rng.permutation(n))]
        sides.append([(k, q, d, x) for k, q, d, x in rows if n == 300 or k != "2"] + [("only" + str(n), 1, 1, 0.5)])
    frames = [spark.createDataFrame(s, "kind string, qid long, doc_id long, dist double") for s in sides]
    got = [sorted(tuple(r) for r in f.select("kind", "qid", "doc_id", "dist").collect()) for f in align.balance(*frames, ["kind"])]
    want = [[], []]
    for k in {r[0] for r in sides[0]} & {r[0] for r in sides[1]}:
        own = [sorted((x, q, d) for kind, q, d, x in s if kind == k) for s in sides]
        m = min(map(len, own))
        for w, o in zip(want, own):
            w += [(k, q, d, x) for x, q, d in o[:m]]
    assert got == [sorted(w) for w in want] and len(got[0]) == len(got[1]) > 100
