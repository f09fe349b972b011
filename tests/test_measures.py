import math

import numpy as np
import pytest

from tuneloom.functions.stats import esd_critical, t_quantile
from tuneloom.operators import align, corpus, esd, metrics, reason, stl, vindex
from tuneloom.plans import fixtures

HAND = [1, 2, 3, 2.5, 1.5, 2.2, 1.8, 2.7, 50, -30]


def test_critical_values():
    assert [round(esd_critical(54, k), 3) for k in range(1, 5)] == [3.159, 3.151, 3.144, 3.136]
    assert [round(esd_critical(10, k), 6) for k in range(1, 5)] == [2.289954, 2.215004, 2.126645, 2.019969]
    assert round(t_quantile(0.975, 10), 6) == 2.228139


def test_hand_series():
    steps = esd.esd_steps(HAND, bound=4)
    assert [HAND[p] for p, *_ in steps] == [50, -30, 1, 3]
    assert [round(s, 6) for _, s, *_ in steps] == [79.833333, 64.0, 2.2, 2.0]
    assert [a for *_, a in steps] == [True, True, True, False]
    assert sum(a for *_, a in esd.esd_steps(HAND, bound=4, scale=1.4826)) == 2


@pytest.mark.parametrize("direction", ["both", "high", "low"])
@pytest.mark.parametrize("how", [{}, {"spread": "mean_ad"}, {"center": "mean", "spread": "std"}, {"stop": "last_significant"}, {"zero": "inf"}])
def test_fast_equals_naive(direction, how):
    rng = np.random.default_rng(3)
    for n in (3, 8, 21, 60):
        for x in (rng.normal(size=n), rng.integers(0, 4, n).astype(float)):
            a, b = esd.esd_steps(x, bound=n // 2, direction=direction, **how), esd.esd_naive(x, bound=n // 2, direction=direction, **how)
            assert len(a) == len(b)
            for u, v in zip(a, b):
                assert u[3] == v[3] and (u[1] == v[1] or math.isclose(u[1], v[1], rel_tol=1e-6, abs_tol=1e-6))


def test_scale_and_shift_change_nothing():
    x = np.random.default_rng(1).normal(size=80)
    x[7] = 9
    assert [(p, a) for p, _, _, a in esd.esd_steps(x)] == [(p, a) for p, _, _, a in esd.esd_steps(x * 3 + 11)]


def test_stl_recovers_planted_parts():
    i = np.arange(240)
    s, t, r = stl.stl(10 * np.sin(2 * np.pi * i / 24) + 0.1 * i, 24)
    assert np.allclose(s + t + r, 10 * np.sin(2 * np.pi * i / 24) + 0.1 * i)
    assert np.abs(t[24:-24] - 0.1 * i[24:-24]).max() < 0.5 and np.abs(r[24:-24]).max() < 0.5
    with pytest.raises(ValueError):
        stl.stl([1.0] * 10, 24)
    with pytest.raises(ValueError):
        stl.stl([float("nan")] * 100, 24)


def test_loss_signs_and_gradients():
    q, near, far = np.array([[1.0, 0.0]]), np.array([[0.9, math.sqrt(0.19)]]), np.array([[-1.0, 0.0]])
    loss = lambda p, f: align.info_nce(q, p, near[None], 1.0, f)[0][0]
    assert loss(near, "attract") < loss(far, "attract") and loss(near, "standard") < loss(far, "standard")
    assert loss(near, "as_printed") > loss(far, "as_printed")
    rng = np.random.default_rng(0)
    a, p, n = rng.normal(size=(2, 3)), rng.normal(size=(2, 3)), rng.normal(size=(2, 4, 3))
    for form in ("attract", "standard"):
        _, g, _, _ = align.info_nce(a, p, n, 0.5, form)
        e = np.zeros_like(a)
        e[1, 2] = 1e-6
        num = (align.info_nce(a + e, p, n, 0.5, form)[0].sum() - align.info_nce(a - e, p, n, 0.5, form)[0].sum()) / 2e-6
        assert abs(num - g[1, 2]) < 1e-4


def test_prf_by_hand(spark):
    pred = spark.createDataFrame([(1, "a"), (1, "b"), (2, "a"), (3, "c"), (5, "x"), (5, "x")], "qid int, knob string")
    truth = spark.createDataFrame([(1, "a"), (1, "b"), (2, "b"), (3, "c"), (3, "d"), (4, "e")], "qid int, knob string")
    got = {r["qid"]: (r["precision"], r["recall"], round(r["f1"], 6)) for r in metrics.prf(pred, truth).collect()}
    assert got == {1: (1, 1, 1), 2: (0, 0, 0), 3: (1, 0.5, 0.666667), 4: (0, 0, 0), 5: (0, 0, 0)}
    m = metrics.macro(metrics.prf(pred, truth)).first()
    assert (m["questions"], m["without_truth"], m["f1"]) == (4, 1, 0.416667)


def test_recall_is_monotone(spark):
    hits = spark.createDataFrame([(1, 1, ["x"]), (1, 2, ["a"]), (1, 4, ["b"])], "qid int, rank int, knobs array<string>")
    truth = spark.createDataFrame([(1, "a"), (1, "b")], "qid int, knob string")
    assert [(r["k"], r["recall"]) for r in metrics.doc_recall(hits, truth).orderBy("k").collect()] == [(1, 0.0), (3, 0.5), (5, 1.0), (10, 1.0)]


def test_full_probe_equals_exact(spark):
    rng = np.random.default_rng(2)
    docs = spark.createDataFrame([(i, "question", [float(x) for x in rng.normal(size=6)], ["k"]) for i in range(60)] + [(99, "question", [0.0] * 6, ["k"])], "doc_id long, source string, vec array<double>, knobs array<string>")
    q = docs.filter("doc_id < 5").select(docs.doc_id.alias("qid"), "vec")
    exact = sorted(map(tuple, vindex.topk_exact(q, docs, 4).select("qid", "rank", "doc_id").collect()))
    ivf = vindex.IVF(nlist=4, nprobe=4).fit(docs)
    assert sorted(map(tuple, ivf.search(q, ivf.index(docs), 4).select("qid", "rank", "doc_id").collect())) == exact
    assert sorted(map(tuple, vindex.topk_blocked(q, docs, 4).select("qid", "rank", "doc_id").collect())) == exact
    assert 99 not in {d for *_, d in exact}


def test_settings_and_answers(spark):
    texts = spark.createDataFrame([(1, "Use autocommit = 0 and set sort_buffer_size to 4M."), (2, "turn off unique_checks please"), (3, "warp = 9"), (4, None)], "doc_id long, text string")
    got = {r["doc_id"]: r["config"] for r in corpus.extract_config(texts, "text", fixtures.knobs(spark), ["doc_id"]).collect()}
    assert got == {1: {"autocommit": "0", "sort_buffer_size": "4M"}, 2: {"unique_checks": "off"}}
    parsed = {r["qid"]: r["ok"] for r in reason.parse(fixtures.answers(spark).filter("kind = 'dict'")).collect()}
    assert parsed == {2: True, 3: False, 4: False, 5: False, 6: True, 7: True, 8: False, 9: True}


def test_noise_is_nested(spark):
    docs = spark.createDataFrame([(i, ["a"]) for i in range(300)], "doc_id long, knobs array<string>")
    names = spark.createDataFrame([("a",), ("b",), ("c",)], "knob string")
    sets = [{r["doc_id"] for r in corpus.corrupt(docs, "doc_id", "knobs", r, names).filter("noisy").collect()} for r in (0.1, 0.3, 0.5)]
    assert sets[0] < sets[1] < sets[2] and abs(len(sets[2]) - 150) < 40
    assert all(r["knobs"] != ["a"] for r in corpus.corrupt(docs, "doc_id", "knobs", 0.5, names).filter("noisy").collect())
