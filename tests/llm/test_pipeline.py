"""Every stage of the pipeline against a plain version, on the given documents and on edge rows."""

import re
import zlib

import numpy as np
import pytest

import corpus_pipeline
from tests.conftest import SMALL
from tests.llm.test_operators import edit_search
from tests.llm.test_similar_pairs import brute
from tuneloom.llm import decontamination, quality_rules, secret_scan, stages
from tuneloom.llm.common import table

WORDS = " ".join(f"w{i}" for i in range(120))
SECRET = "24be64439e3e49cf46b2d7c90f3602a3d0b907ff"
COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def edge(spark):
    rows = [(1, WORDS), (2, WORDS), (2, WORDS), (3, WORDS.replace("w60", "x")), (None, WORDS), (None, None), (4, None), (5, ""), (6, "few words"), (7, "word " * 400), (8, " ".join(f"v{i}" for i in range(30_000))), (9, " ".join(f"u{i}" for i in range(80)) + f' token = "{SECRET}" end')]
    return spark.createDataFrame([(d, t, None, None, None) for d, t in rows], COLUMNS).repartition(3)


def rows_of(df):
    return sorted(((r["doc_id"], r["text"]) for r in df.collect()), key=str)


def test_names_and_order():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "simhash_dedup", "decontamination", "secret_scan", "packing"]
    assert corpus_pipeline.run is stages.run


@pytest.mark.parametrize("name,stage", stages.STAGES)
def test_edge_rows(spark, edge, name, stage):
    got = stage(spark, edge, SMALL)
    if name != "packing":
        assert got.columns == edge.columns
    every, out = rows_of(edge), rows_of(got) if name != "packing" else None
    if name == "quality_rules":
        assert out == sorted((r for r in every if quality_rules.judged_by_brute_force(r[1])["kept"]), key=str)
    elif name == "simhash_dedup":
        assert [r[0] for r in out] == sorted([1, 4, 6, 7, 8, 9, None, None], key=str)
    elif name == "decontamination":
        assert out == every
    elif name == "secret_scan":
        assert out == [(d, t and t.replace(SECRET, secret_scan.BLANK)) for d, t in every]
    else:
        assert sum(r["length"] for r in got.filter("doc_id is null").collect()) > 120 and got.filter("doc_id = 5").count() == 1
    assert stage(spark, edge.filter("doc_id < 0"), SMALL).collect() == []


def test_whole_run(spark):
    """The stages on all of the smallest documents, one after the other, against plain versions."""
    from tokenizers import Tokenizer

    docs = table(spark, SMALL, "documents")
    bench = [(r["item_id"], decontamination.normal(r["text"])) for r in table(spark, SMALL, "benchmark").collect()]
    plain = {r["doc_id"]: r["text"] for r in docs.collect()}
    plain = {d: t for d, t in plain.items() if quality_rules.judged_by_brute_force(t)["kept"]}
    groups = brute(list(plain.items()))
    plain = {d: t for d, t in plain.items() if groups[d] == d}

    def leaks(text):
        text = decontamination.normal(text)
        # one edit in twenty characters breaks three words in ten at most; the rest need no distance
        words = set(text.split())
        return any(sum(w in words for w in i.split()) > 0.6 * len(i.split()) and edit_search(i, text) <= int(0.05 * len(i)) for _, i in bench if i)

    plain = {d: t for d, t in plain.items() if not leaks(t)}
    plain = {d: re.sub(r'(?i)(token = ")[0-9a-f]{32,}', r"\1" + secret_scan.BLANK, t) for d, t in plain.items()}
    model = Tokenizer.from_file(stages.tokenizer_path())
    want = {d: model.encode(t, add_special_tokens=False).ids + [2] for d, t in plain.items()}
    got = {}
    for r in corpus_pipeline.run(spark, SMALL).collect():
        ids = want[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert r["ids_crc32"] == zlib.crc32(np.array(ids, "<u4").tobytes()) and r["doc_tokens"] == len(want[r["doc_id"]])
        got[r["doc_id"]] = got.get(r["doc_id"], 0) + len(ids)
    assert got == {d: len(i) for d, i in want.items()}
