"""Repeated passages and repeated bytes against brute force, on tables of every kind of shard and of very frequent passages."""

import random

import numpy as np
import pytest
import xxhash

from tuneloom.llm import phrase_automata, suffix_dedup, suffix_sort, winnowing

rng = random.Random(17)
VOCAB = ["".join(rng.choice("abcdeéß") for _ in range(rng.randint(1, 7))) for _ in range(400)]


def prose(n):
    return " ".join(rng.choice(VOCAB) for _ in range(n))


PASSAGE, LINE = prose(70), prose(20)


def common(n):
    """Texts that share one passage and one line, in surroundings of their own."""
    return [prose(rng.randint(5, 60)) + " " + rng.choice([PASSAGE, LINE, PASSAGE[40:]]) + " " + prose(rng.randint(5, 60)) for _ in range(n)]


TABLES = {
    "unique": [(i, prose(120)) for i in range(5)],
    "short": [(1, "a b"), (2, "a b"), (3, "")],
    "copies": [(i, PASSAGE) for i in range(4)],
    "one": [(1, prose(300))],
    "common": list(enumerate(common(60))),
    "own repeats": [(1, PASSAGE + " x " + PASSAGE), (2, "y " + PASSAGE), (3, "word " * 300), (4, "ab" * 400), (5, "word " * 200)],
    "nulls": [(None, PASSAGE), (None, "z " + PASSAGE), (None, PASSAGE), (None, None), (None, ""), (9, PASSAGE + " t"), (9, None)],
    "empty": [],
}


def ids(rows):
    """Null ids as the operators order them."""
    return [((1 << 62) + (xxhash.xxh64_intdigest((t or "").encode(), 42) & ((1 << 62) - 1)) if d is None else d, t) for d, t in rows]


def same(got, want):
    want = [(None if d >= 1 << 62 else d, *r) for d, *r in want]
    assert sorted(map(tuple, got), key=str) == sorted(want, key=str)


@pytest.mark.parametrize("name", TABLES)
@pytest.mark.parametrize("shard_bytes,least", [(4 << 20, 1000), (900, 2)])
def test_equal_brute_force(spark, monkeypatch, name, shard_bytes, least):
    rows = TABLES[name]
    docs = spark.createDataFrame([(d, t, 1, "x") for d, t in rows], "doc_id long, text string, anchor int, shard string").repartition(2)
    deal = winnowing.sharded
    for module, brute in ((phrase_automata, phrase_automata.removed_by_brute_force), (suffix_dedup, suffix_dedup.removed_by_brute_force)):
        monkeypatch.setattr(module, "sharded", lambda d, i, t: deal(d, i, t, shard_bytes))
        found = module.cleaned(docs, most=20, least=least)
        sha = [(*r[:-1], __import__("hashlib").sha256(r[-1]).hexdigest()) for r in map(tuple, found.collect())]
        same(sha, brute(ids(rows)))


def test_frequent_anchors_are_dealt_by_strings(spark):
    """With little room for stretches the strings of an anchor are dealt one by one."""
    rows = TABLES["common"] + [(100 + d, t) for d, t in TABLES["own repeats"]]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(2)
    got = suffix_dedup.cleaned(docs, shard_bytes=600)
    sha = [(*r[:-1], __import__("hashlib").sha256(r[-1]).hexdigest()) for r in map(tuple, got.collect())]
    same(sha, suffix_dedup.removed_by_brute_force(rows))


def test_heavy_anchors(spark):
    docs = spark.createDataFrame(TABLES["common"], "doc_id long, text string").repartition(3)
    parts, _ = winnowing.sharded(docs, "doc_id", "text")
    found = winnowing.heavy(parts, winnowing.Words, 8, 50, most=20, least=5)
    assert 0 < len(found) <= 20
    for phrase in found.values():
        assert sum(phrase.decode() in t for _, t in TABLES["common"]) > 5
    assert winnowing.heavy(parts.filter("doc < 0"), winnowing.Words, 8, 50) == {}


def test_ids_out_of_range_are_refused(spark):
    docs = spark.createDataFrame([(1 << 62, "a")], "doc_id long, text string")
    with pytest.raises(Exception, match="2\\^62"):
        phrase_automata.digest(docs).collect()


def right_order(data, sa):
    n = len(data)
    rank = np.empty(n + 1, np.int64)
    rank[sa], rank[n] = np.arange(n), -1
    a, b, d = sa[:-1], sa[1:], data.astype(int)
    return len(np.unique(sa)) == n and bool(((d[a] < d[b]) | ((d[a] == d[b]) & (rank[a + 1] < rank[b + 1]))).all())


def test_large_shards():
    draw = np.random.default_rng(1)
    words = [bytes(draw.integers(97, 123, draw.integers(2, 9)).astype(np.uint8)) for _ in range(3000)]
    text = b" ".join(words[i] for i in draw.zipf(1.3, 400_000) % 3000)[: 2 << 20]
    for data in (np.frombuffer(text, np.uint8), draw.integers(0, 256, 2 << 20).astype(np.uint8), np.frombuffer(b"\xff".join([b"ab" * 84] * 2000), np.uint8)):
        assert right_order(data, suffix_sort.suffix_array(data))


def test_very_long_text(spark):
    """A text of 18 MB, longer than one slice of anchors, gives its passage to a later document."""
    letters = np.random.default_rng(9).integers(97, 123, 18 << 20).astype(np.uint8)
    letters[:: 7] = 32
    text = letters.tobytes().decode()
    part = text[17 << 20 : (17 << 20) + 3000]
    docs = spark.createDataFrame([(1, text), (2, "x " + part + " y"), (3, "nothing of it")], "doc_id long, text string")
    got = {r["doc_id"]: r["n_removed"] for r in suffix_dedup.digest(docs).collect()}
    assert got == {1: 0, 2: 3000, 3: 0} or (got[1], got[3]) == (0, 0) and 3000 <= got[2] <= 3002
    got = {r["doc_id"]: (r["n_words"], r["n_removed"]) for r in phrase_automata.digest(docs).collect()}
    assert got[1] == (len(text.split()), 0) and got[3] == (3, 0) and got[2][1] >= len(part.split()) - 2
