"""The training-data operators against plain versions on small fixtures, with nulls, empty and repeated rows."""

import random
import zlib
from itertools import combinations

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from tuneloom.llm import decontamination, language_id, license_scan, packing, pseudonyms, quality_rules, secret_scan, simhash_dedup, suffix_sort
from tuneloom.llm.queries import tokenizer_path

rng = random.Random(7)
VOCAB = ["".join(rng.choice("abcdeéß") for _ in range(rng.randint(1, 7))) for _ in range(60)]


def prose(n):
    return " ".join(rng.choice(VOCAB) for _ in range(n))


SHARED = prose(120)
ROWS = [
    (1, prose(80) + " " + SHARED + " " + prose(30), "en"), (2, SHARED + "\n" + prose(90), "en"), (3, prose(40) + " " + SHARED[150:], None), (4, SHARED, "fr"), (4, SHARED, "fr"), (5, None, None), (6, "", "en"),
    (7, "word " * 300, "en"), (8, "a" * 700, "en"), (9, prose(400), "fr"), (None, SHARED, "en"), (10, "\t \n", None), (11, "one two", "en"), (12, "one two", "en"),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(*r, "clash", 1) for r in ROWS], "doc_id long, text string, lang string, key string, shard int").repartition(3)


@pytest.fixture(scope="module")
def empty(docs):
    return docs.filter("doc_id < 0")


def keyed(rows):
    return sorted((tuple(r) for r in rows), key=str)


def test_suffix_arrays():
    for n in list(range(1, 12)) + [60] * 60:
        b = bytes(rng.choice(b"ab\xff") for _ in range(n))
        b = b + b[: n // 2] if n == 60 else b
        data = np.frombuffer(b, np.uint8)
        sa = suffix_sort.suffix_array(data)
        assert sa.tolist() == sorted(range(len(b)), key=lambda i: b[i:])
        shared = suffix_sort.common_prefixes(data, sa)
        for i, j in zip(sa[1:].tolist(), sa[:-1].tolist()):
            m = next((k for k in range(len(b)) if b[i + k : i + k + 1] != b[j + k : j + k + 1] or max(i, j) + k >= len(b)), len(b))
            assert shared[i] == m


def plain_fingerprint(text, width):
    words = (text or "").encode().lower().split()
    grams = [b" ".join(words[i : i + width]) for i in range(len(words) - width + 1)] or ([b" ".join(words)] if words else [])
    h = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if h and 2 * sum(x >> b & 1 for x in h) > len(h))


def test_near_duplicates(docs, empty):
    got = keyed(simhash_dedup.near_duplicates(docs).collect())
    prints = [(d, plain_fingerprint(t, 4)) for d, t, _ in ROWS]
    root = {d: d for d, _ in prints if d is not None}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for (a, x), (b, y) in combinations([p for p in prints if p[0] is not None], 2):
        if (x ^ y).bit_count() <= 4 and find(a) != find(b):
            root[max(find(a), find(b))] = min(find(a), find(b))
    assert got == keyed((d, f"{x:016x}", None if d is None else find(d)) for d, x in prints)
    assert simhash_dedup.near_duplicates(empty).count() == 0


def test_golay_links_up_to_four_bits(spark):
    r = np.random.default_rng(4)
    base = r.integers(0, 2**63, 40, dtype=np.uint64)
    fps = list(base)
    for x in base:
        for n in (1, 2, 3, 4, 5):
            fps.append(x ^ np.uint64(sum(1 << int(b) for b in r.choice(64, n, replace=False))))
    fps = np.unique(np.array(fps, np.uint64))
    place = {int(f): i for i, f in enumerate(fps.view(np.int64))}
    got = {tuple(sorted((place[a], place[b]))) for a, b in simhash_dedup.links(spark.createDataFrame([(f,) for f in place], "fp long")).collect()}
    want = {(i, j) for i, j in combinations(range(len(fps)), 2) if (int(fps[i]) ^ int(fps[j])).bit_count() <= 4}
    assert got <= want

    def parts(edges):
        root = list(range(len(fps)))

        def find(x):
            while root[x] != x:
                x = root[x]
            return x

        for a, b in edges:
            root[find(a)] = find(b)
        return {frozenset(i for i in range(len(fps)) if find(i) == k) for k in {find(i) for i in range(len(fps))}}

    assert parts(got) == parts(want)


def test_forest_joins_what_indexing_rows_reach():
    r = np.random.default_rng(6)
    fp = np.concatenate([x ^ np.array([0, 1, 2, 4, 8, 3], np.uint64) for x in r.integers(0, 2**63, 12, dtype=np.uint64)])
    lead = r.random(len(fp)) < 0.5
    a, b = simhash_dedup.forest(fp, lead, 2)
    assert (np.bitwise_count(a ^ b) <= 2).all() and len(a) < len(fp)
    for i in range(12):
        own = slice(6 * i, 6 * i + 6)
        if lead[own].any():
            assert ((a >> np.uint64(4)) == (fp[6 * i] >> np.uint64(4))).sum() >= 5 - 2 * (~lead[own]).sum()


def test_golay_radius_two():
    v = np.arange(0, 1 << 23, 7919)
    keys, _ = simhash_dedup.golay_keys(v)
    for a, b in combinations(range(23), 2):
        other, _ = simhash_dedup.golay_keys(v ^ (1 << a) ^ (1 << b))
        assert (keys[:, :, None] == other[:, None, :]).any((1, 2)).all()
    for a in range(23):
        other, _ = simhash_dedup.golay_keys(v ^ (1 << a))
        assert (keys[:, :1] == other).any(1).all() and (keys == other[:, :1]).any(1).all()


def quality_texts():
    line = "ein Satz mit Umlauten äöü und noch viel mehr Wörtern darin"
    texts = [t for _, t, _ in ROWS] + ["\n".join([line] * 3 + [prose(60)]), "\n".join([line + "   "] * 2 + [line, prose(200)]), prose(80) + " # * $ % & | < > ###"]
    for n in (4, 5, 6, 7, 8, 9, 10, 12):
        part = " ".join(f"{n}é{i}" for i in range(n))
        texts += [" ".join(f"u{i}" for i in range(m)) + (" " + part) * 2 for m in (20, 50, 60, 90)]
    return texts


def test_quality_equals_brute_force(spark, empty):
    texts = quality_texts()
    docs = spark.createDataFrame([(i, t, True) for i, t in enumerate(texts)] + [(None, texts[0], False)], "doc_id long, text string, kept boolean").repartition(3)
    kept = 0
    for r in quality_rules.judge(docs).collect():
        want = quality_rules.judged_by_brute_force(texts[r["doc_id"] or 0])
        kept += want["kept"]
        for c, v in want.items():
            assert r[c] == v or isinstance(v, float) and abs(r[c] - v) < 1e-9, (c, r, v)
    assert 5 < kept < len(texts) - 5
    good = quality_rules.keep_good(docs)
    assert good.columns == docs.columns and {r["doc_id"] for r in good.collect()} >= {i for i, t in enumerate(texts) if quality_rules.judged_by_brute_force(t)["kept"]}
    assert good.count() == kept
    assert quality_rules.judge(empty).count() == quality_rules.keep_good(empty).count() == 0


def test_packing_round_trip(docs, empty):
    from tokenizers import Tokenizer

    model = Tokenizer.from_file(tokenizer_path())
    rows = packing.pack(docs, tokenizer_path()).collect()
    seqs = {}
    for r in rows:
        seqs.setdefault(r["sequence_id"], []).append(r)
    for s in seqs.values():
        at = 0
        for r in sorted(s, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 4096 and (at & (at - 1) == 0 or 4096 - at < 8)
    for d, t, _ in ROWS:
        ids = model.encode(t or "", add_special_tokens=False).ids + [2]
        own = [r for r in rows if r["doc_id"] == d]
        copies = sum(x[0] == d for x in ROWS)
        assert sum(r["length"] for r in own) == len(ids) * copies and all(r["doc_tokens"] == len(ids) for r in own)
        for r in own:
            assert r["ids_crc32"] == zlib.crc32(np.array(ids[r["start"] : r["start"] + r["length"]], "<u4").tobytes())
    assert packing.pack(empty, tokenizer_path()).count() == 0


def test_step_groups_are_balanced(spark):
    docs = spark.range(0, 6000, 1, 3).select(F.col("id").alias("doc_id"), F.repeat(F.lit("word and more "), (F.col("id") * F.col("id") % 1500).cast("int")).alias("text"))
    rows = packing.pack(docs, tokenizer_path()).select("sequence_id", "tier", "step_group").distinct().collect()
    groups = {}
    for r in rows:
        groups.setdefault(r["step_group"], []).append(r["tier"])
    small = 0
    for tiers in groups.values():
        whole = min(tiers) >= 512
        assert not whole or len(set(tiers)) == 1
        assert sum(tiers) <= 1 << 16
        small += sum(tiers) < 1 << 16
    assert len(groups) > 60 and small <= 3 * 4


def test_encoder_equals_tokenizer():
    from tokenizers import Tokenizer

    model, encode = Tokenizer.from_file(tokenizer_path()), packing.Encoder(tokenizer_path(), 2)
    odd = ["a\x1cb <|endoftext|>x it's We'LL İstanbul ΟΔΟΣ ΟΔΟΣ. naïve ² x²y 12ab3 ...!! 　q́ é", " ́a", "", None, "ß.SS ªº µ", "it<|endoftext|>", "x y z"]
    assert encode(odd) == [np.array(model.encode(t or "", add_special_tokens=False).ids + [2], "<u4").tobytes() for t in odd]


def edit_search(pattern, text):
    row = [0] * (len(text) + 1)
    for i, p in enumerate(pattern, 1):
        new = [i]
        for j, c in enumerate(text, 1):
            new.append(min(row[j - 1] + (p != c), row[j] + 1, new[-1] + 1))
        row = new
    return min(row)


def test_leaks_equal_brute_force(spark):
    items = [(i, prose(30)) for i in range(6)] + [(98, None), (99, "")]
    rows = []
    for d in range(40):
        text, (_, item) = prose(40), items[d % 6]
        cut = list(item)
        for _ in range(d // 6):
            cut[rng.randrange(len(cut))] = "z"
        rows.append((d, text + " " + "".join(cut) + " " + prose(20) if d % 2 else text))
    rows += [(100, None), (101, "")]
    docs, bench = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["distance"] for r in decontamination.leaks(docs, bench, block_chars=300).collect()}
    want = {}
    for d, t in rows:
        for i, item in items:
            n = decontamination.normal(item)
            if n and (e := edit_search(n, decontamination.normal(t))) <= int(0.05 * len(n)):
                want[d, i] = e
    assert got == want
    kept = {r["doc_id"] for r in decontamination.without_leaks(docs, bench).collect()}
    assert kept == {d for d, _ in rows} - {d for d, _ in want}


def test_pseudonyms():
    p = pseudonyms.Pseudonymiser(b"key")
    text = "card 4111 1111 1111 1111, not 4111 1111 1111 1112; mail a.b7@x.example.com; +1 (743) 555-3824; 1999-12-31, 31.12.1999, 12/31/1999; 2021-02-30; 10.0.0.255; 300.1.1.1; DE89 3704 0044 0532 0130 00; 123-45-6789"
    new, seen = p(text)
    assert seen == {"mail": 1, "iban": 1, "date": 3, "address": 1, "social": 1, "phone": 1, "card": 1}
    assert "4111 1111 1111 1112" in new and "2021-02-30" in new and "300.1.1.1" in new
    assert p(new, True)[0] == text and p(new)[1] == seen and p(text)[0] == new
    assert p(None)[0] is None and p("")[0] == ""
    f = pseudonyms.Feistel(b"k")
    assert sorted(f(i, 1000, "t") for i in range(1000)) == list(range(1000)) and all(f(f(i, 1000, "t"), 1000, "t", True) == i for i in range(1000))


def test_licenses():
    known = license_scan.Templates(license_scan.TEMPLATES, 0.8)
    w = license_scan.words("Released under the MIT license!")
    assert [(n, d) for n, d, _ in known.score(w)] == [("MIT/notice", 1.0)]
    text = "intro line\n" + license_scan.TEMPLATES["MIT/text"][0].replace(". ", ".\n") + "\nend"
    assert any(u == "block" and name == "MIT/text" and dice > 0.9 for u, _, _, name, dice, _ in known.scan(text))
    for _ in range(200):  # pruning loses nothing
        c, name = rng.choice(known.entries)
        w = [x for x in license_scan.words(rng.choice([t for ts in license_scan.TEMPLATES.values() for t in ts])) if rng.random() > 0.1]
        own = license_scan.bigrams(w)
        want = {n for b, n in known.entries if own.total() and 2 * (b & own).total() / (b.total() + own.total()) >= 0.8}
        assert {n for n, *_ in known.score(w)} == want


def test_secrets(spark, empty):
    text = 'x token = "24be64439e3e49cf46b2d7c90f3602a3d0b907ff" y'
    rows = [(1, text), (2, None), (3, ""), (4, "plain internationalisation words"), (5, "see https://a.example/path/settingsPageWidgetFactory12/index.html"), (1, text)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("score", F.lit(1))
    forest = secret_scan.Forest(secret_scan.labelled_findings(spark))
    found = secret_scan.scan(docs, forest).collect()
    assert [r["doc_id"] for r in found if r["is_secret"]] == [1, 1]
    clean = [(r["doc_id"], r["text"]) for r in secret_scan.redacted(docs, forest).collect()]
    assert keyed(clean) == keyed([(d, t.replace("24be64439e3e49cf46b2d7c90f3602a3d0b907ff", secret_scan.BLANK) if t else t) for d, t in rows])
    assert secret_scan.scan(empty, forest).count() == 0
    plan = secret_scan.scan(docs, forest)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Exchange" not in plan


def test_language(spark, docs, empty):
    table = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = language_id.identify(table).join(table.select("doc_id", "lang"), "doc_id").filter("held_out").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double"))).first()[0]
    assert got > 0.97
    rows = {r["doc_id"]: r["lang_pred"] for r in language_id.identify(docs).collect()}
    assert rows[5] == rows[6] == rows[10] == "und" and rows[9] in ("en", "fr")
    assert language_id.identify(empty).count() == 0


def test_gru_gradients():
    net = language_id.Network(3, hidden=4, embed=3)
    net.w = {k: v.astype(np.float64) for k, v in net.w.items()}
    x, mask = language_id.padded([b"abc", b"de", b"f"])
    y = np.array([0, 1, 2])
    _, g = net.gradients(x, mask, y)
    for k, w in net.w.items():
        at = np.unravel_index(np.abs(g[k]).argmax(), w.shape)
        keep = w[at]
        w[at] = keep + 1e-3
        up = net.gradients(x, mask, y)[0]
        w[at] = keep - 1e-3
        down = net.gradients(x, mask, y)[0]
        w[at] = keep
        assert abs((up - down) / 2e-3 - g[k][at]) < 1e-3
