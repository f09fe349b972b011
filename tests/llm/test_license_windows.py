"""License windows against all windows of lines, and whole tables."""

import random

from tuneloom.llm import license_scan as ls

MIT, BSD, ISC = (ls.TEMPLATES[n][0] for n in ("MIT/text", "BSD-2-Clause/text", "ISC/text"))


def lines_of(text, rng, width=12):
    w, out = text.split(), []
    while w:
        n = rng.randint(width // 2, width)
        out.append(" ".join(w[:n]))
        w = w[n:]
    return out


def brute(lines, own, t):
    """Best window of whole lines, then the same before and behind it."""
    best = None
    for a in range(len(lines)):
        for b in range(a, len(lines)):
            w = [x for line in lines[a : b + 1] for x in line]
            g = ls.bigrams(w)
            if w and (dice := 2 * (g & own).total() / max(1, g.total() + own.total())) >= t and (best is None or dice > best[0]):
                best = dice, a, b
    if best is None:
        return []
    return [best] + brute(lines[: best[1]], own, t) + [(d, a + best[2] + 1, b + best[2] + 1) for d, a, b in brute(lines[best[2] + 1 :], own, t)]


def test_windows_equal_all_windows():
    rng = random.Random(3)
    small = {"one": ["alpha beta gamma delta epsilon zeta eta theta"], "two": ["beta gamma alpha beta kappa lambda"]}
    known = ls.Templates(small, 0.6)
    pool = "alpha beta gamma delta epsilon zeta eta theta kappa lambda x y".split()
    for _ in range(150):
        lines = [[rng.choice(pool) for _ in range(rng.randint(1, 4))] if rng.random() < 0.4 else ls.words(rng.choice([t[0] for t in small.values()]))[:: rng.choice([1, 1, 2])][: rng.randint(2, 8)] for _ in range(rng.randint(1, 9))]
        for i, (own, _) in enumerate(known.entries):
            assert sorted(known.windows(lines, i)) == sorted(brute(lines, own, 0.6))


def found(text):
    known = ls.Templates(ls.TEMPLATES | ls.full_texts(), 0.8)
    return [(a, b, n) for u, a, b, n, _, best in known.scan(text) if u == "block" and best]


def test_neighbours_and_foreign_lines():
    rng = random.Random(5)
    mit, bsd, isc = (lines_of(t, rng) for t in (MIT, BSD, ISC))
    got = found("\n".join([*mit, *bsd, *isc]))
    assert [n for *_, n in got] == ["MIT/text", "BSD-2-Clause/text", "ISC/text"]
    assert all(abs(a - want) <= 1 for (a, *_), want in zip(got, (0, len(mit), len(mit) + len(bsd))))
    got = found("\n".join(["first a line of the author", *mit[:5], "", "a line of another hand", *mit[5:], "and a last one"]))
    assert [n for *_, n in got] == ["MIT/text"] and got[0][0] == 1
    assert [n for *_, n in found("\n".join([*mit, "-- some other words stand here --", *mit]))] == ["MIT/text"] * 2


def test_full_texts():
    full = ls.full_texts()
    assert {"Apache-2.0/full", "GPL-2/full", "GPL-3/full", "MPL-2.0/full", "LGPL-2.1/full"} <= set(full)
    for name in ("Apache-2.0/full", "GPL-3/full"):
        assert (name) in [n for *_, n in found("Copyright somebody\n\n" + full[name][0] + "\nint main() { return 0; }\n")]
    assert len(ls.full_texts("/nowhere")) == 0


def test_tables(spark):
    text = "prose here\n" + "\n".join(lines_of(MIT, random.Random(1))) + "\nReleased under the MIT License."
    rows = [(1, text), (2, None), (3, ""), (None, text), (1, text), (4, "nothing of the kind"), (5, "word " * 50_000)]
    docs = spark.createDataFrame([(*r, "clash") for r in rows], "doc_id long, text string, license string").repartition(3)
    got = ls.scan(docs).collect()
    assert sorted((r["doc_id"], r["unit"], r["license"]) for r in got if r["best"] and r["doc_id"] is not None and r["unit"] != "text") == [(1, "block", "MIT/text")] * 2 + [(1, "line", "MIT/notice")] * 2
    assert {r["doc_id"] for r in got} == {1, None}
    assert ls.scan(docs.filter("doc_id < 0")).collect() == []
