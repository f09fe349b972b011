"""Equal values stay linked over layouts and documents; tables with nulls, repeats and clashing columns."""

import re
import random

from tuneloom.llm import pseudonyms


def test_dates_are_linked_over_layouts():
    p, rng = pseudonyms.Pseudonymiser(b"key"), random.Random(1)
    seen = {}
    for _ in range(1500):
        y, m, d = rng.randint(1900, 2099), rng.randint(1, 12), rng.randint(1, 28)
        texts = [f"{y}-{m:02}-{d:02}", f"{y}/{m:02}/{d:02}", f"{d:02}.{m:02}.{y}"] + ([f"{m:02}/{d:02}/{y}"] if d > 12 else [])
        new = [p(t)[0] for t in texts]
        a, b, c = (int(x) for x in new[0].split("-"))
        assert new == [f"{a}-{b:02}-{c:02}", f"{a}/{b:02}/{c:02}", f"{c:02}.{b:02}.{a}"] + ([f"{b:02}/{c:02}/{a}"] if d > 12 else [])
        assert [p(t, True)[0] for t in new] == texts
        assert seen.setdefault(new[0], texts[0]) == texts[0]


def test_addresses_are_linked_over_case():
    p = pseudonyms.Pseudonymiser(b"key")
    a, b, c = (p(t)[0] for t in ("Anna.B7@x.example", "anna.b7@x.example", "ANNA.B7@X.example"))
    assert a.lower() == b and c.partition("@")[0].lower() == b.partition("@")[0] and b != "anna.b7@x.example"
    assert re.match(r"[A-Z][a-z]{3}\.[A-Z]\d@", a) and p(a, True)[0] == "Anna.B7@x.example"
    assert len({p(f"{x}{y}@d.example")[0] for x in "abcdefghij" for y in range(10)}) == 100


def test_tables(spark):
    text = "write to a.b@x.example before 1999-12-31 with 4111 1111 1111 1111"
    rows = [(1, text), (2, text), (2, text), (3, None), (4, ""), (None, text), (5, "nothing here")]
    docs = spark.createDataFrame([(*r, 7) for r in rows], "doc_id long, text string, n_mail int").repartition(3)
    got = pseudonyms.pseudonymise(docs, b"key").collect()
    one = pseudonyms.Pseudonymiser(b"key")(text)[0]
    assert one != text
    assert sorted(((r["doc_id"], r["text"]) for r in got), key=str) == sorted(((d, one if t == text else t) for d, t in rows), key=str)
    assert sum(r["n_mail"] for r in got) == sum(r["n_date"] for r in got) == sum(r["n_card"] for r in got) == 4
    assert pseudonyms.pseudonymise(docs.filter("doc_id < 0"), b"key").collect() == []
