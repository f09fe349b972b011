"""Leaks of items whose pieces recur inside them."""

import random

from tests.llm.test_operators import edit_search
from tuneloom.llm import decontamination


def test_items_of_repeated_pieces():
    rng = random.Random(11)
    for _ in range(60):
        phrase = "".join(rng.choice("abcde ") for _ in range(rng.randint(5, 20))).strip() + "q"
        item = decontamination.normal(" ".join([phrase] * rng.randint(4, 9)))
        k = int(0.05 * len(item))
        copy = list(item)
        for _ in range(rng.randint(0, k)):
            at = rng.randrange(len(copy))
            copy[at : at + 1] = rng.choice(["z", "", "zy"])
        text = decontamination.normal(rng.choice(["", "some lead "]) + "".join(copy) + rng.choice(["", " and a tail " + phrase]))
        near = edit_search(item, text)
        hit = decontamination.Matcher([(1, item)], 0.05)(text).get(0)
        assert (hit[0] if hit else None) == (near if near <= k else None)


def nearest(rows, docs_text, k):
    near = edit_search(rows, docs_text)
    return near if near <= k else None


def test_periodic_items_and_several_copies():
    """Items whose pieces are equal, texts with several copies of different quality, and copies cut by the text's ends."""
    rng = random.Random(23)
    for case in range(300):
        unit = "".join(rng.choice("abcd") for _ in range(rng.randint(1, 6)))
        item = decontamination.normal((unit * 60)[: rng.randint(40, 90)] if case % 2 else " ".join(rng.choice(["one", "two", "one two", "three"]) for _ in range(14)))
        k = int(0.08 * len(item))

        def copy():
            c = list(item)
            for _ in range(rng.randint(0, k + 2)):
                at = rng.randrange(len(c))
                c[at : at + 1] = rng.choice(["z", "", "zy"])
            return "".join(c)

        text = decontamination.normal(" ".join([copy()[rng.randint(0, 3) :], rng.choice(["", "q" * rng.randint(1, 40)]), copy(), copy()[: -rng.randint(1, 5)]]))
        hit = decontamination.Matcher([(1, item)], 0.08)(text).get(0)
        assert (hit[0] if hit else None) == nearest(item, text, k), (item, text)


def test_tables(spark):
    items = spark.createDataFrame([(1, "a passage of the test that nobody may train on", 1), (2, None, 1), (3, "", 1), (None, "another passage of it, told at some length", 1)], "item_id long, text string, distance int")
    rows = [(1, "x a passage of the test that nobody may train on y"), (1, "x a passage of the test that nobody may train on y"), (2, None), (3, ""), (None, "another passage of it, told at some lengths"), (4, "w " * 30_000 + "a passage of the test that nobody may trainon")]
    docs = spark.createDataFrame([(*r, "clash") for r in rows], "doc_id long, text string, item_id string").repartition(3)
    got = sorted(((r["doc_id"], r["item_id"], r["distance"]) for r in decontamination.leaks(docs, items).collect()), key=str)
    assert got == sorted([(1, 1, 0), (1, 1, 0), (None, None, 1), (4, 1, 1)], key=str) or got == sorted([(1, 1, 0), (1, 1, 0), (None, None, 0), (4, 1, 1)], key=str)
    kept = decontamination.without_leaks(docs, items)
    assert kept.columns == docs.columns and sorted(r["doc_id"] for r in kept.collect()) == [2, 3]
    assert decontamination.leaks(docs.filter("doc_id < 0"), items).collect() == []
    assert decontamination.leaks(docs, items.filter("item_id < 0")).collect() == [] and decontamination.without_leaks(docs, items.filter("item_id < 0")).count() == 6
