"""The pipeline's near copies against all pairs compared."""

import random
from itertools import combinations

from tuneloom.llm import similar_pairs, stages


def jaccard(a, b, width=5):
    x, y = ({tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} for w in (a.lower().split(), b.lower().split()))
    return len(x & y) / len(x | y)


def brute(rows):
    root = {i: i for i, _ in rows}

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for (i, a), (j, b) in combinations(rows, 2):
        if jaccard(a or "", b or "") >= 0.8:
            x, y = sorted((top(i), top(j)))
            root[y] = x
    return {i: top(i) for i in root}


def test_near_copies_equal_all_pairs(spark):
    rng = random.Random(3)
    words = [f"w{i}" for i in range(500)]
    rows, common = [], [rng.choice(words) for _ in range(60)]
    for base in range(30):
        text = common + [rng.choice(words) for _ in range(140)]
        for copy in range(4 if base else 60):  # one large group, so that buckets over `small` occur
            new = list(text)
            for at in rng.sample(range(len(new)), copy % 5):
                new[at] = f"x{rng.randrange(10**6)}"
            rows.append((len(rows), " ".join(new)))
    rows += [(900, None), (901, ""), (902, "One two"), (903, "one  two"), (904, "one three")]
    rng.shuffle(rows)
    want = brute(rows)
    df = spark.createDataFrame([*rows, (None, rows[0][1])], "doc_id long, text string").repartition(3)
    for small, block in ((3, 7), (3, 2000), (16, 25)):
        assert {r["doc_id"]: r["component_id"] for r in similar_pairs.similar_groups(df, small=small, block=block).collect()} == want
    kept = {r["doc_id"] for r in stages.near_duplicates(spark, df, "").collect()}
    assert kept == set(want.values()) | {None}
    assert similar_pairs.similar_groups(df.filter("doc_id < 0")).collect() == []
