"""Components: every linked node has a row, the smallest one too, and near copies get the smallest id of their group."""

import random

import pytest
import xxhash

from tests.llm.test_operators import plain_fingerprint
from tuneloom.llm import simhash_dedup
from tuneloom.llm.hash_sql import xxh64_ctes


def smallest(edges):
    root = {x: x for e in edges for x in e}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        root[max(find(a), find(b))] = min(find(a), find(b))
    return {x: find(x) for x in root}


@pytest.mark.parametrize("n,m", [(2, 1), (60, 40), (40, 200)])
def test_every_linked_node_has_a_row(spark, n, m):
    r = random.Random(n + m)
    edges = [tuple(sorted(r.sample(range(-n, n), 2))) for _ in range(m)]
    got = simhash_dedup.components(spark.createDataFrame(edges, "src long, dst long")).collect()
    assert len(got) == len({x["node"] for x in got}) and {x["node"]: x["root"] for x in got} == smallest(edges)


def test_near_copies_with_the_smallest_id_at_any_fingerprint(spark):
    """Chains of edited copies in any order of ids, so that roots by fingerprint and by id differ; some texts twice."""
    r = random.Random(11)
    rows, ids = [], iter(r.sample(range(1000), 400))
    for _ in range(12):
        words = [f"w{r.randrange(10**6)}" for _ in range(300)]
        for _ in range(8):
            rows += [(next(ids), " ".join(words))] * r.choice((1, 1, 2))
            rows.append((next(ids), " ".join(words)))
            words[r.randrange(300)] = f"v{r.randrange(10**6)}"
    prints = {(d, plain_fingerprint(t, 4)) for d, t in rows}
    edges = [(a, b) for a, x in prints for b, y in prints if a < b and (x ^ y).bit_count() <= 4]
    root = smallest(edges)
    assert len({x for _, x in prints}) > len(set(root.values())) > 0
    got = {(x["doc_id"], x["fingerprint"], x["component_id"]) for x in simhash_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {(d, f"{x:016x}", root.get(d, d)) for d, x in prints}


def test_hash_in_sql(duck):
    texts = ["", "é", "word " * 30] + ["ab字c "[i % 5] * i for i in range(1, 130)]
    rows = ", ".join(f"('{t}')" for t in dict.fromkeys(texts))
    got = dict(duck.execute(f"WITH src(s) AS (VALUES {rows}), {xxh64_ctes('src')} SELECT s, h FROM xxh").fetchall())
    assert got == {t: xxhash.xxh64_intdigest(t.encode(), 42) for t in texts}
