"""Secrets on findings and documents that the forest was not trained on."""

import random
import re

import pytest
from pyspark.sql import functions as F

from tests.conftest import MIDDLE
from tuneloom.llm import secret_scan as ss


@pytest.fixture(scope="module")
def forest(spark):
    return ss.Forest(ss.labelled_findings(spark))


def rates(rows, forest):
    """(precision, recall) of rows (token, before, after, label)."""
    hit = forest(ss.features(F.col("token"), F.col("before"), F.col("after"))) >= 0.5
    n = rows.select(hit.alias("hit"), (F.col("label") == 1).alias("true")).agg(F.sum((F.col("hit") & F.col("true")).cast("int")), F.sum(F.col("hit").cast("int")), F.sum(F.col("true").cast("int"))).first()
    return n[0] / max(1, n[1]), n[0] / max(1, n[2])


def test_findings_of_other_numbers(spark, forest):
    train, test = ss.labelled_findings(spark), ss.labelled_findings(spark, 4000, first=1_000_000)
    secret = test.filter("label = 1")
    assert secret.join(train, "token").count() == 0
    precision, recall = rates(test, forest)
    assert precision > 0.9 and recall > 0.9, (precision, recall)


def test_findings_of_other_forms(spark, forest):
    """Forms and surroundings that the rules of labelled_findings do not write."""
    rng = random.Random(8)
    pick = lambda pool, n: "".join(rng.choice(pool) for _ in range(n))
    low, up, dig = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
    rows = []
    for _ in range(150):
        rows += [
            (pick(low + up + dig, 32), 'client_secret: "', '"', 1.0),
            ("glpat-" + pick(low + up + dig, 20), "export GITLAB_TOKEN=", " && run", 1.0),
            (pick(up + dig, 26), "{'aws_secret_access_key': '", "'}", 1.0),
            (pick("0123456789abcdef", 64), "SIGNING_SECRET = '", "'\n", 1.0),
            ("-".join(rng.choice(ss.DICTIONARY) for _ in range(4)) + "-" + pick(dig, 2), "kubectl get pod ", " -o wide", 0.0),
            (rng.choice(ss.DICTIONARY).upper() + "_" + rng.choice(ss.DICTIONARY).upper() + "_" + rng.choice(ss.DICTIONARY).upper() + "_2", "#define ", " 17", 0.0),
            (pick("0123456789abcdef", 40), "merged in revision ", " of the tree", 0.0),
            (pick(dig, 18), "order number ", " was sent", 0.0),
        ]
    precision, recall = rates(spark.createDataFrame(rows, "token string, before string, after string, label double"), forest)
    assert precision > 0.9 and recall > 0.85, (precision, recall)


def test_secrets_of_documents(spark, forest):
    """The secrets that stand in the given documents as token = "..."."""
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet").select("doc_id", "text")
    planted = {(r[0], t) for r in docs.collect() for t in re.findall(r'(?i)token = "([0-9a-f]{32,})"', r[1] or "")}
    found = ss.scan(docs, forest).filter("is_secret").select("doc_id", "token_sha256").collect()
    import hashlib

    want = {(d, hashlib.sha256(t.encode()).hexdigest()) for d, t in planted}
    got = {tuple(r) for r in found}
    assert len(want) > 10 and len(got & want) >= 0.95 * len(want) and len(got & want) >= 0.95 * len(got), (len(want), len(got), len(got & want))


def test_tables(spark, forest):
    text = 'x token = "24be64439e3e49cf46b2d7c90f3602a3d0b907ff" y'
    docs = spark.createDataFrame([(None, text, "a"), (1, None, "b"), (2, "", "c"), (3, text + "\n" + "z " * 40_000 + text, "d")], "doc_id long, text string, token string")
    got = ss.scan(docs, forest).filter("is_secret").collect()
    assert sorted((r["doc_id"] or 0, r["finding"]) for r in got) == [(0, 0), (3, 0), (3, 1)]
    clean = ss.redacted(docs, forest)
    assert clean.columns == docs.columns and clean.count() == 4
    assert clean.filter(F.col("text").contains("24be64439e3e")).count() == 0
    assert ss.redacted(docs.filter("doc_id < 0"), forest).count() == ss.scan(docs.filter("doc_id < 0"), forest).count() == 0
