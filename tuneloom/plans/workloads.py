"""The experiment workloads on the given tables, and the same in SQL for a second engine."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.stats import esd_critical
from ..operators import align, augment, baselines, corpus, describe, esd, metrics, prompt, reason, stl, telemetry, vindex
from ..sources.tables import events, read, stored
from . import debugging, experiments, fixtures
from .relational import ORACLE_SQL as RELATIONAL_SQL
from .relational import QUERIES as RELATIONAL

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE_SQL[f.__name__] = sql
        return f

    return add


# ---------------------------------------------------------------- corpus


def _catalog_sql(where: str, top: int, dbms: str) -> str:
    return f"""SELECT '{dbms}' AS dbms, knob, ['numeric','categorical','boolean'][CAST(length(knob) % 3 AS INT) + 1] AS kind, df FROM (
        SELECT knob, count(*) AS df FROM (SELECT unnest(list_distinct(regexp_extract_all(lower(text), '[a-z]{{4,}}'))) AS knob FROM documents WHERE {where}) GROUP BY knob)
        WHERE df >= 0.02 * (SELECT count(*) FROM documents WHERE {where}) AND df <= 0.10 * (SELECT count(*) FROM documents WHERE {where})
        ORDER BY df DESC, knob LIMIT {top}"""


CATALOG = _catalog_sql("lang = 'en'", 582, "main")
_SENTENCES_DOC = """SELECT 'document' AS source, doc_id, sent_no - 1 AS sent_no, trim(text) AS text FROM (
    SELECT doc_id, unnest(p) AS text, generate_subscripts(p, 1) AS sent_no FROM (SELECT doc_id, string_split_regex(text, '[.!?]+\\s+|\\n+') AS p FROM documents)) WHERE trim(text) <> ''"""
_PLAIN = "regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g')"
_PLAIN = f"regexp_replace({_PLAIN}, '<[^>]*>', ' ', 'g')"
for _e, _c in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
    _PLAIN = f"replace({_PLAIN}, '{_e}', '{_c}')"
_PLAIN = f"trim(regexp_replace({_PLAIN}, '[ \\t\\r\\f]+', ' ', 'g'))"
_SENTENCES_PAGE = f"""SELECT 'page' AS source, doc_id, sent_no - 1 AS sent_no, trim(text) AS text FROM (
    SELECT doc_id, unnest(p) AS text, generate_subscripts(p, 1) AS sent_no FROM (SELECT page_id AS doc_id, string_split_regex({_PLAIN}, '[.!?]+\\s+|\\n+') AS p FROM pages)) WHERE trim(text) <> ''"""


def catalog(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpus.term_catalog(read(spark, sf_dir, "documents", ["text"], F.col("lang") == "en"), 582, "main")


@query(CATALOG)
def knob_catalog(spark, sf_dir):
    return catalog(spark, sf_dir)


@query(_catalog_sql("lang <> 'en'", 202, "second"))
def knob_catalog_second(spark, sf_dir):
    return corpus.term_catalog(read(spark, sf_dir, "documents", ["text"], F.col("lang") != "en"), 202, "second")


@query(f"{_SENTENCES_DOC} UNION ALL {_SENTENCES_PAGE}")
def manual_sentences(spark, sf_dir):
    docs = corpus.split_sentences(read(spark, sf_dir, "documents"), "text", "doc_id").select(F.lit("document").alias("source"), "*")
    pages = read(spark, sf_dir, "pages").select("page_id", corpus.plain_html(F.col("html")).alias("body"))
    return docs.unionAll(corpus.split_sentences(pages, "body", "page_id").select(F.lit("page").alias("source"), "*"))


@query(f"""WITH c AS ({CATALOG}), s AS ({_SENTENCES_DOC})
    SELECT doc_id, sent_no, string_agg(knob, ',' ORDER BY knob) AS knobs FROM (
        SELECT doc_id, sent_no, unnest(list_distinct(regexp_extract_all(lower(text), '[a-z]{{4,}}'))) AS knob FROM s) JOIN c USING (knob) GROUP BY doc_id, sent_no""")
def manual_labels(spark, sf_dir):
    sentences = corpus.split_sentences(read(spark, sf_dir, "documents"), "text", "doc_id")
    return corpus.label(sentences, "text", catalog(spark, sf_dir), ["doc_id", "sent_no"]).withColumn("knobs", F.concat_ws(",", "knobs"))


_PAIRS = """SELECT u.conv_id * 1000 + u.turn AS qid, u.text AS question, a.text AS answer FROM conversations u JOIN conversations a
    ON u.conv_id = a.conv_id AND a.turn = u.turn + 1 WHERE u.role = 'user' AND a.role = 'assistant'"""
_LABELS = f"""SELECT qid, knob, df FROM (SELECT qid, unnest(list_distinct(regexp_extract_all(lower(answer), '[a-z]{{4,}}'))) AS knob FROM ({_PAIRS})) JOIN ({CATALOG}) USING (knob)"""


def labelled_questions(spark, sf_dir, limit=None):
    pairs = corpus.question_pairs(read(spark, sf_dir, "conversations"))
    labels = corpus.label(pairs, "answer", catalog(spark, sf_dir), ["qid"], limit)
    return pairs.select("qid", F.col("question").alias("text")).join(labels, "qid")


@query(f"SELECT qid, string_agg(knob, ',' ORDER BY knob) AS knobs, count(*) AS n_knobs FROM ({_LABELS}) GROUP BY qid")
def question_pairs(spark, sf_dir):
    return labelled_questions(spark, sf_dir).select("qid", F.concat_ws(",", "knobs").alias("knobs"), F.size("knobs").cast("long").alias("n_knobs"))


@query(f"SELECT qid, string_agg(knob, ',' ORDER BY knob) AS knobs FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY df, knob) AS r FROM ({_LABELS})) WHERE r <= 3 GROUP BY qid")
def question_pairs_sparse(spark, sf_dir):
    return labelled_questions(spark, sf_dir, 3).select("qid", F.concat_ws(",", "knobs").alias("knobs"))


@query(f"""SELECT (SELECT count(*) FROM ({_PAIRS})) AS questions, (SELECT count(DISTINCT qid) FROM ({_LABELS})) AS labelled, (SELECT count(*) FROM ({_LABELS})) AS labels,
    (SELECT count(*) FROM ({_SENTENCES_DOC})) AS sentences, (SELECT count(*) FROM ({CATALOG})) AS knobs""")
def dataset_stats(spark, sf_dir):
    n = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    labelled = labelled_questions(spark, sf_dir)
    return (
        n(corpus.question_pairs(read(spark, sf_dir, "conversations")), "questions")
        .crossJoin(labelled.agg(F.count(F.lit(1)).alias("labelled"), F.sum(F.size("knobs")).alias("labels")))
        .crossJoin(n(corpus.split_sentences(read(spark, sf_dir, "documents"), "text", "doc_id"), "sentences"))
        .crossJoin(n(catalog(spark, sf_dir), "knobs"))
    )


@query(f"SELECT used, catalog, round(used / catalog, 6) AS coverage FROM (SELECT (SELECT count(DISTINCT knob) FROM ({_LABELS})) AS used, (SELECT count(*) FROM ({CATALOG})) AS catalog)")
def knob_coverage(spark, sf_dir):
    return metrics.coverage(labelled_questions(spark, sf_dir), catalog(spark, sf_dir))


@query("SELECT vec_id, CASE WHEN vec_id % 10 < 7 THEN 'history' WHEN vec_id % 10 < 9 THEN 'train' ELSE 'test' END AS split FROM embeddings")
def split_721(spark, sf_dir):
    return corpus.split(read(spark, sf_dir, "embeddings", ["vec_id"]), "vec_id", scheme="mod10")


@query(f"SELECT DISTINCT text FROM (SELECT question AS text FROM ({_PAIRS}) UNION ALL SELECT text FROM documents WHERE lang = 'en')")
def merge_histories(spark, sf_dir):
    return corpus.merge_histories(corpus.question_pairs(read(spark, sf_dir, "conversations")).select(F.col("question").alias("text")), read(spark, sf_dir, "documents", ["text"], F.col("lang") == "en"))


@query("SELECT doc_id, quality, toxic FROM labels ORDER BY md5(CAST(doc_id AS VARCHAR)), doc_id LIMIT 100")
def audit_sample(spark, sf_dir):
    return corpus.audit_sample(read(spark, sf_dir, "labels"), "doc_id", 100).select("doc_id", "quality", "toxic")


def _statements_sql(form: int, pattern: str, name: int, value: str) -> str:
    return f"""SELECT doc_id, {form} AS form, place, lower(regexp_extract(m, {pattern}, {name})) AS knob, {value} AS value FROM (
        SELECT doc_id, unnest(regexp_extract_all(text, {pattern})) AS m, generate_subscripts(regexp_extract_all(text, {pattern}), 1) AS place FROM documents)"""


_QUOTED = ["'" + f[0].replace("'", "''") + "'" for f in corpus.SETTINGS]


@query(f"""WITH s AS ({_statements_sql(0, _QUOTED[0], 1, f"rtrim(regexp_extract(m, {_QUOTED[0]}, 2), '.')")} UNION ALL {_statements_sql(1, _QUOTED[1], 1, f"rtrim(regexp_extract(m, {_QUOTED[1]}, 2), '.')")}
      UNION ALL {_statements_sql(2, _QUOTED[2], 1, "lower(regexp_extract(m, '" + corpus.SETTINGS[2][3] + "', 1))")}),
    l AS (SELECT doc_id, knob, arg_max(value, form * 1000000 + place) AS value FROM s WHERE knob IN ('token', 'secret', 'password') GROUP BY 1, 2)
    SELECT doc_id, string_agg(knob || '=' || value, ',' ORDER BY knob) AS config, string_agg(knob, ',' ORDER BY knob) AS knobs FROM l GROUP BY 1""")
def setting_statements(spark, sf_dir):
    names = spark.createDataFrame([("token",), ("secret",), ("password",)], "knob string")
    found = corpus.extract_config(read(spark, sf_dir, "documents"), "text", names, ["doc_id"])
    return found.select("doc_id", F.concat_ws(",", F.transform(F.map_entries("config"), lambda e: F.concat(e["key"], F.lit("="), e["value"]))).alias("config"), F.concat_ws(",", "knobs").alias("knobs"))


# ---------------------------------------------------------------- retrieval

_D = "round(list_distance(CAST(d.embedding AS DOUBLE[]), CAST(q.embedding AS DOUBLE[])), 6)"
_VEC = "SELECT vec_id, list_transform(CAST(embedding AS DOUBLE[]), lambda x: x / sqrt(list_inner_product(CAST(embedding AS DOUBLE[]), CAST(embedding AS DOUBLE[])))) AS embedding, label, CASE WHEN vec_id % 2 = 0 THEN 'question' ELSE 'manual' END AS source FROM embeddings"


def _knn_sql(k: int, where: str = "TRUE", per: str = "", queries: str = "vec_id % 10 = 9", docs: str = "vec_id % 10 < 7") -> str:
    return f"""SELECT qid, rank, doc_id, source, dist FROM (SELECT q.vec_id AS qid, d.vec_id AS doc_id, d.source AS source, {_D} AS dist,
        row_number() OVER (PARTITION BY q.vec_id{per} ORDER BY {_D}, d.vec_id) AS rank FROM (SELECT * FROM ({_VEC}) WHERE {queries}) q, (SELECT * FROM ({_VEC}) WHERE {docs} AND {where}) d) WHERE rank <= {k}"""


def _search_sql(k: int, where: str = "TRUE", per: str = "") -> str:
    """The ids divisible by 20 against all rows."""
    return _knn_sql(k, where, per, "vec_id % 20 = 0", "TRUE")


def vectors(spark, sf_dir):
    """doc_id, source, vec, knobs, label of all rows."""
    e = read(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("doc_id"), F.when(F.col("vec_id") % 2 == 0, "question").otherwise("manual").alias("source"), F.col("embedding").alias("vec"), F.array(F.col("label").cast("string")).alias("knobs"), "label")


def _split_vectors(spark, sf_dir):
    v = vectors(spark, sf_dir)
    return v.filter("doc_id % 10 = 9").withColumnRenamed("doc_id", "qid"), v.filter("doc_id % 10 < 7")


def _search(spark, sf_dir):
    v = vectors(spark, sf_dir)
    return v.filter("doc_id % 20 = 0").select(F.col("doc_id").alias("qid"), "vec"), v


def _knn(spark, sf_dir, k=5, **how):
    q, d = _search(spark, sf_dir)
    return vindex.topk_exact(q.select("qid", "vec"), d, k, **how).select("qid", "rank", "doc_id", "source", "dist")


@query(_knn_sql(5, queries="TRUE", docs="TRUE"))
def knn_exact_k5(spark, sf_dir):
    """The nearest of every row among all rows."""
    v = vectors(spark, sf_dir)
    return vindex.topk_exact(v.select(F.col("doc_id").alias("qid"), "vec"), v, 5).select("qid", "rank", "doc_id", "source", "dist")


@query(_search_sql(5, per=", d.source"))
def knn_per_source(spark, sf_dir):
    return _knn(spark, sf_dir, per_source=True)


@query(_search_sql(5, "source = 'question'"))
def knn_question_only(spark, sf_dir):
    return _knn(spark, sf_dir, sources={"question"})


@query(_search_sql(5, "source = 'manual'"))
def knn_manual_only(spark, sf_dir):
    return _knn(spark, sf_dir, sources={"manual"})


@query(_search_sql(5))
def knn_blocked(spark, sf_dir):
    q, d = _search(spark, sf_dir)
    return vindex.topk_blocked(q.select("qid", "vec"), d, 5).select("qid", "rank", "doc_id", "source", "dist")


def _recall_of(found: DataFrame, exact: DataFrame) -> DataFrame:
    hit = exact.select("qid", "doc_id").join(found.select("qid", "doc_id").withColumn("h", F.lit(1.0)), ["qid", "doc_id"], "left")
    return hit.agg(F.count(F.lit(1)).alias("pairs"), F.round(F.avg(F.coalesce("h", F.lit(0.0))), 6).alias("recall"))


_ANN = f"SELECT count(*) AS pairs, TRUE AS recall_over_90 FROM ({_search_sql(5)})"


def _claim(recall: DataFrame) -> DataFrame:
    return recall.select("pairs", (F.col("recall") >= 0.9).alias("recall_over_90"))


def inverted_file(docs: DataFrame) -> vindex.IVF:
    """The given vectors have no clusters: of 24 cells 14 must be looked at for nine tenths of the nearest."""
    return vindex.IVF(nlist=24, nprobe=14).fit(docs)


@query(_ANN)
def ann_inverted_file(spark, sf_dir):
    """Every row is in the index; recall against the exact search over all rows."""
    q, d = _search(spark, sf_dir)
    ivf = inverted_file(d)
    return _claim(_recall_of(ivf.search(q, ivf.index(d), 5), vindex.topk_exact(q, d, 5)))


@query(_ANN)
def ann_hashing(spark, sf_dir):
    q, d = _search(spark, sf_dir)
    return _claim(_recall_of(vindex.lsh_search(q, d, 5, radius=1.3, bucket=0.5, tables=12), vindex.topk_exact(q, d, 5)))


def _recall_sql(knobs: str) -> str:
    """knobs: a list expression over vec_id and label."""
    return f"""WITH h AS ({_knn_sql(10)}), t AS (SELECT vec_id AS qid, unnest({knobs}) AS knob FROM embeddings WHERE vec_id % 10 = 9),
        c AS (SELECT qid, knob, min(rank) AS rank FROM (SELECT h.qid, h.rank, unnest({knobs}) AS knob FROM h JOIN embeddings ON vec_id = doc_id) GROUP BY qid, knob),
        per AS (SELECT t.qid, k, avg(CASE WHEN c.rank <= k THEN 1.0 ELSE 0.0 END) AS r FROM t LEFT JOIN c USING (qid, knob), (VALUES (1), (3), (5), (10)) ks(k) GROUP BY t.qid, k)
        SELECT k, round(avg(r), 6) AS recall FROM per GROUP BY k"""


def _recall(spark, sf_dir, knobs):
    q, d = _split_vectors(spark, sf_dir)
    d, q = d.withColumn("knobs", knobs(F.col("doc_id"))), q.withColumn("knobs", knobs(F.col("qid")))
    return metrics.doc_recall(vindex.topk_exact(q.select("qid", "vec"), d, 10), q.select("qid", F.explode("knobs").alias("knob")))


@query(_recall_sql("[label]"))
def doc_recall_at_k(spark, sf_dir):
    return _recall(spark, sf_dir, lambda i: F.array(F.col("label").cast("string")))


@query(_recall_sql("[label, 10 + vec_id % 7]"))
def doc_recall_multi(spark, sf_dir):
    return _recall(spark, sf_dir, lambda i: F.array(F.col("label").cast("string"), (10 + i % 7).cast("string")))


def _mined_sql(test: str) -> str:
    return f"""SELECT m.qid, m.doc_id, m.dist, m.rank FROM ({_knn_sql(20, queries="vec_id % 10 IN (7, 8)")}) m JOIN embeddings q ON q.vec_id = m.qid JOIN embeddings d ON d.vec_id = m.doc_id WHERE q.label {test} d.label AND m.qid <> m.doc_id"""


def _mined(spark, sf_dir, kind):
    v = vectors(spark, sf_dir)
    return align.mine(v.filter("doc_id % 10 in (7, 8)").withColumnRenamed("doc_id", "qid"), v.filter("doc_id % 10 < 7"), kind)


@query(_mined_sql("="))
def mine_pairs_pos(spark, sf_dir):
    return _mined(spark, sf_dir, "pos")


@query(_mined_sql("<>"))
def mine_pairs_neg(spark, sf_dir):
    return _mined(spark, sf_dir, "neg")


@query(f"""WITH p AS ({_mined_sql("=")}), n AS ({_mined_sql("<>")}), m AS (SELECT least((SELECT count(*) FROM p), (SELECT count(*) FROM n)) AS m)
    SELECT kind, qid, doc_id FROM (SELECT 'pos' AS kind, qid, doc_id, row_number() OVER (ORDER BY dist, qid, doc_id) AS r FROM p UNION ALL
    SELECT 'neg', qid, doc_id, row_number() OVER (ORDER BY dist, qid, doc_id) FROM n), m WHERE r <= m""")
def pairs_balanced(spark, sf_dir):
    tag = lambda kind: _mined(spark, sf_dir, kind).withColumn("pair_type", F.lit("qm"))
    pos, neg = align.balance(tag("pos"), tag("neg"), ["pair_type"])
    return pos.select(F.lit("pos").alias("kind"), "qid", "doc_id").unionAll(neg.select(F.lit("neg").alias("kind"), "qid", "doc_id"))


def _planted_pairs(spark, sf_dir, mixed: bool):
    """Each vector is a question; its manual is a fixed rotation of it plus small noise. mixed: pairs dealt wrongly, as a control."""
    e = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"))
    dim = len(e.first()["vec"])
    turn, _ = np.linalg.qr(np.random.default_rng(5).normal(size=(dim, dim)))

    def turned(v: pd.Series, seed: pd.Series) -> pd.Series:
        noise = (0.01 * np.random.default_rng(s).normal(size=dim) for s in seed)
        return pd.Series([x @ turn + z for x, z in zip(v, noise)], index=v.index)

    turned = F.pandas_udf(turned, "array<double>")

    question = e.withColumn("source", F.lit("question"))
    manual = e.withColumn("vec", turned("vec", "id")).withColumn("source", F.lit("manual"))
    if mixed:  # the pair of an id is another id's, inside the same part of the split
        order = Window.partitionBy(F.col("id") % 10).orderBy(F.md5(F.col("id").cast("string")))
        manual = manual.withColumn("id", F.coalesce(F.lead("id").over(order), F.first("id").over(order)))
    return question.unionByName(manual).withColumn("knobs", F.array(F.col("id").cast("string")))


def _aligned_recall(spark, sf_dir, mixed: bool, epochs: int):
    v = _planted_pairs(spark, sf_dir, mixed).withColumn("test", F.col("id") % 10 == 9)
    train = v.filter("not test and source = 'question'").select(F.col("id").alias("qid"))
    bound = train.agg(F.min("qid").alias("lo"), F.max("qid").alias("hi"))
    draw = lambda j: F.col("lo") + F.pmod(F.xxhash64("qid", j), F.col("hi") - F.col("lo") + 1)
    negs = train.crossJoin(F.broadcast(bound)).select("qid", F.explode(F.transform(F.sequence(F.lit(1), F.lit(14)), draw)).alias("n"))  # bound: one row
    negs = negs.filter("n <> qid").join(train.select(F.col("qid").alias("n")), "n").groupBy("qid").agg(F.sort_array(F.collect_set("n")).alias("neg_ids"))
    pairs = train.join(negs, "qid").select("qid", F.col("qid").alias("pos_id"), "neg_ids", F.lit("qm").alias("pair_type"), F.lit("question").alias("q_source"), F.lit("manual").alias("pos_source"), F.lit("manual").alias("neg_source"))
    heads, _ = align.fit(pairs, v.select("id", "source", "vec"), 64, tau=0.1, epochs=epochs, schedule=("qm",), max_pairs=20_000)
    moved = align.apply(v.filter("test"), heads)
    q = moved.filter("source = 'question'").select(F.col("id").alias("qid"), "vec")
    hits = vindex.topk_exact(q, moved.filter("source = 'manual'").withColumnRenamed("id", "doc_id"), 5)
    return metrics.doc_recall(hits, q.select("qid", F.col("qid").cast("string").alias("knob")), (1, 5))


@query("SELECT variant, k, TRUE AS as_expected FROM (VALUES ('no-train'), ('aligned'), ('aligned, mixed pairs')) v(variant), (VALUES (1), (5)) ks(k)")
def align_recovery(spark, sf_dir):
    """Recall on pairs that were not trained on: near chance without training and after training on mixed pairs, over 0.9 else."""
    parts = [_aligned_recall(spark, sf_dir, mixed, n).withColumn("variant", F.lit(name)) for name, mixed, n in (("no-train", False, 0), ("aligned", False, 25), ("aligned, mixed pairs", True, 25))]
    recall = parts[0].unionByName(parts[1]).unionByName(parts[2])
    return recall.select("variant", "k", F.when(F.col("variant") == "aligned", F.col("recall") > 0.9).otherwise(F.col("recall") < 0.3).alias("as_expected"))


@query(f"""WITH h AS ({_knn_sql(5)}), n AS (SELECT e.vec_id, r, CASE WHEN (e.vec_id * 37 % 100) < r * 10 THEN (e.label + 1 + e.vec_id % 9) % 10 ELSE e.label END AS label FROM embeddings e, (VALUES (1), (2), (3), (4), (5)) rs(r)),
    hit AS (SELECT h.qid, n.r, max(CASE WHEN n.label = q.label THEN 1.0 ELSE 0.0 END) AS found FROM h JOIN n ON n.vec_id = h.doc_id JOIN embeddings q ON q.vec_id = h.qid GROUP BY h.qid, n.r)
    SELECT r AS tenths, round(avg(found), 6) AS recall FROM hit GROUP BY r""")
def noise_sweep(spark, sf_dir):
    """Labels of history wrong at five nested shares: retrieval recall at 5."""
    q, d = _split_vectors(spark, sf_dir)
    hits = vindex.topk_exact(q.select("qid", "vec"), d, 5).select("qid", "doc_id")
    wrong = F.when(F.col("doc_id") * 37 % 100 < F.col("tenths") * 10, (F.col("label") + 1 + F.col("doc_id") % 9) % 10).otherwise(F.col("label"))
    noisy = d.select("doc_id", "label", F.explode(F.sequence(F.lit(1), F.lit(5))).alias("tenths")).select("doc_id", "tenths", wrong.alias("guess"))
    per = hits.join(noisy, "doc_id").join(q.select("qid", "label"), "qid").groupBy("qid", "tenths").agg(F.max((F.col("guess") == F.col("label")).cast("double")).alias("found"))
    return per.groupBy("tenths").agg(F.round(F.avg("found"), 6).alias("recall"))


@query()
def plm_multilabel(spark, sf_dir):
    """The classifier where the knobs follow from the vector: one for each of the first ten places that holds over 0.15."""
    names = [f"place{i}" for i in range(10)]
    has = F.filter(F.transform(F.slice("vec", 1, 10), lambda x, i: F.when(x > 0.15, F.concat(F.lit("place"), i.cast("string")))), lambda k: k.isNotNull())
    v = vectors(spark, sf_dir).withColumn("knobs", has)
    model = baselines.plm_fit(v.filter("doc_id % 10 < 9"), names, 64, iters=60, rate=20.0)
    return baselines.plm_predict(model, v.filter("doc_id % 10 = 9").withColumnRenamed("doc_id", "qid"))


# ---------------------------------------------------------------- telemetry

_GRID = "SELECT unnest(generate_series((SELECT date_trunc('hour', min(ts)) FROM events), (SELECT date_trunc('hour', max(ts)) FROM events), INTERVAL 1 HOUR)) AS ts"
_HOURLY = f"""SELECT event_type || ':' || agg AS metric, g.ts AS ts, CASE agg WHEN 'count' THEN coalesce(c, 0) ELSE coalesce(s, 0) END AS value
    FROM (SELECT DISTINCT event_type FROM events) t CROSS JOIN (VALUES ('count'), ('sum')) a(agg) CROSS JOIN ({_GRID}) g
    LEFT JOIN (SELECT event_type AS et, date_trunc('hour', ts) AS h, CAST(count(value) AS DOUBLE) AS c, sum(value) AS s FROM events GROUP BY 1, 2) e ON e.et = event_type AND e.h = g.ts"""


def hourly(spark, sf_dir):
    points = telemetry.bucket(events(spark, sf_dir), "ts", "value", ["event_type"], 3600, ("count", "sum"))
    return telemetry.densify(points, ["metric"], 3600)


def _decomposed_sql(points: str, period: int) -> str:
    h = period // 2
    ends = f" - (lag(value, {h}) OVER w + lead(value, {h}) OVER w) / 2" if period % 2 == 0 else ""
    return f"""SELECT p.metric, ts, value, round(raw - centre, 9) AS seasonal, trend, round(value - round(raw - centre, 9) - trend, 6) AS resid FROM (
        SELECT *, i % {period} AS phase FROM (SELECT *, CASE WHEN i >= {h} AND i < n - {h} THEN round((sum(value) OVER (PARTITION BY metric ORDER BY ts ROWS BETWEEN {h} PRECEDING AND {h} FOLLOWING){ends}) / {period}, 9) END AS trend
          FROM (SELECT *, row_number() OVER (PARTITION BY metric ORDER BY ts) - 1 AS i, count(*) OVER (PARTITION BY metric) AS n FROM ({points})) WINDOW w AS (PARTITION BY metric ORDER BY ts))) p
      JOIN (SELECT metric, phase, raw, avg(raw) OVER (PARTITION BY metric) AS centre FROM (SELECT metric, i % {period} AS phase, avg(value - trend) AS raw FROM (
        SELECT *, CASE WHEN i >= {h} AND i < n - {h} THEN round((sum(value) OVER (PARTITION BY metric ORDER BY ts ROWS BETWEEN {h} PRECEDING AND {h} FOLLOWING){ends}) / {period}, 9) END AS trend
          FROM (SELECT *, row_number() OVER (PARTITION BY metric ORDER BY ts) - 1 AS i, count(*) OVER (PARTITION BY metric) AS n FROM ({points})) WINDOW w AS (PARTITION BY metric ORDER BY ts)) GROUP BY 1, 2)) f USING (metric, phase)"""


_DAILY = """SELECT o.m AS metric, g.ts AS ts, coalesce(v, 0) AS value FROM (SELECT DISTINCT o_orderstatus AS m FROM orders) o
    CROSS JOIN (SELECT unnest(generate_series((SELECT min(date_trunc('day', o_orderdate)) FROM orders), (SELECT max(date_trunc('day', o_orderdate)) FROM orders), INTERVAL 1 DAY)) AS ts) g
    LEFT JOIN (SELECT o_orderstatus AS s, date_trunc('day', o_orderdate) AS d, round(sum(o_totalprice), 2) AS v FROM orders GROUP BY 1, 2) x ON x.s = o.m AND x.d = g.ts"""
_EPOCH = "CAST(epoch(ts) AS BIGINT)"


def daily_revenue(spark, sf_dir):
    orders = read(spark, sf_dir, "orders", ["o_orderstatus", "o_orderdate", "o_totalprice"])
    day = F.date_trunc("day", F.col("o_orderdate").cast("timestamp"))
    sums = orders.groupBy(F.col("o_orderstatus").alias("metric"), day.alias("ts")).agg(F.round(F.sum("o_totalprice"), 2).alias("value"))
    span = orders.agg(F.min(day).alias("a"), F.max(day).alias("b"))
    grid = orders.select(F.col("o_orderstatus").alias("metric")).distinct().crossJoin(F.broadcast(span)).select("metric", F.explode(F.sequence("a", "b", F.expr("interval 1 day"))).alias("ts"))
    return grid.join(sums, ["metric", "ts"], "left").fillna(0.0, ["value"])


def _second(df):
    return df.withColumn("ts", F.unix_timestamp("ts"))


@query(f"SELECT metric, {_EPOCH} AS ts, round(value, 6) AS value FROM ({_HOURLY})")
def telemetry_hourly(spark, sf_dir):
    return _second(hourly(spark, sf_dir)).withColumn("value", F.round("value", 6))


@query("""SELECT CAST(user_id AS VARCHAR) || ':' || event_type || ':sum' AS metric, CAST(floor(epoch(ts) / 86400) * 86400 AS BIGINT) AS ts, round(sum(value), 6) AS value FROM events GROUP BY user_id, event_type, 2""")
def telemetry_user_metrics(spark, sf_dir):
    return _second(telemetry.bucket(events(spark, sf_dir), "ts", "value", ["user_id", "event_type"], 86400, ("sum",))).withColumn("value", F.round("value", 6))


_COLS = f"metric, {_EPOCH} AS ts, round(seasonal, 5) AS seasonal, trend, resid"


def _shown(df):
    return _second(df).select("metric", "ts", F.round("seasonal", 5).alias("seasonal"), "trend", "resid")


@query(f"SELECT {_COLS} FROM ({_decomposed_sql(_HOURLY, 24)})")
def decompose_classical(spark, sf_dir):
    return _shown(stl.decompose_classical(hourly(spark, sf_dir), ["metric"], 24))


@query(f"SELECT metric, {_EPOCH} AS ts, round(seasonal, 1) AS seasonal, round(trend, 1) AS trend FROM ({_decomposed_sql(_DAILY, 7)})")
def decompose_classical_daily(spark, sf_dir):
    return _second(stl.decompose_classical(daily_revenue(spark, sf_dir), ["metric"], 7)).select("metric", "ts", F.round("seasonal", 1).alias("seasonal"), F.round("trend", 1).alias("trend"))


@query(f"""SELECT metric, {_EPOCH} AS ts, round(seasonal, 6) AS seasonal, round(value - seasonal, 6) AS resid FROM (SELECT *, median(value) OVER (PARTITION BY metric, i % 24) AS seasonal FROM (SELECT *, row_number() OVER (PARTITION BY metric ORDER BY ts) - 1 AS i FROM ({_HOURLY})))""")
def decompose_median(spark, sf_dir):
    return _second(stl.decompose_median(hourly(spark, sf_dir), ["metric"], 24)).select("metric", "ts", F.round("seasonal", 6).alias("seasonal"), F.round("resid", 6).alias("resid"))


@query(f"""WITH p AS (SELECT *, row_number() OVER (PARTITION BY metric ORDER BY ts) AS i FROM ({_HOURLY}) WHERE metric LIKE '%:sum'),
    s AS (SELECT a.metric, a.ts, a.value, sum(w) AS sw, sum(w * x) AS sx, sum(w * b.value) AS sy, sum(w * x * x) AS sxx, sum(w * x * b.value) AS sxy FROM p a JOIN (SELECT d, CAST(d AS DOUBLE) AS x, pow(1 - pow(abs(d) / 37.0, 3), 3) AS w FROM range(-36, 37) r(d)) o ON TRUE JOIN p b ON b.metric = a.metric AND b.i = a.i + o.d GROUP BY 1, 2, 3)
    SELECT metric, {_EPOCH} AS ts, round((sxx * sy - sx * sxy) / (sw * sxx - sx * sx), 4) AS trend FROM s""")
def loess_trend(spark, sf_dir):
    return _second(stl.loess_trend(hourly(spark, sf_dir).filter(F.col("metric").endswith(":sum")), ["metric"], 36)).select("metric", "ts", "trend")


@query()
def decompose_stl(spark, sf_dir):
    return _shown(stl.decompose_stl(hourly(spark, sf_dir), ["metric"], 24))


_RESID = f"SELECT * FROM ({_decomposed_sql(_HOURLY, 24)}) WHERE resid IS NOT NULL"


@query(f"""WITH r AS ({_RESID}), m AS (SELECT metric, median(resid) AS mid FROM r GROUP BY 1), d AS (SELECT r.*, abs(resid - mid) AS off FROM r JOIN m USING (metric)), s AS (SELECT metric, median(off) AS mad FROM d GROUP BY 1)
    SELECT metric, {_EPOCH} AS ts, CASE WHEN mad > 0 THEN round(off / mad, 4) END AS score FROM d JOIN s USING (metric)""")
def mad_score(spark, sf_dir):
    parts = stl.decompose_classical(hourly(spark, sf_dir), ["metric"], 24).filter("resid is not null")
    return _second(esd.one_shot_score(parts, ["metric"])).select("metric", "ts", F.round("score", 4).alias("score"))


def _esd_sql(direction: str = "both", stop: str = "first", scale: float = 1.0, classic: bool = False, n: int = 696, bound: int = 13) -> str:
    tail = "both" if direction == "both" else "one"
    lam = ", ".join(f"({n}, {k}, {esd_critical(n, k, 0.05, tail)!r})" for k in range(1, bound + 1))
    low = {"both": "(mid - v[1]) >= (v[-1] - mid)", "high": "FALSE", "low": "TRUE"}[direction]
    mid = "list_avg(v)" if classic else "list_median(v)"
    spread = "list_stddev_samp(v)" if classic else f"list_median(list_transform(v, lambda x: abs(x - mid))) * {scale}"
    flag = "min(hit) OVER (PARTITION BY metric ORDER BY k)" if stop == "first" else "max(hit) OVER (PARTITION BY metric ORDER BY k DESC)"
    return f"""WITH RECURSIVE r AS ({_RESID}), s AS (
        SELECT metric, count(*) AS n, 0 AS k, list(resid ORDER BY resid, ts) AS v, list({_EPOCH} ORDER BY resid, ts) AS t, CAST(NULL AS DOUBLE) AS resid, CAST(NULL AS BIGINT) AS ts, CAST(NULL AS DOUBLE) AS score FROM r GROUP BY metric
        UNION ALL SELECT metric, n, k + 1, v[1:pos - 1] || v[pos + 1:], t[1:pos - 1] || t[pos + 1:], v[pos], t[pos], greatest(CASE WHEN low THEN mid - v[1] ELSE v[-1] - mid END, 0) / spread FROM (
          SELECT *, CASE WHEN low THEN 1 ELSE list_position(v, v[-1]) END AS pos FROM (SELECT *, {low} AS low, {spread} AS spread FROM (SELECT *, {mid} AS mid FROM s WHERE k < {bound}))) WHERE spread > 0)
      SELECT metric, CAST(k AS INT) AS k, ts, round(resid, 4) AS resid, round(score, 4) AS score, round(CAST(lam AS DOUBLE), 6) AS "lambda", {flag} = 1 AS is_anomaly FROM (
        SELECT s.*, l.lam, CASE WHEN score > lam THEN 1 ELSE 0 END AS hit FROM s JOIN (VALUES {lam}) l(n, k, lam) ON l.n = s.n AND l.k = s.k WHERE s.k > 0)"""


def _esd(spark, sf_dir, **how):
    parts = stl.decompose_classical(hourly(spark, sf_dir), ["metric"], 24)
    found = _second(esd.detect(parts, ["metric"], **how))
    return found.select("metric", "k", "ts", F.round("resid", 4).alias("resid"), F.round("score", 4).alias("score"), F.round("lambda", 6).alias("lambda"), "is_anomaly")


@query(_esd_sql())
def esd_anomalies(spark, sf_dir):
    return _esd(spark, sf_dir)


@query(_esd_sql("high"))
def esd_high_only(spark, sf_dir):
    return _esd(spark, sf_dir, direction="high")


@query(_esd_sql(stop="last"))
def esd_last_significant(spark, sf_dir):
    return _esd(spark, sf_dir, stop="last_significant")


@query(_esd_sql(scale=1.4826))
def esd_calibrated(spark, sf_dir):
    return _esd(spark, sf_dir, scale=1.4826)


@query(_esd_sql(classic=True))
def esd_mean_std(spark, sf_dir):
    return _esd(spark, sf_dir, center="mean", spread="std")


@query()
def esd_redecomposed(spark, sf_dir):
    parts = stl.decompose_none(hourly(spark, sf_dir))
    found = esd.detect(parts, ["metric"], redecompose=lambda y: stl.stl(y, 24)[2])
    return _second(found).select("metric", "k", "ts", F.round("score", 4).alias("score"), "is_anomaly")


_SCORED = ORACLE_SQL["mad_score"]


@query(f"""WITH a AS (SELECT metric, ts, score FROM ({_SCORED}) WHERE score > 5), f AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY metric ORDER BY ts) <= 7200 THEN 0 ELSE 1 END AS fresh FROM a),
    e AS (SELECT *, sum(fresh) OVER (PARTITION BY metric ORDER BY ts) AS episode FROM f) SELECT metric, CAST(episode AS BIGINT) AS episode, min(ts) AS start, max(ts) AS "end", count(*) AS n, max(score) AS peak FROM e GROUP BY metric, episode""")
def anomaly_episodes(spark, sf_dir):
    parts = stl.decompose_classical(hourly(spark, sf_dir), ["metric"], 24).filter("resid is not null")
    scored = esd.one_shot_score(parts, ["metric"]).withColumn("score", F.round("score", 4)).filter("score > 5")
    e = telemetry.episodes(scored, ["metric"], 7200)
    return e.select("metric", "episode", F.unix_timestamp("start").alias("start"), F.unix_timestamp("end").alias("end"), "n", "peak")


_WORDS = fixtures.values([(f"{t}:{a}", w) for t, (w, _) in fixtures.METRIC_WORDS.items() for a in ("count", "sum")])
_METRIC_KNOBS = fixtures.values([(f"{t}:{a}", k) for t, (_, ks) in fixtures.METRIC_WORDS.items() for a in ("count", "sum") for k in ks])


def metric_dictionary(spark):
    rows = [(f"{t}:{a}", w, k) for t, (w, ks) in fixtures.METRIC_WORDS.items() for a in ("count", "sum") for k in ks]
    return spark.createDataFrame(rows, "metric string, explanation string, knob string")


_TEXT = f"""WITH a AS (SELECT * FROM ({_esd_sql()}) WHERE is_anomaly), p AS ({_HOURLY}),
    ab AS (SELECT a.metric, arg_max(p.value, struct_pack(s := round(a.score, 9), t := -a.ts)) AS abnormal FROM a JOIN p ON p.metric = a.metric AND CAST(epoch(p.ts) AS BIGINT) = a.ts GROUP BY 1),
    nm AS (SELECT metric, quantile_cont(value, 0.05) AS normal FROM p GROUP BY 1), k AS (SELECT metric, string_agg(knob, ', ' ORDER BY knob) AS knobs FROM (VALUES {_METRIC_KNOBS}) v(metric, knob) GROUP BY 1)
    SELECT metric, 'Metric ' || metric || ' (' || coalesce(w.explanation, 'no explanation') || ') moved from its usual ' || CAST(CAST(round(normal, 2) AS DECIMAL(18,2)) AS VARCHAR) || ' to ' || CAST(CAST(round(abnormal, 2) AS DECIMAL(18,2)) AS VARCHAR)
      || coalesce('; related settings: ' || knobs, '') || '.' AS text FROM ab JOIN nm USING (metric) LEFT JOIN (VALUES {_WORDS}) w(metric, explanation) USING (metric) LEFT JOIN k USING (metric)"""


def described(spark, sf_dir, method="classical"):
    return debugging.telemetry_sentences(hourly(spark, sf_dir), metric_dictionary(spark), method=method)


@query(_TEXT)
def telemetry_text(spark, sf_dir):
    return described(spark, sf_dir).select("metric", "text")


_QVEC = "list_transform(range(0, 64), lambda i: CAST(len(list_filter(list_transform(regexp_extract_all(lower(text), '[a-z]{3,}'), lambda t: CAST(concat('0x', md5(t)[1:4]) AS BIGINT) % 64), lambda p: p = i)) AS DOUBLE))"


def question_vectors(spark, sf_dir):
    return debugging.encode(corpus.question_pairs(read(spark, sf_dir, "conversations")).select("qid", F.col("question").alias("text")))


@query(f"""WITH q AS (SELECT qid, {_QVEC} AS v FROM (SELECT qid, question AS text FROM ({_PAIRS}))), d AS (SELECT metric, {_QVEC} AS v FROM ({_TEXT})),
    x AS (SELECT qid, metric, round(sqrt(list_sum(list_transform(list_zip(q.v, d.v), lambda z: pow(z[1] / nq - z[2] / nd, 2)))), 6) AS dist FROM (SELECT *, sqrt(list_inner_product(v, v)) AS nq FROM q) q, (SELECT *, sqrt(list_inner_product(v, v)) AS nd FROM d) d WHERE nq > 0 AND nd > 0)
    SELECT qid, min(dist) AS dist, count(*) AS n FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist) AS r FROM x) WHERE r <= 3 GROUP BY qid""")
def telemetry_select(spark, sf_dir):
    desc = debugging.encode(described(spark, sf_dir))
    hits = describe.select(question_vectors(spark, sf_dir), desc, 3)
    return hits.groupBy("qid").agg(F.min("dist").alias("dist"), F.count(F.lit(1)).alias("n"))


@query("SELECT * FROM (VALUES ('stl', CAST(1 AS DOUBLE), CAST(1 AS DOUBLE), CAST(1 AS DOUBLE)), ('classical', 1, 1, 1)) v(method, \"precision\", recall, f1)")
def planted_anomalies(spark, sf_dir):
    """Sine, slope and real residuals with spikes at known places: all of them are found, and nothing else."""
    base = stl.decompose_classical(hourly(spark, sf_dir).filter("metric = 'click:sum'"), ["metric"], 24).filter("resid is not null")
    i = F.row_number().over(Window.partitionBy("metric").orderBy("ts")) - 1
    spike = F.when(F.col("i") % 97 == 50, F.lit(400.0)).when(F.col("i") % 131 == 70, F.lit(-400.0)).otherwise(F.lit(0.0))
    points = base.withColumn("i", i).withColumn("spike", spike).select("metric", "ts", (100 + 20 * F.sin(2 * 3.141592653589793 * F.col("i") / 24) + 0.05 * F.col("i") + 0.1 * F.col("resid") + F.col("spike")).alias("value"), "spike")
    truth = points.filter("spike <> 0").select("metric", "ts")
    out = None
    for name, parts in (("stl", stl.decompose_stl(points.drop("spike"), ["metric"], 24, s_win="periodic")), ("classical", stl.decompose_classical(points.drop("spike"), ["metric"], 24))):
        found = esd.detect(parts, ["metric"], scale=1.4826, bound=20).filter("is_anomaly")
        row = metrics.detection(found, truth, ["metric", "ts"]).select(F.lit(name).alias("method"), *(F.round(c, 6).alias(c) for c in ("precision", "recall", "f1")))
        out = row if out is None else out.unionByName(row)
    return out


@query("SELECT 21600 AS step, (SELECT count(*) FROM (SELECT DISTINCT event_type, floor(epoch(ts) / 21600) FROM events)) AS buckets UNION ALL SELECT 3600, (SELECT count(*) FROM (SELECT DISTINCT event_type, floor(epoch(ts) / 3600) FROM events)) UNION ALL SELECT 600, (SELECT count(*) FROM (SELECT DISTINCT event_type, floor(epoch(ts) / 600) FROM events)) UNION ALL SELECT 60, (SELECT count(*) FROM (SELECT DISTINCT event_type, floor(epoch(ts) / 60) FROM events))")
def scal_interval(spark, sf_dir):
    e, out = events(spark, sf_dir), None
    for step in (21600, 3600, 600, 60):
        row = telemetry.bucket(e, "ts", "value", ["event_type"], step, ("count",)).agg(F.lit(step).alias("step"), F.count(F.lit(1)).alias("buckets"))
        out = row if out is None else out.unionAll(row)
    return out


@query("WITH m AS (SELECT DISTINCT user_id, event_type FROM events), r AS (SELECT *, row_number() OVER (ORDER BY CAST(user_id AS VARCHAR) || ':' || event_type || ':sum') AS r FROM m) SELECT CAST(s AS INT) AS metrics, count(*) AS points FROM (VALUES (5), (20), (750)) v(s) JOIN r ON r.r <= s JOIN (SELECT DISTINCT user_id, event_type, floor(epoch(ts) / 86400) AS d FROM events) USING (user_id, event_type) GROUP BY s")
def scal_metrics(spark, sf_dir):
    points = telemetry.bucket(events(spark, sf_dir), "ts", "value", ["user_id", "event_type"], 86400, ("sum",))
    out = None
    for m in (5, 20, 750):
        some = points.select("metric").distinct().orderBy("metric").limit(m)
        row = points.join(some, "metric").agg(F.lit(m).alias("metrics"), F.count(F.lit(1)).alias("points"))
        out = row if out is None else out.unionAll(row)
    return out


# ---------------------------------------------------------------- prompts, reasoning, baselines


@query(f"""SELECT qid, 'You advise on database settings.' || chr(10) || 'Retrieved:' || chr(10) || docs || chr(10) || 'Question: ' || question || chr(10) || 'Name the settings to change as a JSON list of strings.' AS text
    FROM ({_PAIRS}) JOIN (SELECT qid, string_agg('- knob ' || knob, chr(10) ORDER BY r) AS docs FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY df, knob) AS r FROM ({_LABELS})) WHERE r <= 3 GROUP BY qid) USING (qid)""")
def prompt_build(spark, sf_dir):
    q = labelled_questions(spark, sf_dir, None).select("qid", "text")
    labels = corpus.label(corpus.question_pairs(read(spark, sf_dir, "conversations")), "answer", catalog(spark, sf_dir), ["qid"])
    ranked = labels.select("qid", F.explode("knobs").alias("knob")).join(F.broadcast(catalog(spark, sf_dir).select("knob", "df")), "knob")
    ranked = ranked.withColumn("rank", F.row_number().over(Window.partitionBy("qid").orderBy("df", "knob"))).filter("rank <= 3")
    return prompt.build(q, ranked.select("qid", "rank", F.concat(F.lit("knob "), "knob").alias("text"))).select("qid", "text")


@query(f"""SELECT qid, md5('You advise on database settings.' || chr(10) || 'Choose among: ' || (SELECT string_agg(knob, ', ' ORDER BY knob) FROM ({CATALOG})) || chr(10) || 'Question: ' || question || chr(10) || 'Name the settings to change as a JSON list of strings.') AS text_md5 FROM ({_PAIRS})""")
def prompt_all_knobs(spark, sf_dir):
    q = corpus.question_pairs(read(spark, sf_dir, "conversations")).select("qid", F.col("question").alias("text"))
    return prompt.build_all_knobs(q, catalog(spark, sf_dir)).select("qid", F.md5("text").alias("text_md5"))


#: Names that recorded answers use: those of the reference catalogue, and one that it does not have.
_ASKED = [k[0] for k in fixtures.KNOBS] + ["warp_speed"]
_RECORDED = f"""SELECT event_id AS qid, CASE WHEN form = 0 THEN 'list' ELSE 'dict' END AS kind, CASE form WHEN 0 THEN '["' || name || '", "sync_binlog"]' WHEN 1 THEN replace(named, '}}', ', "sync_binlog": 1}}')
    WHEN 2 THEN 'Try to lower ' || name || '.' WHEN 3 THEN named || ' hope this helps' WHEN 4 THEN replace(replace(named, ': ', ': ['), '}}', ']}}') WHEN 7 THEN '' WHEN 8 THEN '{{"' || name || '": "ROW"}}' ELSE named END AS raw
    FROM (SELECT event_id, event_id % 9 AS form, name, replace(props, '"k"', '"' || name || '"') AS named FROM (SELECT *, {_ASKED}[CAST(user_id % {len(_ASKED)} AS INT) + 1] AS name FROM events))"""
_PARSED = f"""SELECT qid, kind, ok, CASE WHEN ok AND kind = 'list' THEN list_filter(CAST(j AS VARCHAR[]), lambda x, i: list_position(CAST(j AS VARCHAR[]), x) = i) WHEN ok THEN list_sort(json_keys(j)) ELSE [] END AS knobs, CASE WHEN ok AND kind = 'dict' THEN j END AS config FROM (SELECT *, coalesce(CASE
    WHEN kind = 'list' AND json_type(j) = 'ARRAY' THEN len(list_filter(CAST(j AS JSON[]), lambda x: json_type(x) <> 'VARCHAR')) = 0
    WHEN kind = 'dict' AND json_type(j) = 'OBJECT' THEN len(list_filter(json_keys(j), lambda k: json_type(json_extract(j, '$."' || k || '"')) IN ('ARRAY', 'OBJECT', 'NULL'))) = 0 END, FALSE) AS ok
    FROM (SELECT *, CASE WHEN json_valid(raw) THEN CAST(raw AS JSON) END AS j FROM ({_RECORDED})))"""
_DOMAINS = fixtures.values([(k, kind, lo, hi, c and "|".join(c)) for k, kind, lo, hi, c, _ in fixtures.KNOBS])


def recorded_answers(spark, sf_dir):
    """(qid, raw, kind): one answer for each event, which gives the value; its number says in which of nine forms, good and bad,
    its user which setting is named."""
    e = read(spark, sf_dir, "events", ["event_id", "user_id", "props"])
    name = F.element_at(F.array(*map(F.lit, _ASKED)), (F.col("user_id") % len(_ASKED) + 1).cast("int"))
    named = F.replace("props", F.lit('"k"'), F.concat(F.lit('"'), name, F.lit('"')))
    form, swap = F.col("event_id") % 9, lambda c, a, b: F.replace(c, F.lit(a), F.lit(b))
    forms = {0: F.concat(F.lit('["'), name, F.lit('", "sync_binlog"]')), 1: swap(named, "}", ', "sync_binlog": 1}'), 2: F.concat(F.lit("Try to lower "), name, F.lit(".")), 3: F.concat(named, F.lit(" hope this helps")), 4: swap(swap(named, ": ", ": ["), "}", "]}"), 7: F.lit(""), 8: F.concat(F.lit('{"'), name, F.lit('": "ROW"}'))}
    raw = F.when(form == 0, forms[0])
    for i, text in list(forms.items())[1:]:
        raw = raw.when(form == i, text)
    return e.select(F.col("event_id").alias("qid"), raw.otherwise(named).alias("raw"), F.when(form == 0, "list").otherwise("dict").alias("kind"))


def parsed_answers(spark, sf_dir):
    a = recorded_answers(spark, sf_dir)
    return reason.parse(a.filter("kind = 'list'"), "list").unionByName(reason.parse(a.filter("kind = 'dict'"), "dict"))


@query(f"SELECT qid, ok, array_to_string(knobs, ',') AS knobs FROM ({_PARSED})")
def answer_parse(spark, sf_dir):
    return parsed_answers(spark, sf_dir).select("qid", "ok", F.concat_ws(",", "knobs").alias("knobs"))


@query(f"""SELECT qid, knob, CASE WHEN kind IS NULL THEN 'unknown' WHEN kind = 'numeric' AND TRY_CAST(value AS DOUBLE) BETWEEN lo AND hi THEN 'ok' WHEN kind <> 'numeric' AND list_contains(string_split(choices, '|'), lower(value)) THEN 'ok' ELSE 'outside' END AS status
    FROM (SELECT qid, knob, json_extract_string(config, '$."' || knob || '"') AS value FROM (SELECT qid, config, unnest(knobs) AS knob FROM ({_PARSED}) WHERE kind = 'dict')) LEFT JOIN (VALUES {_DOMAINS}) k(knob, kind, lo, hi, choices) USING (knob)""")
def answer_validate(spark, sf_dir):
    answers = reason.parse(recorded_answers(spark, sf_dir).filter("kind = 'dict'"), "dict").filter("ok")
    return reason.validate(answers, fixtures.knobs(spark)).select("qid", "knob", "status")


_VOTE = f"""SELECT qid, place, knob, score FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, knob) AS place FROM (SELECT h.qid, CAST(e.label AS VARCHAR) AS knob, round(sum(1.0 / (60 + h.rank)), 9) AS score FROM ({_knn_sql(10)}) h JOIN embeddings e ON e.vec_id = h.doc_id GROUP BY 1, 2)) WHERE place <= 5"""


@query(_VOTE.replace("score FROM (SELECT *", "round(score, 6) AS score FROM (SELECT *", 1))
def evidence_vote(spark, sf_dir):
    q, d = _split_vectors(spark, sf_dir)
    return reason.evidence_vote(vindex.topk_exact(q.select("qid", "vec"), d, 10)).withColumn("score", F.round("score", 6))


@query()
def runtime_breakdown(spark, sf_dir):
    """Mean seconds a question of retrieval, telemetry and reasoning, and their total."""
    from .methods import main_corpus

    questions, docs = main_corpus(spark, sf_dir)
    hits = vindex.topk_blocked(questions.select("qid", "vec"), docs, 5).persist()
    stages = {
        "retrieval": lambda: hits,
        "telemetry": lambda: describe.select(questions.select("qid", "vec"), debugging.encode(described(spark, sf_dir)), 3),
        "reasoning": lambda: reason.EvidenceVote().answer(hits),
    }
    seconds = experiments.runtime(stages, questions.count())
    hits.unpersist()
    return spark.createDataFrame(seconds, "stage string, seconds double")


_STYLED = "chr(10) || 'Question: ' || question || chr(10) || 'Name the settings to change as a JSON list of strings.'"


@query(f"""SELECT qid, style, md5(opening || {_STYLED}) AS text_md5 FROM ({_PAIRS}) CROSS JOIN (VALUES ('plain', 'You advise on database settings.'),
    ('cot', 'You advise on database settings. Reason in small steps before you answer.'), ('decompose', 'You advise on database settings. Split the problem into parts, solve each, then combine.')) s(style, opening)""")
def prompt_styles(spark, sf_dir):
    """Prompts without evidence: plain, step by step, task decomposition."""
    q = corpus.question_pairs(read(spark, sf_dir, "conversations")).select("qid", F.col("question").alias("text"))
    parts = [prompt.build(q, style=s).select("qid", F.lit(s).alias("style"), F.md5("text").alias("text_md5")) for s in prompt.STYLES]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query(f"""SELECT qid, to_json(struct_pack(instruction := 'Name the settings to change as a JSON list of strings.', "input" := question, "output" := '[' || string_agg('"' || knob || '"', ',' ORDER BY knob) || ']')) AS line FROM ({_LABELS}) JOIN ({_PAIRS}) USING (qid) GROUP BY qid, question""")
def sft_export(spark, sf_dir):
    return baselines.sft_pairs(labelled_questions(spark, sf_dir))


def part_settings(spark, sf_dir):
    """(knobs, functions, issues): parts as settings. Type and size name one, its first part describes it, its two commonest part
    names are its functions, and the two commonest types and brands of a name are what goes wrong with it. All are small."""
    part = read(spark, sf_dir, "part", ["p_partkey", "p_name", "p_brand", "p_type", "p_size"])
    part = part.select("p_partkey", "p_name", F.concat(F.lower("p_type"), F.lit("_"), F.col("p_size").cast("string")).alias("knob"), F.concat(F.lower("p_type"), F.lit(" "), F.lower("p_brand")).alias("issue"))
    part = stored(part, "part")
    knobs = part.groupBy("knob").agg(F.min_by("p_name", "p_partkey").alias("description")).withColumn("dbms", F.lit("parts"))

    def commonest(key, item):
        n = part.groupBy(key, item).agg(F.count(F.lit(1)).alias("n"))
        top = n.groupBy(key).agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("n")).alias("n"), F.col(item).alias("item")))), 1, 2).alias("top"))
        return {r[key]: [t["item"] for t in r["top"]] for r in top.collect()}

    return stored(knobs, "settings"), commonest("knob", "p_name"), commonest("p_name", "issue")


def _augmented(settings, name):
    knobs, functions, issues = settings
    gen = augment.TemplateGenerator(functions, issues, fixtures.BEHAVIOURS)
    _, chain = augment.logic_chain(knobs, gen)
    if name == "chain":
        return chain
    return (augment.cot if name == "cot" else augment.direct)(knobs, gen, chain.count())


_ID = "CAST('0x' || md5(method || '|' || knob || '|' || text)[1:15] AS BIGINT) AS doc_id"
_SETTINGS = "SELECT p_partkey, p_name, lower(p_type) || '_' || p_size AS knob, lower(p_type) || ' ' || lower(p_brand) AS issue FROM part"
_TOP = lambda key, item: f"(SELECT {key} AS k, {item} AS v, row_number() OVER (PARTITION BY {key} ORDER BY count(*) DESC, {item}) - 1 AS n FROM ({_SETTINGS}) GROUP BY {key}, {item})"
_CHAIN_SQL = f"""SELECT {_ID}, 'parts' AS dbms, text, knob AS knobs, method FROM (SELECT 'chain' AS method, f.k AS knob,
    'While ' || f.v || ' is at work I see that ' || i.v || ' misbehaves; it looks like ' || i.v || '. Which settings should I look at?' AS text
    FROM {_TOP("knob", "p_name")} f JOIN {_TOP("p_name", "issue")} i ON i.k = f.v WHERE f.n < 2 AND i.n < 2)"""


def _volume_sql(method: str, before: str, between: str, after: str) -> str:
    return f"""SELECT {_ID}, 'parts' AS dbms, text, knob AS knobs, method FROM (SELECT '{method}' AS method, knob, '{before}' || description || '{between}' || n || '{after}' AS text
        FROM (SELECT knob, arg_min(p_name, p_partkey) AS description FROM ({_SETTINGS}) GROUP BY knob), range(0, 12) r(n) ORDER BY n, md5(knob), knob LIMIT (SELECT count(*) FROM ({_CHAIN_SQL})))"""


_COT_SQL = _volume_sql("cot", "Step by step: the setting described as ''", "'' may be wrong, case ", ". What should I change?")
_DIRECT_SQL = _volume_sql("direct", "How do I use the setting described as ''", "'', variant ", "?")


@query(_CHAIN_SQL)
def augment_chain(spark, sf_dir):
    return _augmented(part_settings(spark, sf_dir), "chain").withColumn("knobs", F.concat_ws(",", "knobs"))


@query(_COT_SQL)
def augment_cot(spark, sf_dir):
    return _augmented(part_settings(spark, sf_dir), "cot").withColumn("knobs", F.concat_ws(",", "knobs"))


@query(_DIRECT_SQL)
def augment_direct(spark, sf_dir):
    return _augmented(part_settings(spark, sf_dir), "direct").withColumn("knobs", F.concat_ws(",", "knobs"))


@query(f"""WITH t AS ({_CHAIN_SQL} UNION ALL {_COT_SQL} UNION ALL {_DIRECT_SQL}), w AS (SELECT method, string_split_regex(lower(trim(text)), '\\s+') AS w FROM t),
    one AS (SELECT method, round(count(DISTINCT g) / count(g), 6) AS distinct_1 FROM (SELECT method, unnest(w) AS g FROM w) GROUP BY 1),
    two AS (SELECT method, round(count(DISTINCT g) / count(g), 6) AS distinct_2 FROM (SELECT method, unnest(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS g FROM w) GROUP BY 1),
    v AS MATERIALIZED (SELECT method, doc_id, list_transform(v, lambda x: x / sqrt(list_inner_product(v, v))) AS v FROM (SELECT method, doc_id, {_QVEC} AS v FROM t)), d AS (SELECT a.method, a.doc_id, min(round(list_distance(a.v, b.v), 6)) AS dist
      FROM v a JOIN v b ON a.method = b.method AND a.doc_id <> b.doc_id GROUP BY 1, 2)
    SELECT method, distinct_1, distinct_2, mean_distance FROM one JOIN two USING (method) JOIN (SELECT method, round(avg(dist), 6) AS mean_distance FROM d GROUP BY 1) USING (method)""")
def augment_diversity(spark, sf_dir):
    """Distinct n-grams, and the mean distance of a synthetic question to the nearest other one."""
    settings, out = part_settings(spark, sf_dir), None
    for name in ("chain", "cot", "direct"):
        texts = stored(_augmented(settings, name), "texts")
        row = metrics.diversity(texts).crossJoin(metrics.nearest_distance(texts)).withColumn("method", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


# ---------------------------------------------------------------- measures at scale

_TRUTH = "SELECT DISTINCT l_orderkey AS qid, l_partkey AS knob FROM lineitem WHERE l_returnflag <> 'N'"
_PRED = "SELECT DISTINCT l_orderkey AS qid, l_partkey AS knob FROM lineitem WHERE l_linestatus = 'F'"


def _prf_sql(pred: str, truth: str) -> str:
    return f"""SELECT qid, count(p) AS n_pred, count(t) AS n_true, count(p + t) AS n_hit, CASE WHEN count(p) > 0 THEN count(p + t) / count(p) ELSE 0.0 END AS "precision", CASE WHEN count(t) > 0 THEN count(p + t) / count(t) ELSE 0.0 END AS recall,
        CASE WHEN count(p + t) > 0 THEN 2.0 * count(p + t) / (count(p) + count(t)) ELSE 0.0 END AS f1 FROM (SELECT qid, knob, 1 AS p FROM ({pred})) FULL JOIN (SELECT qid, knob, 1 AS t FROM ({truth})) USING (qid, knob) GROUP BY qid"""


_MACRO = """count(CASE WHEN n_true > 0 THEN 1 END) AS questions, count(CASE WHEN n_true = 0 THEN 1 END) AS without_truth, round(avg(CASE WHEN n_true > 0 THEN "precision" END), 6) AS "precision", round(avg(CASE WHEN n_true > 0 THEN recall END), 6) AS recall, round(avg(CASE WHEN n_true > 0 THEN f1 END), 6) AS f1"""


def _sets(spark, sf_dir):
    l = read(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_returnflag", "l_linestatus"])  # noqa: E741
    rows = lambda where: l.filter(where).select(F.col("l_orderkey").alias("qid"), F.col("l_partkey").alias("knob"))
    return rows("l_linestatus = 'F'"), rows("l_returnflag <> 'N'")


@query(f"SELECT {_MACRO} FROM ({_prf_sql(_PRED, _TRUTH)})")
def set_prf(spark, sf_dir):
    return metrics.macro(metrics.prf(*_sets(spark, sf_dir)))


@query(f"""SELECT round(sum(n_hit) / sum(n_pred), 6) AS "precision", round(sum(n_hit) / sum(n_true), 6) AS recall, round(2.0 * sum(n_hit) / (sum(n_pred) + sum(n_true)), 6) AS f1 FROM ({_prf_sql(_PRED, _TRUTH)}) WHERE n_true > 0""")
def set_prf_micro(spark, sf_dir):
    return metrics.micro(metrics.prf(*_sets(spark, sf_dir)))


_BUCKET = "SELECT knob, ntile(3) OVER (ORDER BY uses DESC, knob) AS bucket FROM (SELECT l_partkey AS knob, count(*) AS uses FROM lineitem GROUP BY 1)"
_IN = lambda s: f"SELECT CAST(qid AS VARCHAR) || '/' || bucket AS qid, knob FROM ({s}) JOIN ({_BUCKET}) USING (knob)"


@query(f"SELECT CAST(split_part(qid, '/', 2) AS INT) AS bucket, {_MACRO} FROM ({_prf_sql(_IN(_PRED), _IN(_TRUTH))}) GROUP BY 1")
def prf_by_frequency(spark, sf_dir):
    return metrics.by_frequency(*_sets(spark, sf_dir), read(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("knob")))


@query(f"""WITH t AS ({_TRUTH}), p AS ({_PRED}), s AS (SELECT qid, count(p.knob) = count(*) AS solved FROM t LEFT JOIN p USING (qid, knob) GROUP BY qid)
    SELECT kind, count(*) AS questions, round(avg(CAST(solved AS DOUBLE)), 6) AS success_rate FROM (SELECT DISTINCT qid, p_type AS kind FROM t JOIN part ON p_partkey = knob) JOIN s USING (qid) GROUP BY kind""")
def success_by_kind(spark, sf_dir):
    kinds = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("knob"), F.col("p_type").alias("kind"))
    return metrics.by_kind(*_sets(spark, sf_dir), kinds)


@query(f"""WITH t AS ({_TRUTH}), p AS ({_PRED}) SELECT count(*) AS questions, round(avg(CAST(solved AS DOUBLE)), 6) AS success_rate FROM (SELECT qid, count(p.knob) = count(*) AS solved FROM t LEFT JOIN p USING (qid, knob) GROUP BY qid)""")
def success_rate(spark, sf_dir):
    return metrics.success_rate(*_sets(spark, sf_dir))


@query(f"SELECT round(avg(n), 6) AS mean_size FROM (SELECT count(*) AS n FROM ({_PRED}) GROUP BY qid)")
def mean_set_size(spark, sf_dir):
    pred, _ = _sets(spark, sf_dir)
    return metrics.mean_set_size(pred.groupBy("qid").agg(F.collect_set("knob").alias("knobs")))


@query(f"""SELECT model, count(*) AS prompts, round(avg(n), 6) AS mean_tokens, round(avg(n * usd / 1000), 9) AS usd FROM (SELECT len(list_filter(string_split_regex(trim(question), '\\s+'), lambda w: w <> '')) AS n FROM ({_PAIRS})) CROSS JOIN (VALUES ('small', 0.5), ('large', 10.0)) p(model, usd) GROUP BY model""")
def cost_per_question(spark, sf_dir):
    prices = spark.createDataFrame(fixtures.PRICES, "model string, usd_per_1k_in double, usd_per_1k_out double")
    return metrics.cost(corpus.question_pairs(read(spark, sf_dir, "conversations")).select(F.col("question").alias("text")), prices)


@query("""SELECT o_orderpriority AS strategy, CAST(o_custkey % 7 AS VARCHAR) AS expert, round(avg(CAST(o_orderstatus = 'F' AS INT)), 6) AS success, round(avg(CAST(day(o_orderdate) AS DOUBLE)), 6) AS minutes FROM orders GROUP BY 1, 2""")
def expert_summary(spark, sf_dir):
    """Orders as cases: the priority is the strategy, one of seven desks the expert, a finished order is solved."""
    orders = read(spark, sf_dir, "orders", ["o_orderpriority", "o_custkey", "o_orderstatus", "o_orderdate"])
    cases = orders.select(F.col("o_orderpriority").alias("strategy"), (F.col("o_custkey") % 7).cast("string").alias("expert"), (F.col("o_orderstatus") == "F").cast("int").alias("solved"), F.dayofmonth("o_orderdate").cast("double").alias("minutes"))
    return experiments.expert_table(cases)


@query(f"""WITH p AS MATERIALIZED ({_PARSED}) SELECT (SELECT round(avg(CASE WHEN ok THEN 0.0 ELSE 1.0 END), 6) FROM p) AS format_failures,
    (SELECT round(avg(CASE WHEN known IS NULL THEN 1.0 ELSE 0.0 END), 6) FROM (SELECT unnest(knobs) AS knob FROM p) LEFT JOIN (SELECT knob, 1 AS known FROM (VALUES {_DOMAINS}) v(knob, kind, lo, hi, choices)) USING (knob)) AS hallucinated""")
def failure_rates(spark, sf_dir):
    return metrics.failure_rates(parsed_answers(spark, sf_dir), fixtures.knobs(spark))


QUERIES.update(RELATIONAL)
ORACLE_SQL.update(RELATIONAL_SQL)
