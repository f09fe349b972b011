"""Corpus preparation: catalogue, sentences, labels, splits, statistics."""

from __future__ import annotations

import re
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SENTENCE_END = r"[.!?]+\s+|\n+"
TERM = "[a-z]{4,}"


def terms(text: Column) -> Column:
    """Distinct catalogue-shaped tokens of a text."""
    return F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit(TERM), F.lit(0)))


def term_catalog(docs: DataFrame, top: int, dbms: str, low: float = 0.02, high: float = 0.10) -> DataFrame:
    """(dbms, knob, kind, df): the `top` terms whose document share lies between low and high."""
    total = docs.agg(F.count(F.lit(1)).alias("n"))
    df = docs.select(F.explode(terms(F.col("text"))).alias("knob")).groupBy("knob").agg(F.count(F.lit(1)).alias("df"))
    inside = df.crossJoin(F.broadcast(total)).filter((F.col("df") >= low * F.col("n")) & (F.col("df") <= high * F.col("n")))  # one row
    kind = F.element_at(F.array(*map(F.lit, ("numeric", "categorical", "boolean"))), F.length("knob") % 3 + 1)
    return inside.orderBy(F.desc("df"), "knob").limit(top).select(F.lit(dbms).alias("dbms"), "knob", kind.alias("kind"), "df")


def plain_html(html: Column) -> Column:
    body = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    body = F.regexp_replace(body, r"<[^>]*>", " ")
    for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
        body = F.replace(body, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(body, r"[ \t\r\f]+", " "))


def split_sentences(df: DataFrame, text_col: str, id_col: str) -> DataFrame:
    """(doc_id, sent_no, text): non-empty sentences with their place; other columns are left behind."""
    parts = df.select(F.col(id_col).alias("doc_id"), F.posexplode(F.split(F.col(text_col), SENTENCE_END)).alias("sent_no", "text"))
    return parts.withColumn("text", F.trim("text")).filter("text <> ''")


def label(df: DataFrame, text_col: str, knobs: DataFrame, keys: list[str], limit: int | None = None) -> DataFrame:
    """keys + knobs: the catalogue terms in each text, sorted; with a limit the rarest ones. Texts without any are dropped.

    Candidate tokens are exploded and meet the catalogue in one hash join (a catalogue is hundreds of rows)."""
    hits = df.select(*keys, F.explode(terms(F.col(text_col))).alias("knob")).join(F.broadcast(knobs.select("knob", "df")), "knob")
    found = hits.groupBy(*keys).agg(F.array_sort(F.collect_set(F.struct("df", "knob"))).alias("found"))
    chosen = F.col("found") if limit is None else F.slice("found", 1, limit)
    return found.select(*keys, F.array_sort(F.transform(chosen, lambda s: s["knob"])).alias("knobs"))


def label_rows(df: DataFrame, text_col: str, knobs: DataFrame, limit: int) -> DataFrame:
    """df with the rarest `limit` catalogue terms of each text in knobs, sorted; rows without any are dropped.

    As label(), where no other row is needed: the catalogue (hundreds of rows) goes to the tasks and rows stay where they are."""
    df_of = {r["knob"]: r["df"] for r in knobs.select("knob", "df").collect()}
    shared = df.sparkSession.sparkContext.broadcast(df_of)
    term = re.compile(TERM)

    def pick(texts: pa.Array) -> pa.Array:
        known, out = shared.value, []
        for t in texts.to_pylist():
            found = {x for x in term.findall(t or "") if x in known}
            out.append(sorted(sorted(found, key=lambda x: (known[x], x))[:limit]) or None)
        return pa.array(out, pa.list_(pa.string()))

    return df.withColumn("knobs", F.arrow_udf(pick, "array<string>")(F.lower(F.col(text_col)))).filter("knobs is not null")


#: Statements of a setting: "name = value", "set name to value", "turn on/off name".
SETTINGS = (
    (r"([a-z][a-z0-9_.]{2,})\s*[=:]\s*['\"]?([A-Za-z0-9_.%-]+)", 1, 2, None),
    (r"(?i)\bset\s+(?:the\s+)?([a-z][a-z0-9_.]{2,})\s+to\s+['\"]?([A-Za-z0-9_.%-]+)", 1, 2, None),
    (r"(?i)\b(?:turn|switch)(?:ing)?\s+(?:on|off)\s+([a-z][a-z0-9_.]{2,})", 1, None, r"(?i)\b(?:turn|switch)(?:ing)?\s+(on|off)\s"),
)


def _statement(pattern: str, name: int, value: int | None, mode: str | None):
    """From a matched statement to (knob, value)."""

    def read(m: Column) -> Column:
        stated = F.rtrim(F.regexp_extract(m, pattern, value), F.lit(".")) if value else F.lower(F.regexp_extract(m, mode, 1))
        return F.struct(F.lower(F.regexp_extract(m, pattern, name)).alias("knob"), stated.alias("value"))

    return read


def extract_config(df: DataFrame, text_col: str, knobs: DataFrame, keys: list[str]) -> DataFrame:
    """keys + config (map) + knobs: settings stated in a text whose name is in the catalogue; the last statement wins."""
    found = []
    for rank, form in enumerate(SETTINGS):
        whole = F.regexp_extract_all(F.col(text_col), F.lit(form[0]), F.lit(0))
        found.append(df.select(*keys, F.lit(rank).alias("form"), F.posexplode(F.transform(whole, _statement(*form))).alias("place", "s")))
    hits = reduce(DataFrame.unionByName, found).select(*keys, "form", "place", "s.knob", "s.value").join(F.broadcast(knobs.select("knob")), "knob")
    last = hits.groupBy(*keys, "knob").agg(F.max_by("value", F.struct("form", "place")).alias("value"))
    config = last.groupBy(*keys).agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("knob", "value")))).alias("config"))
    return config.withColumn("knobs", F.array_sort(F.map_keys("config")))


def following_values(df: DataFrame, text_col: str, knobs_col: str = "knobs") -> DataFrame:
    """df with config: each of its knobs with the word behind its first mention in the text (knobs at the end have none)."""
    words = F.regexp_extract_all(F.lower(F.col(text_col)), F.lit("[a-z]+"), F.lit(0))
    pair = lambda k: F.struct(k.alias("knob"), F.try_element_at("_words", (F.array_position("_words", k) + 1).cast("int")).alias("value"))
    found = F.filter(F.transform(F.filter(F.col(knobs_col), lambda k: F.array_contains("_words", k)), pair), lambda s: s["value"].isNotNull())
    return df.withColumn("_words", words).withColumn("config", F.map_from_entries(F.array_sort(found))).drop("_words")


def question_pairs(turns: DataFrame) -> DataFrame:
    """(qid, question, answer): a user turn with the assistant turn right after it."""
    user = turns.filter("role = 'user'").select("conv_id", (F.col("turn") + 1).alias("turn"), F.col("text").alias("question"))
    reply = turns.filter("role = 'assistant'").select("conv_id", "turn", F.col("text").alias("answer"))
    return user.join(reply, ["conv_id", "turn"]).select((F.col("conv_id") * 1000 + F.col("turn") - 1).alias("qid"), "question", "answer")


def split(df: DataFrame, key: str, weights=(7, 2, 1), seed: int = 42, scheme: str = "hash") -> DataFrame:
    """df with split in history / train / test. mod10 splits by the key itself, hash by its hash, md5 by a hash that any engine has."""
    total = sum(weights)
    u = {
        "mod10": lambda: F.pmod(F.col(key), F.lit(total)),
        "hash": lambda: F.pmod(F.xxhash64(F.col(key), F.lit(seed)), F.lit(total)),
        "md5": lambda: F.conv(F.substring(F.md5(F.col(key).cast("string")), 1, 8), 16, 10).cast("long") % total,
    }[scheme]()
    return df.withColumn("split", F.when(u < weights[0], "history").when(u < weights[0] + weights[1], "train").otherwise("test"))


def merge_histories(*parts: DataFrame) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), parts).dropDuplicates()


def audit_sample(df: DataFrame, key: str, n: int) -> DataFrame:
    """n rows in the order of the key's md5: a sample that anyone can draw again."""
    return df.orderBy(F.md5(F.col(key).cast("string")), key).limit(n)


def corrupt(df: DataFrame, key: str, knobs_col: str, ratio: float, catalog: DataFrame, seed: int = 42) -> DataFrame:
    """A nested share of the rows loses its labels for one wrong catalogue entry: rows wrong at .1 stay wrong at .2."""
    names = catalog.agg(F.array_sort(F.collect_set("knob")).alias("names"))  # a catalogue is hundreds of rows
    h = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), F.col(key).cast("string"))), 1, 15), 16, 10).cast("long")
    u = F.pmod(h, F.lit(1_000_000)) / 1_000_000
    wrong = F.array_except(F.col("names"), F.col(knobs_col))
    pick = F.element_at(wrong, (F.pmod(F.floor(h / F.lit(1 << 20)), F.size(wrong)) + 1).cast("int"))
    out = df.crossJoin(F.broadcast(names)).withColumn("noisy", (u < ratio) & (F.size(wrong) > 0))
    return out.withColumn(knobs_col, F.when(F.col("noisy"), F.array(pick)).otherwise(F.col(knobs_col))).drop("names")
