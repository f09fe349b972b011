"""Registered queries of the operators over whole tables, and their SQL where SQL can say the same."""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame, SparkSession

from . import decontamination, language_id, license_scan, packing, phrase_automata, pseudonyms, quality_rules, secret_scan, simhash_dedup, stages, suffix_dedup
from .common import table
from .hash_sql import xxh64_ctes
from .stages import tokenizer_path

#: Stands for a key from the user's key store.
PSEUDONYM_KEY = hashlib.sha256(b"pseudonym key of the registered query").digest()


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan(table(spark, sf_dir, "documents"))


def op2_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_dedup.near_duplicates(table(spark, sf_dir, "documents"), width=4)


def op3_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pseudonyms.pseudonymise(table(spark, sf_dir, "documents"), PSEUDONYM_KEY)


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan(table(spark, sf_dir, "documents"))


def op5_phrase_automata(spark: SparkSession, sf_dir: str) -> DataFrame:
    return phrase_automata.digest(table(spark, sf_dir, "documents"))


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.digest(table(spark, sf_dir, "documents"))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_path())


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge(table(spark, sf_dir, "documents"))


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify(table(spark, sf_dir, "documents"))


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stages.run(spark, sf_dir)


QUERIES = {
    f.__name__: f
    for f in (op1_license_scan, op2_simhash_dedup, op3_pseudonyms, op4_secret_scan, op5_phrase_automata, op6_suffix_dedup, op7_packing, op8_quality_rules, op9_language_id, op10_decontamination, pipeline)
}

_BLANK = r"[ \t\n\x0B\f\r]+"
#: One row for each word of each document.
_WORDS = f"""w AS MATERIALIZED (SELECT doc_id, i, word, count(*) OVER (PARTITION BY doc_id) AS n FROM (SELECT doc_id, unnest(ws) AS word, generate_subscripts(ws, 1) AS i FROM (
    SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '{_BLANK}'), lambda x: x <> '') AS ws FROM documents)))"""


def _gram(n: int) -> str:
    return f"string_agg(word, ' ') OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND {n - 1} FOLLOWING)"


def _covered(flag: str, n: int) -> str:
    return f"max({flag}) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN {n - 1} PRECEDING AND CURRENT ROW)"


def _phrase_sql(width: int = 50) -> str:
    return f"""WITH {_WORDS}, g AS MATERIALIZED (SELECT doc_id, i, word, CASE WHEN i <= n - {width - 1} THEN md5({_gram(width)}) END AS h FROM w),
        f AS (SELECT h, min(doc_id) AS first FROM g WHERE h IS NOT NULL GROUP BY h), b AS (SELECT g.doc_id, i, word, CASE WHEN first < g.doc_id THEN 1 ELSE 0 END AS bad FROM g LEFT JOIN f USING (h)),
        c AS (SELECT doc_id, i, word, {_covered("bad", width)} AS gone FROM b),
        r AS (SELECT doc_id, count(*) AS n_words, sum(gone) AS n_removed, coalesce(string_agg(word, ' ' ORDER BY i) FILTER (WHERE gone = 0), '') AS kept FROM c GROUP BY doc_id)
      SELECT d.doc_id, coalesce(n_words, 0) AS n_words, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM documents d LEFT JOIN r USING (doc_id)"""


def _quality_sql() -> str:
    rules = quality_rules
    later = {n: f"c{n}" for n in rules.LATER}
    grams = ", ".join(f"CASE WHEN i <= n - {k - 1} THEN {_gram(k)} END AS g{k}" for k in (3, *later))
    flags = ", ".join(["CASE WHEN g3 IS NOT NULL AND count(*) OVER (PARTITION BY doc_id, g3) > 1 THEN 1 ELSE 0 END AS f3"] + [f"CASE WHEN g{k} IS NOT NULL AND row_number() OVER (PARTITION BY doc_id, g{k} ORDER BY i) > 1 THEN 1 ELSE 0 END AS f{k}" for k in later])
    cover = ", ".join(f"{_covered(f'f{k}', k)} AS x{k}" for k in (3, *later))
    sums = ", ".join(f"sum(CASE WHEN x{k} = 1 THEN length(word) ELSE 0 END) AS c{k}" for k in later)
    bad = " OR ".join([f"dup > {rules.LINE_CHARS} * size", f"n_symbols > {rules.SYMBOL_SHARE} * n_words"] + [f"c{k} > {most} * size" for k, most in rules.LATER.items()])
    zero = ", ".join(f"coalesce(c{k}, 0) AS c{k}" for k in later)
    return f"""WITH {_WORDS}, g AS (SELECT *, {grams} FROM w), f AS (SELECT *, {flags} FROM g), x AS (SELECT *, {cover} FROM f),
        m AS (SELECT doc_id, count(*) AS n_words, sum(length(word)) AS word_chars, sum(x3) AS n_repeat_words, {sums} FROM x GROUP BY doc_id),
        l AS (SELECT doc_id, line, count(*) AS n FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE regexp_matches(line, '[^ \\t\\n\\x0B\\f\\r]') GROUP BY 1, 2),
        k AS (SELECT doc_id, sum(n - 1) AS n_dup_lines, sum((n - 1) * length(regexp_replace(line, '{_BLANK}', '', 'g'))) AS dup FROM l GROUP BY doc_id),
        a AS (SELECT d.doc_id, coalesce(n_words, 0) AS n_words, coalesce(word_chars, 0) AS word_chars, length(regexp_replace(coalesce(text, ''), '[^#*$%&|<>]', '', 'g')) AS n_symbols, coalesce(n_dup_lines, 0) AS n_dup_lines,
          coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(dup, 0) AS dup, greatest(coalesce(word_chars, 0), 1) AS size, {zero} FROM documents d LEFT JOIN m USING (doc_id) LEFT JOIN k USING (doc_id)),
        v AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed, {bad} AS bad FROM a)
      SELECT doc_id, n_words, CAST(word_chars AS BIGINT) AS word_chars, n_symbols, CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(n_repeat_words AS BIGINT) AS n_repeat_words, base_failed, NOT base_failed AND NOT bad AS kept,
        CAST(dup AS DOUBLE) / size AS dup_line_chars, CAST(c5 AS DOUBLE) / size AS later_5gram_chars, CAST(c10 AS DOUBLE) / size AS later_10gram_chars FROM v"""


def _bytes_sql(length: int = 100) -> str:
    return f"""WITH w AS MATERIALIZED (SELECT doc_id, i, b, count(*) OVER (PARTITION BY doc_id) AS n FROM (SELECT doc_id, unnest(bs) AS b, generate_subscripts(bs, 1) AS i FROM (SELECT doc_id, regexp_extract_all(hex(encode(coalesce(text, ''))), '..') AS bs FROM documents))),
        g AS MATERIALIZED (SELECT doc_id, i, b, CASE WHEN i <= n - {length - 1} THEN md5(string_agg(b, '') OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND {length - 1} FOLLOWING)) END AS h FROM w),
        f AS (SELECT h, min(CAST(doc_id AS HUGEINT) * 4294967296 + i) AS first FROM g WHERE h IS NOT NULL GROUP BY h),
        c AS (SELECT doc_id, i, b, {_covered("bad", length)} AS gone FROM (SELECT doc_id, i, b, CASE WHEN first < CAST(doc_id AS HUGEINT) * 4294967296 + i THEN 1 ELSE 0 END AS bad FROM g LEFT JOIN f USING (h))),
        r AS (SELECT doc_id, count(*) AS n_bytes, sum(gone) AS n_removed, sum(CASE WHEN gone = 1 AND coalesce(before, 0) = 0 THEN 1 ELSE 0 END) AS n_spans, coalesce(string_agg(b, '' ORDER BY i) FILTER (WHERE gone = 0), '') AS kept
          FROM (SELECT *, lag(gone) OVER (PARTITION BY doc_id ORDER BY i) AS before FROM c) GROUP BY doc_id)
      SELECT d.doc_id, coalesce(n_bytes, 0) AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, CAST(coalesce(n_spans, 0) AS BIGINT) AS n_spans, sha256(unhex(coalesce(kept, ''))) AS kept_sha256 FROM documents d LEFT JOIN r USING (doc_id)"""


def _fingerprint_sql(width: int = 4, radius: int = 4) -> str:
    upper, lower = "".join(map(chr, range(65, 91))), "".join(map(chr, range(97, 123)))
    words = _WORDS.replace("string_split_regex(coalesce(text, '')", f"string_split_regex(translate(coalesce(text, ''), '{upper}', '{lower}')")
    bits = ", ".join(f"sum((h >> {i}) & 1) AS b{i}" for i in range(64))
    fp = " + ".join(f"CASE WHEN 2 * b{i} > m THEN {1 << i}::UHUGEINT ELSE 0::UHUGEINT END" for i in range(64))
    return f"""WITH RECURSIVE {words}, t AS MATERIALIZED (SELECT doc_id, {_gram(width)} AS s, i, n FROM w),
        g AS MATERIALIZED (SELECT doc_id, s FROM t WHERE i <= greatest(n - {width - 1}, 1)), u AS MATERIALIZED (SELECT DISTINCT s FROM g), {xxh64_ctes("u")},
        b AS (SELECT doc_id, count(*) AS m, {bits} FROM g JOIN xxh USING (s) GROUP BY doc_id),
        p AS MATERIALIZED (SELECT d.doc_id, coalesce(fp, 0::UBIGINT) AS fp FROM documents d LEFT JOIN (SELECT doc_id, CAST({fp} AS UBIGINT) AS fp FROM b) USING (doc_id)),
        k AS MATERIALIZED (SELECT fp, min(doc_id) AS least FROM p GROUP BY fp),
        e AS MATERIALIZED (SELECT x.fp AS a, y.fp AS b FROM k x JOIN k y ON x.fp <> y.fp AND bit_count(xor(x.fp, y.fp)) <= {radius}),
        r AS (SELECT fp AS a, fp AS b FROM k UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a),
        c AS (SELECT r.a AS fp, min(least) AS component_id FROM r JOIN k ON r.b = k.fp GROUP BY r.a)
      SELECT doc_id, lower(lpad(hex(fp), 16, '0')) AS fingerprint, component_id FROM p JOIN c USING (fp)"""


def _leak_sql(rate: float = 0.05) -> str:
    plain = r"trim(regexp_replace(lower(text), '\s+', ' ', 'g'))"
    return f"""WITH t AS MATERIALIZED (SELECT item_id, t, length(t) AS m, CAST(floor({rate} * length(t)) AS BIGINT) AS k FROM (SELECT item_id, {plain} AS t FROM benchmark) WHERE t <> ''),
        p AS MATERIALIZED (SELECT item_id, t, m, k, i * m // (k + 1) AS place, substr(t, i * m // (k + 1) + 1, (i + 1) * m // (k + 1) - i * m // (k + 1)) AS piece FROM (SELECT *, unnest(range(k + 1)) AS i FROM t)),
        d AS MATERIALIZED (SELECT doc_id, {plain} AS body FROM documents WHERE text IS NOT NULL),
        h AS MATERIALIZED (SELECT doc_id, item_id, body, t, m, k, place, piece FROM d JOIN p ON contains(body, piece)),
        s AS MATERIALIZED (SELECT DISTINCT doc_id, item_id, body, t, m, k, unnest(range(found - place - k, found - place + k + 1)) AS first
          FROM (SELECT *, unnest(list_filter(range(1, length(body) + 1), lambda i: substr(body, i, length(piece)) = piece)) AS found FROM h)),
        v AS (SELECT doc_id, item_id, first + size - 1 AS match_end, k, levenshtein(substr(body, first, size), t) AS distance FROM (SELECT *, unnest(range(greatest(m - k, 1), m + k + 1)) AS size FROM s WHERE first >= 1) WHERE first + size - 1 <= length(body))
      SELECT doc_id, item_id, min(distance) AS distance, min_by(match_end, distance * 4294967296 + match_end) AS match_end FROM v WHERE distance <= k GROUP BY doc_id, item_id"""


ORACLE_SQL: dict[str, str] = {
    "op2_simhash_dedup": _fingerprint_sql(),
    "op5_phrase_automata": _phrase_sql(),
    "op6_suffix_dedup": _bytes_sql(),
    "op8_quality_rules": _quality_sql(),
    "op10_decontamination": _leak_sql(),
}
