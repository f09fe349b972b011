"""Repetition coverage of documents by rolling n-gram hashes in numpy.

Word hashes of many documents lie in one array. The hash of an n-gram follows from that of the (n-1)-gram by one
multiplication and one addition; a document number mixed into it keeps repetitions inside their document. All shares are
code points in words, of n-grams and of lines alike, over the code points in words of the text.

Edges: a null or empty text has no words, fails the base rules and is not kept; ties and repeated rows are judged
one by one; a text of any length is read whole; an empty table gives an empty result; a null id stays null.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, column, pieces

SPACE, SYMBOLS = " \t\n\r\x0b\x0c", "#*$%&|<>"
#: Largest tolerated share of characters inside later copies of n-grams and of lines, and of symbols to words.
LATER = {5: 0.15, 6: 0.14, 7: 0.13, 8: 0.12, 9: 0.11, 10: 0.10}
LINE_CHARS, SYMBOL_SHARE = 0.20, 0.10
_BASE, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)


def _cover(starts: np.ndarray, n: int, total: int) -> np.ndarray:
    """Mask of the words inside windows of n words at these starts."""
    edge = np.zeros(total + 1, np.int64)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + n, -1)
    return np.cumsum(edge[:-1]) > 0


def repetition(words: np.ndarray, chars: np.ndarray, doc: np.ndarray, docs: int) -> dict[str, np.ndarray]:
    """Coverage per document. words: hashes; chars: characters; doc: document number of each word, rising."""
    total = len(words)
    out = {"repeat3": np.zeros(docs, np.int64)} | {f"later{n}": np.zeros(docs) for n in LATER}
    rolling = words.copy()
    with np.errstate(over="ignore"):
        salt = (doc.astype(np.uint64) + np.uint64(1)) * _MIX
        for n in range(2, max(LATER) + 1):
            if total < n:
                break
            rolling = rolling[:-1] * _BASE + words[n - 1 :]
            inside = np.flatnonzero(doc[: total - n + 1] == doc[n - 1 :])
            if n != 3 and n not in LATER:
                continue
            key = (rolling[inside] ^ (rolling[inside] >> np.uint64(29))) * _MIX + salt[inside]
            order = np.argsort(key, kind="stable")
            run = np.concatenate([[True], key[order][1:] != key[order][:-1]]) if len(key) else np.empty(0, bool)
            group = np.cumsum(run) - 1
            size = np.bincount(group, minlength=1) if len(key) else np.zeros(1, np.int64)
            many = size[group] > 1 if len(key) else np.empty(0, bool)
            if n == 3:
                hit = _cover(inside[order[many]], 3, total)
                out["repeat3"] = np.bincount(doc[hit], minlength=docs)
            if n in LATER:
                hit = _cover(inside[order[many & ~run]], n, total)
                out[f"later{n}"] = np.bincount(doc[hit], weights=chars[hit], minlength=docs)
    return out


def measures(texts: list[str | None]) -> dict[str, np.ndarray]:
    docs = len(texts)
    n_words, word_chars, n_symbols = np.zeros(docs, np.int64), np.zeros(docs, np.int64), np.zeros(docs, np.int64)
    n_dup, dup_chars = np.zeros(docs, np.int64), np.zeros(docs, np.int64)
    hashes, lengths = [], []
    digest = xxhash.xxh3_64_intdigest
    for i, text in enumerate(texts):
        if not text:
            continue
        raw = text.encode()
        words = raw.split()
        n_words[i] = len(words)
        word_chars[i] = len(text) - sum(map(text.count, SPACE))
        n_symbols[i] = sum(map(text.count, SYMBOLS))
        lines = [x for x in raw.split(b"\n") if x.strip()]
        if len(set(lines)) < len(lines):
            n_dup[i] = len(lines) - len(set(lines))
            dup_chars[i] = sum((n - 1) * sum(len(w.decode()) for w in x.split()) for x, n in Counter(lines).items() if n > 1)
        hashes.append(np.fromiter(map(digest, words), np.uint64, len(words)))
        sizes = map(len, words) if len(raw) == len(text) else (len(w.decode()) for w in words)
        lengths.append(np.fromiter(sizes, np.int64, len(words)))
    doc = np.repeat(np.arange(docs), n_words)
    words = np.concatenate(hashes) if hashes else np.empty(0, np.uint64)
    chars = np.concatenate(lengths) if lengths else np.empty(0, np.int64)
    rep = repetition(words, chars, doc, docs)
    size = np.maximum(np.bincount(doc, weights=chars, minlength=docs), 1)
    base_failed = (n_words < 50) | (100 * rep["repeat3"] > 50 * n_words)
    bad = (dup_chars > LINE_CHARS * size) | (n_symbols > SYMBOL_SHARE * n_words)
    for n, most in LATER.items():
        bad |= rep[f"later{n}"] > most * size
    return {
        "n_words": n_words, "word_chars": word_chars, "n_symbols": n_symbols, "n_dup_lines": n_dup, "n_repeat_words": rep["repeat3"],
        "base_failed": base_failed, "kept": ~base_failed & ~bad, "dup_line_chars": dup_chars / size,
        "later_5gram_chars": rep["later5"] / size, "later_10gram_chars": rep["later10"] / size,
    }


_LONG, _FLAG, _REAL = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"), ("base_failed", "kept"), ("dup_line_chars", "later_5gram_chars", "later_10gram_chars")


def judge(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of measures and a verdict for each row of docs."""
    out = pa.schema([("doc_id", pa.int64()), *((c, pa.int64()) for c in _LONG), *((c, pa.bool_()) for c in _FLAG), *((c, pa.float64()) for c in _REAL)])

    def run(batches):
        for batch in pieces(batches, "body", 1 << 19):
            found = measures(column(batch, "body"))
            yield batch_of(out, [column(batch, "doc_id"), *(found[c] for c in (*_LONG, *_FLAG, *_REAL))])

    ddl = "doc_id long, " + ", ".join([f"{c} long" for c in _LONG] + [f"{c} boolean" for c in _FLAG] + [f"{c} double" for c in _REAL])
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("body")).mapInArrow(run, ddl)


def keep_good(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The rows of docs that pass, with all their columns and no shuffle: the verdict is made beside the row."""

    def run(batches):
        for batch in pieces(batches, text_col, 1 << 19):
            yield batch.filter(pa.array(measures(column(batch, text_col))["kept"]))

    return docs.mapInArrow(run, docs.schema)


def judged_by_brute_force(text: str | None) -> dict:
    """The measures of one text word by word, for small fixtures."""
    raw = (text or "").encode()
    words = [w.decode() for w in raw.split()]
    lines = [x for x in raw.split(b"\n") if x.split()]
    total = max(1, sum(map(len, words)))

    def inside(n: int, least: int) -> set[int]:
        """Words in windows of n words that are at least the least-th of their kind (least 0: of a kind that recurs)."""
        seen, grams = Counter(), [tuple(words[i : i + n]) for i in range(len(words) - n + 1)]
        many, hit = Counter(grams), set()
        for i, g in enumerate(grams):
            seen[g] += 1
            if many[g] > 1 and seen[g] >= least:
                hit.update(range(i, i + n))
        return hit

    later = {n: sum(len(words[i]) for i in inside(n, 2)) / total for n in LATER}
    dup, seen = 0, set()
    for x in lines:
        dup += sum(len(w.decode()) for w in x.split()) if x in seen else 0
        seen.add(x)
    symbols, repeat = sum(c in SYMBOLS for c in text or ""), len(inside(3, 0))
    failed = len(words) < 50 or 100 * repeat > 50 * len(words)
    bad = dup / total > LINE_CHARS or symbols > SYMBOL_SHARE * len(words) or any(later[n] > LATER[n] for n in LATER)
    return {
        "n_words": len(words), "word_chars": sum(map(len, words)), "n_symbols": symbols, "n_dup_lines": len(lines) - len(set(lines)), "n_repeat_words": repeat,
        "base_failed": failed, "kept": not failed and not bad, "dup_line_chars": dup / total, "later_5gram_chars": later[5], "later_10gram_chars": later[10],
    }
