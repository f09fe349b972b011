"""Benchmark leaks by pigeonhole edit matching.

A test item of m characters may be met with up to k = floor(rate * m) edits. Cut into k + 1 pieces, at least one piece
stands unharmed in any such copy. One automaton holds the pieces of a block of items; every text is streamed through
it, and each exact piece hit is verified by Myers' bit-parallel distance over the stretch of text it allows.

Texts and items are compared in lower case with runs of white space as one blank. Items go in blocks of bounded size, so
a large benchmark costs more passes and not more memory.

Edges: null or empty texts and items match nothing; repeated rows give repeated results; items that need no edit budget
are matched exactly; an empty table on either side gives no rows.
"""

from __future__ import annotations

import math

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, column, pieces


def normal(text: str | None) -> str:
    return " ".join(text.lower().split()) if text else ""


def cut(text: str, parts: int) -> list[tuple[int, str]]:
    """The text in pieces of nearly equal length, each with its place."""
    edges = [len(text) * i // parts for i in range(parts + 1)]
    return [(a, text[a:b]) for a, b in zip(edges, edges[1:]) if b > a]


class Pattern:
    """Myers' bit vectors of one item, searched anywhere in a text."""

    def __init__(self, text: str):
        self.length, self.masks = len(text), {}
        for i, c in enumerate(text):
            self.masks[c] = self.masks.get(c, 0) | 1 << i

    def best(self, text: str, most: int) -> tuple[int, int] | None:
        """(distance, end) of the nearest substring of text within `most` edits, the first of equals."""
        full, top, get = (1 << self.length) - 1, 1 << (self.length - 1), self.masks.get
        up, down, score, found = full, 0, self.length, None
        for at, c in enumerate(text):
            eq = get(c, 0)
            across = (((eq & up) + up) ^ up) | eq | down
            right = down | (full & ~(across | up))
            left = up & across
            if right & top:
                score += 1
            elif left & top:
                score -= 1
            right, left = right << 1 & full, left << 1 & full
            vertical = eq | down
            up, down = left | (full & ~(vertical | right)), right & vertical
            if score <= most:
                most, found = score - 1, (score, at + 1)
                if not score:
                    break
        return found


class Matcher:
    def __init__(self, items: list[tuple[int, str]], rate: float):
        self.items = []
        where: dict[str, list] = {}
        for item_id, text in items:
            if not (text := normal(text)):
                continue
            k = int(rate * len(text))
            self.items.append((item_id, Pattern(text), k, text))
            for at, piece in cut(text, k + 1):
                where.setdefault(piece, []).append((len(self.items) - 1, at))
        self.auto = ahocorasick.Automaton()
        for piece, uses in where.items():
            self.auto.add_word(piece, (len(piece), uses))
        if where:
            self.auto.make_automaton()
        self.ready = bool(where)

    def __call__(self, text: str) -> dict[int, tuple[int, int]]:
        """item number -> (distance, end in the normalised text) of its nearest copy."""
        found: dict[int, tuple[int, int]] = {}
        checked: dict[int, list[int]] = {}
        if not self.ready:
            return found
        for end, (size, uses) in self.auto.iter(text):
            for i, at in uses:
                _, pattern, k, item = self.items[i]
                old = found.get(i)
                if old and not old[0]:
                    continue
                start = end + 1 - size - at
                if start >= 0 and text.startswith(item, start):
                    found[i] = (0, start + len(item))
                    continue
                slack, seen = k // 2, checked.setdefault(i, [])
                if any(abs(s - start) <= slack for s in seen):  # that stretch was looked at with slack already
                    continue
                lo, hi = max(0, start - k - slack), start + pattern.length + 2 * k
                seen[:] = [s for s in seen if s + slack + pattern.length >= end] + [start]  # later hits start no further left
                if k and (hit := pattern.best(text[lo : hi + k], old[0] - 1 if old else k)):
                    found[i] = (hit[0], lo + hit[1])
        return found


def leaks(docs: DataFrame, items: DataFrame, rate: float = 0.05, block_chars: int = 4_000_000, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """(doc_id, item_id, distance, match_end): each document with each item it holds within the edit budget."""
    out = pa.schema([("doc_id", pa.int64()), ("item_id", pa.int64()), ("distance", pa.int64()), ("match_end", pa.int64())])
    spark = docs.sparkSession
    source = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("body"))
    tests = items.select(F.col(item_col).cast("long").alias("item"), F.col(item_text).cast("string").alias("body")).filter("body is not null")
    chars = tests.agg(F.sum(F.length("body"))).first()[0] or 0
    blocks = max(1, math.ceil(chars / block_chars))
    found = None
    for b in range(blocks):
        block = [tuple(r) for r in tests.filter(F.pmod(F.xxhash64("item", "body"), F.lit(blocks)) == b).collect()]  # about block_chars characters
        shared = spark.sparkContext.broadcast((block, rate))

        def run(batches, shared=shared):
            matcher = Matcher(*shared.value)
            for batch in pieces(batches, "body"):
                rows = []
                for doc, text in zip(column(batch, "doc_id"), column(batch, "body")):
                    rows += [(doc, matcher.items[i][0], *hit) for i, hit in matcher(normal(text)).items()]
                if rows:
                    yield batch_of(out, list(zip(*rows)))

        part = source.mapInArrow(run, "doc_id long, item_id long, distance long, match_end long")
        found = part if found is None else found.unionAll(part)
    return found


def without_leaks(docs: DataFrame, items: DataFrame, rate: float = 0.05, block_chars: int = 4_000_000, text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """The rows of docs that hold no item, with all their columns and no shuffle."""
    spark = docs.sparkSession
    tests = items.select(F.col(item_col).cast("long").alias("item"), F.col(item_text).cast("string").alias("body")).filter("body is not null")
    chars = tests.agg(F.sum(F.length("body"))).first()[0] or 0
    blocks = max(1, math.ceil(chars / block_chars))
    left = docs
    for b in range(blocks):
        block = [tuple(r) for r in tests.filter(F.pmod(F.xxhash64("item", "body"), F.lit(blocks)) == b).collect()]
        shared = spark.sparkContext.broadcast((block, rate))

        def run(batches, shared=shared):
            matcher = Matcher(*shared.value)
            for batch in pieces(batches, text_col):
                yield batch.filter(pa.array([not matcher(normal(t)) for t in column(batch, text_col)], pa.bool_()))

        left = left.mapInArrow(run, docs.schema)
    return left
