"""Repeated passages of word windows, found by anchors and located by Aho-Corasick automata.

Windows that share an anchor form a stretch: the words of the windows first .. last of that anchor (see winnowing).

1. One shuffle of the stretches' hashes on their anchors finds those whose anchor occurs in two documents. Equal stretches
   have one owner, the document of smallest id.
2. Where an anchor stands in stretches that differ, the owners hash their single windows; a window that starts in two
   documents is confirmed.
3. Anchors that very many documents hold are left out of both: all their windows are hashed, and confirmed by an aggregation
   that combines before its shuffle and a join on the window.
4. Each shard of documents gets the anchors that occur in it, compiles their words into one automaton, and streams all its
   documents through it. A hit is confirmed by the hash of the stretch around it (64 bits, beside the anchor's equal words):
   a stretch of a smaller owner goes whole, of any other the confirmed windows of smaller owners go.

Edges: null and empty texts have no words and are returned with zeros; rows with a null id count as later than all others,
and among themselves by a hash of their text; rows with equal ids never take from each other; texts shorter than a window
lose nothing; texts of any length are read whole; an empty table gives no rows; ids must lie below 2^62.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left
from itertools import accumulate

import ahocorasick
import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import batch_of, column, pieces, stored
from .winnowing import Words, among, anchors, given_id, heavy, per_shard, sharded

ANCHOR_WORDS, _ALL = 8, (1 << 64) - 1
_hash = xxhash.xxh3_64_intdigest


def _signed(values) -> np.ndarray:
    return np.array(values, np.uint64).view(np.int64)


def _long(h: int) -> int:
    """The same 64 bits as a signed number."""
    return h - (1 << 64) if h >> 63 else h


def _groups(*keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order, first of each group, last of each group) of rows with equal keys; the first key given orders within a group."""
    order = np.lexsort(keys)
    change = np.zeros(len(order), bool)
    change[:1] = True
    for k in keys[1:]:
        k = k[order]
        change[1:] |= k[1:] != k[:-1]
    first = np.flatnonzero(change)
    return order, first, np.append(first[1:], len(order))[: len(first)] - 1


def cleaned(docs: DataFrame, width: int = 50, id_col: str = "doc_id", text_col: str = "text", most: int = 1000, least: int = 100_000) -> DataFrame:
    """(doc_id, n_words, n_removed, kept): each row of docs without the words covered by windows of `width` words that also
    start in a document of smaller id. kept: the words left, joined by one blank (UTF-8 bytes). most, least: see heavy()."""
    parts, _ = sharded(docs, id_col, text_col)
    hot = heavy(parts, Words, ANCHOR_WORDS, width, most, least)  # at most `most`
    hot_anchors = np.sort(_signed([k & _ALL for k in hot]).view(np.uint64))
    stretch_schema = pa.schema([("anchor", pa.int64()), ("h", pa.int64()), ("shard", pa.int32()), ("lo", pa.int64()), ("hi", pa.int64()), ("lead", pa.int32()), ("size", pa.int32()), ("phrase", pa.binary())])
    window_schema = pa.schema([("anchor", pa.int64()), ("w", pa.int64()), ("shard", pa.int32()), ("lo", pa.int64()), ("hi", pa.int64())])
    final_schema = pa.schema([("doc", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept", pa.binary())])

    def find_stretches(batches):
        for batch in pieces(batches, "body", 1 << 17):
            doc, shard = np.array(column(batch, "doc"), np.int64), np.array(column(batch, "shard"), np.int32)
            text = Words(column(batch, "body"))
            anchor, place, first, last = anchors(text.units, text.owner, ANCHOR_WORDS, width)
            if not len(anchor):
                continue
            cold = ~among(anchor, hot_anchors)
            anchor, place, first, last = anchor[cold], place[cold], first[cold], last[cold]
            joined, own = text.joined, text.owner[place]
            h = np.array([_hash(joined[a:b]) for a, b in zip(text.at[first].tolist(), (text.at[last + width] - 1).tolist())], np.uint64)
            order, head, tail = _groups(doc[own], shard[own], h, anchor)
            lo, hi = order[head], order[tail]
            phrase = [joined[a:b] for a, b in zip(text.at[place[lo]].tolist(), (text.at[place[lo] + ANCHOR_WORDS] - 1).tolist())]
            yield batch_of(stretch_schema, [anchor[lo].view(np.int64), h[lo].view(np.int64), shard[own[lo]], doc[own[lo]], doc[own[hi]], place[lo] - first[lo], last[lo] + width - first[lo], phrase])

    found = parts.mapInArrow(find_stretches, "anchor long, h long, shard int, lo long, hi long, lead int, size int, phrase binary")

    def find_hot(batches):
        for batch in pieces(batches, "body", 1 << 17):
            doc, shard = np.array(column(batch, "doc"), np.int64), np.array(column(batch, "shard"), np.int32)
            text = Words(column(batch, "body"))
            anchor, _, first, last = anchors(text.units, text.owner, ANCHOR_WORDS, width)
            known = among(anchor, hot_anchors)
            anchor, first, last = anchor[known], first[known], last[known]
            if not len(anchor):
                continue
            anchor = np.repeat(anchor, last - first + 1)
            start = np.concatenate([np.arange(a, b + 1) for a, b in zip(first.tolist(), last.tolist())])
            own, joined = text.owner[start], text.joined
            w = np.array([_hash(joined[a:b]) for a, b in zip(text.at[start].tolist(), (text.at[start + width] - 1).tolist())], np.uint64)
            order, head, tail = _groups(doc[own], shard[own], w, anchor)
            lo, hi = order[head], order[tail]
            yield batch_of(window_schema, [anchor[lo].view(np.int64), w[lo].view(np.int64), shard[own[lo]], doc[own[lo]], doc[own[hi]]])

    anchor, stretch = Window.partitionBy("anchor"), Window.partitionBy("anchor", "h")
    found = found.withColumns({"least": F.min("lo").over(anchor), "most": F.max("hi").over(anchor), "several": F.min("h").over(anchor) != F.max("h").over(anchor)})
    # an anchor of one document alone cannot recur across documents
    found = found.filter("least < most").withColumn("owner", F.min("lo").over(stretch))
    found = stored(found.select("anchor", "h", "shard", "lo", "owner", "several", "lead", "size", "phrase"), "stretches")

    def find_windows(docs_, side):
        rows = list(zip(*(side.column(c).to_pylist() for c in ("anchor", "h", "owner", "lead", "size", "phrase"))))
        owner_of = {(a, h): o for a, h, o, *_ in rows}
        owners, auto = set(owner_of.values()), _automaton((a, h, lead, size, phrase) for a, h, _, lead, size, phrase in rows)
        shard, seen = side.column("shard")[0].as_py() if side.num_rows else 0, ([], [], [])
        for doc, body in zip(docs_.column("doc").to_pylist(), docs_.column("body").to_pylist()):
            if doc in owners:
                text = _Stream(body, auto, width)
                for a, h, lo, m in text.hits():
                    if owner_of[a, h] == doc:
                        n = m - width + 1
                        seen[0].extend([a] * n)
                        seen[1].extend(text.hash(i, width) for i in range(lo, lo + n))
                        seen[2].extend([doc] * n)
        a, w, doc = np.array(seen[0], np.int64), _signed(seen[1]), np.array(seen[2], np.int64)
        order, head, tail = _groups(doc, w, a)
        lo, hi = order[head], order[tail]
        return pa.Table.from_batches([batch_of(window_schema, [a[lo], w[lo], np.full(len(lo), shard, np.int32), doc[lo], doc[hi]])], window_schema)

    owned = found.filter("several and lo = owner").select("shard", "anchor", "h", "owner", "lead", "size", "phrase")
    windows = per_shard(parts, owned, find_windows, "anchor long, w long, shard int, lo long, hi long")
    confirmed = windows.withColumn("owner", F.min("lo").over(Window.partitionBy("anchor", "w"))).filter("owner < hi")
    if hot:
        windows = stored(parts.mapInArrow(find_hot, "anchor long, w long, shard int, lo long, hi long"), "windows")
        first = windows.groupBy("anchor", "w").agg(F.min("lo").alias("owner"), F.max("hi").alias("last")).filter("owner < last").select("anchor", "w", "owner")
        more = windows.select("anchor", "w", "shard", "hi").join(first, ["anchor", "w"]).filter("owner < hi")
        confirmed = confirmed.select("shard", "anchor", "w", "owner").unionByName(more.select("shard", "anchor", "w", "owner").distinct())
    none = {"lead": F.lit(None).cast("int"), "size": F.lit(None).cast("int"), "phrase": F.lit(None).cast("binary")}
    sent = found.select("shard", "anchor", "h", "owner", "lead", "size", "phrase").unionByName(confirmed.select("shard", "anchor", F.col("w").alias("h"), "owner").withColumns(none))

    def locate(docs_, side):
        anchor, h, owner, lead, size, phrase = (side.column(c).to_pylist() for c in ("anchor", "h", "owner", "lead", "size", "phrase"))
        first = {(a, x): o for a, x, o, p in zip(anchor, h, owner, phrase) if p is None}
        owner_of = {(a, x): o for a, x, o, p in zip(anchor, h, owner, phrase) if p is not None}
        auto = _automaton((x for x in zip(anchor, h, lead, size, phrase) if x[4] is not None), {a: hot[a] for a, _ in first if a in hot})
        out = [[], [], [], []]
        for doc, body in zip(docs_.column("doc").to_pylist(), docs_.column("body").to_pylist()):
            text = _Stream(body, auto, width)
            words, gone = text.words, bytearray(len(text.words))
            for a, x, lo, m in text.hits(gone) if len(words) >= width else ():
                if x is not None and owner_of[a, x] < doc:
                    gone[lo : lo + m] = b"\1" * m
                    continue
                for i in range(lo, lo + m - width + 1) if first else ():
                    if first.get((a, _long(text.hash(i, width))), doc) < doc:
                        gone[i : i + width] = b"\1" * width
            kept = [w for w, g in zip(words, gone) if not g] if any(gone) else words
            for c, v in zip(out, (doc, len(words), len(words) - len(kept), b" ".join(kept))):
                c.append(v)
        return pa.Table.from_batches([batch_of(final_schema, out)], final_schema)

    done = per_shard(parts, sent, locate, "doc long, n_words long, n_removed long, kept binary")
    return done.select(given_id(F.col("doc")).alias("doc_id"), "n_words", "n_removed", "kept")


def _automaton(stretches, hot: dict[int, bytes] | None = None):
    """Automaton over the anchors' words of (anchor, hash, lead, size, phrase) rows and of hot anchors; None without any.

    A pattern's value: its length and, for each shape (lead, size) of its stretches, their anchor and hashes. A hot anchor has
    the shape (0, 0): every window around it.
    """
    shapes: dict[bytes, dict] = {}
    for anchor, h, lead, size, phrase in stretches:
        shapes.setdefault(phrase, {}).setdefault((lead, size, anchor), set()).add(h)
    for anchor, phrase in (hot or {}).items():
        shapes.setdefault(phrase, {})[0, 0, anchor] = set()
    auto = ahocorasick.Automaton()
    for phrase, of in shapes.items():
        # blanks around the words keep a pattern to whole words; bytes are read as Latin-1 characters, one for one
        auto.add_word(f" {phrase.decode('latin-1')} ", (len(phrase) + 2, sorted(of.items())))
    if not shapes:
        return None
    auto.make_automaton()
    return auto


class _Stream:
    """One document's words as they pass through an automaton."""

    def __init__(self, body: bytes, auto, width: int):
        self.words, self.auto, self.width = body.split(), auto, width

    def hash(self, start: int, n: int) -> int:
        return _hash(self.joined[self.at[start] : self.at[start + n] - 1])

    def hits(self, gone: bytearray | None = None):
        """(anchor, hash, start, size) of each known stretch, and with hash None of the windows around a hot anchor; not of those
        that lie wholly in what is gone."""
        if self.auto is None or not self.words:
            return
        self.joined = b" ".join(self.words)
        self.at, n = None, len(self.words)
        for end, (length, shapes) in self.auto.iter(" " + self.joined.decode("latin-1") + " "):
            if self.at is None:
                self.at = [0, *accumulate(len(w) + 1 for w in self.words)]
            place = bisect_left(self.at, end + 1 - length)
            for (lead, size, anchor), hashes in shapes:
                if not size:
                    lo, last = max(0, place + ANCHOR_WORDS - self.width), min(place, n - self.width)
                    if lo <= last and (gone is None or gone.find(0, lo, last + self.width) >= 0):
                        yield anchor, None, lo, last - lo + self.width
                    continue
                lo = place - lead
                if lo < 0 or lo + size > n or gone is not None and gone.find(0, lo, lo + size) < 0:
                    continue
                h = _long(self.hash(lo, size))
                if h in hashes:
                    yield anchor, h, lo, size


def digest(docs: DataFrame, width: int = 50) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256."""
    return cleaned(docs, width).select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def removed_by_brute_force(docs: list[tuple[int, str | None]], width: int = 50) -> list[tuple[int, int, int, str]]:
    """The contract word by word, for small fixtures."""
    split = [(d, (t or "").encode().split()) for d, t in docs]
    first: dict[tuple, int] = {}
    for d, w in split:
        for i in range(len(w) - width + 1):
            key = tuple(w[i : i + width])
            first[key] = min(d, first.get(key, d))
    out = []
    for d, w in split:
        gone = [False] * len(w)
        for i in range(len(w) - width + 1):
            if first[tuple(w[i : i + width])] < d:
                gone[i : i + width] = [True] * width
        kept = [x for x, g in zip(w, gone) if not g]
        out.append((d, len(w), sum(gone), hashlib.sha256(b" ".join(kept)).hexdigest()))
    return out
