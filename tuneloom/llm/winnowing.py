"""Anchors: the minimisers of sliding windows, and documents dealt to shards.

Equal windows of `width` units have the same anchor, the n-gram of smallest hash inside them (the leftmost of equals), at
the same place. So a window that recurs has an anchor that recurs, and only about 2 / (width - n + 2) of the positions are
anchors: finding what may recur costs a small part of a shuffle of all windows, and misses nothing.

An anchor that a large share of all texts hold would fill one task of that shuffle. Such heavy anchors are counted before; they
are few, every task knows them, and what they anchor is dealt by whole windows instead.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import batch_of, column, pieces

_BASE, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
PLACE_BITS = 24
#: Ids from here on stand for null ids.
NULL_IDS = 1 << 62


def ngram_hashes(units: np.ndarray, n: int) -> np.ndarray:
    """64-bit hashes of all n-grams (n a power of two) of hashed units, by doubling."""
    h, base, size = units.astype(np.uint64), _BASE, 1
    with np.errstate(over="ignore"):
        while size < n:
            h = h[:-size] * base + h[size:]
            base, size = base * base, 2 * size
        h = (h ^ (h >> np.uint64(32))) * _MIX
        return h ^ (h >> np.uint64(29))


def anchors(units: np.ndarray, owner: np.ndarray, n: int, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(hash, place, first, last): each anchor of the windows that begin at first .. last.

    units: hashed units of many documents in a row; owner: the document number of each. Windows do not cross documents.
    More units than places have bits for go in slices that overlap by width - 1 units; an anchor's run that goes on over a
    seam is joined.
    """
    most = max(width, (1 << PLACE_BITS) - 1)
    if len(units) <= most:
        return _anchors(units, owner, n, width)
    parts = []
    for lo in range(0, len(units) - width + 1, most - width + 1):
        h, place, first, last = _anchors(units[lo : lo + most], owner[lo : lo + most], n, width)
        place, first, last = place + lo, first + lo, last + lo
        if parts and len(h) and len(parts[-1][0]) and parts[-1][1][-1] == place[0] and parts[-1][3][-1] + 1 == first[0]:
            parts[-1][3][-1] = last[0]
            h, place, first, last = h[1:], place[1:], first[1:], last[1:]
        if len(h):
            parts.append((h, place, first, last))
    return tuple(map(np.concatenate, zip(*parts))) if parts else _anchors(units[:0], owner[:0], n, width)


def _anchors(units: np.ndarray, owner: np.ndarray, n: int, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """anchors() of one slice."""
    none = np.empty(0, np.int64)
    if len(units) < width:
        return np.empty(0, np.uint64), none, none, none
    h = ngram_hashes(units, n)
    if len(h) >= 1 << PLACE_BITS:
        raise ValueError("too many units in one batch")
    low = np.uint64((1 << PLACE_BITS) - 1)
    least = (h & ~low) | np.arange(len(h), dtype=np.uint64)
    span, size = width - n + 1, 1
    while 2 * size <= span:
        least = np.minimum(least[:-size], least[size:])
        size *= 2
    if size < span:
        least = np.minimum(least[: len(least) - (span - size)], least[span - size :])
    starts = np.flatnonzero(owner[: len(least)] == owner[width - 1 : width - 1 + len(least)])
    if not len(starts):
        return np.empty(0, np.uint64), none, none, none
    place = (least[starts] & low).astype(np.int64)
    new = np.concatenate([[True], (place[1:] != place[:-1]) | (starts[1:] != starts[:-1] + 1)])
    first = starts[new]
    last = starts[np.append(np.flatnonzero(new)[1:] - 1, len(starts) - 1)]
    place = place[new]
    return h[place], place, first, last


def among(values: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Which values are in wanted (sorted); wanted is not sorted anew for each small batch."""
    if not len(wanted):
        return np.zeros(len(values), bool)
    return wanted[np.minimum(np.searchsorted(wanted, values), len(wanted) - 1)] == values


class Words:
    """Words of several texts in a row: hashes, owners, and slices of the blank-joined text."""

    def __init__(self, bodies: list[bytes]):
        split = [b.split() for b in bodies]
        self.counts = np.array([len(s) for s in split], np.int64)
        self.words = [w for s in split for w in s]
        self.units = np.fromiter(map(xxhash.xxh3_64_intdigest, self.words), np.uint64, len(self.words))
        self.owner = np.repeat(np.arange(len(bodies)), self.counts)
        self.base = np.concatenate([[0], np.cumsum(self.counts)])
        self.joined = b" ".join(self.words)
        size = np.fromiter(map(len, self.words), np.int64, len(self.words))
        self.at = np.concatenate([[0], np.cumsum(size + 1)])

    def text(self, a: int, b: int) -> bytes:
        """Words a .. b-1."""
        return self.joined[self.at[a] : self.at[b] - 1]


class Bytes:
    """Bytes of several texts in a row."""

    def __init__(self, bodies: list[bytes]):
        self.counts = np.array([len(b) for b in bodies], np.int64)
        self.joined = b"".join(bodies)
        self.units = np.frombuffer(self.joined, np.uint8)
        self.owner = np.repeat(np.arange(len(bodies), dtype=np.int32), self.counts)
        self.base = np.concatenate([[0], np.cumsum(self.counts)])

    def text(self, a: int, b: int) -> bytes:
        return self.joined[a:b]


def batches_of(bodies: list[bytes], limit: int = 1 << 16):
    """Index ranges of bodies of about `limit` bytes each, so that the arrays over them stay in the processor's cache."""
    start = size = 0
    for i, b in enumerate(bodies):
        if size and size + len(b) > limit:
            yield start, i
            start, size = i, 0
        size += len(b)
    if start < len(bodies):
        yield start, len(bodies)


def document(id_col: str, body):
    """The id of a row as a long. A null id counts as later than all others: it is a number of 2^62 or more, from the text."""
    given = F.col(id_col).cast("long")
    late = F.xxhash64(body).bitwiseAND(F.lit(NULL_IDS - 1)) + F.lit(NULL_IDS)
    return F.when(given.isNull(), late).when(given < NULL_IDS, given).otherwise(F.raise_error(F.lit("document ids must lie below 2^62")).cast("long"))


def given_id(doc):
    return F.when(doc < NULL_IDS, doc)


def sharded(docs: DataFrame, id_col: str, text_col: str, shard_bytes: int = 4 << 20) -> tuple[DataFrame, int]:
    """(shard, doc, body) with so many shards that each holds about shard_bytes of text."""
    body = F.coalesce(F.col(text_col), F.lit("")).cast("binary")
    total = docs.agg(F.sum(F.octet_length(F.col(text_col)).cast("long"))).first()[0] or 0
    n = max(1, -(-total // shard_bytes))
    doc = document(id_col, body)
    return docs.select(shard_of(doc, n).alias("shard"), doc.alias("doc"), body.alias("body")), n


def shard_of(doc, n: int):
    return F.pmod(F.xxhash64(doc), F.lit(n)).cast("int")


def heavy(parts: DataFrame, kind: type, n: int, width: int, most: int = 1000, least: int = 100_000) -> dict[int, bytes]:
    """{anchor: its text} of the at most `most` anchors that hold over one in `most` of all places, and over `least`.

    Each task keeps a summary of `most` counters over all its texts (counts are merged, and all but the largest `most` lose
    what the next one has), so an anchor left out holds at most two in `most` of all.
    """
    out = pa.schema([("anchor", pa.int64()), ("n", pa.int64()), ("phrase", pa.binary())])

    def count(batches):
        keys, sizes, shown, seen = np.empty(0, np.uint64), np.empty(0, np.int64), {}, 0
        for batch in pieces(batches, "body", 4 << 20):
            bodies, held = column(batch, "body"), []
            for a, b in batches_of(bodies):
                text = kind(bodies[a:b])
                h, place, _, _ = anchors(text.units, text.owner, n, width)
                held.append((h, place, text))
            h = np.concatenate([x[0] for x in held])
            edge = np.cumsum([len(x[0]) for x in held])
            seen += len(h)
            new, at, times = np.unique(h, return_index=True, return_counts=True)
            both, where = np.unique(np.concatenate([keys, new]), return_inverse=True)
            total = np.bincount(where, weights=np.concatenate([sizes, times]), minlength=len(both)).astype(np.int64)
            if len(both) > most:
                total -= np.partition(total, -most - 1)[-most - 1]
            keys, sizes = both[total > 0], total[total > 0]

            def words_of(k):
                i = int(at[np.searchsorted(new, k)])
                g = int(np.searchsorted(edge, i, side="right"))
                place = int(held[g][1][i - edge[g]])  # counted from the end of the slice's anchors
                return held[g][2].text(place, place + n)

            shown = {int(k): shown[int(k)] if int(k) in shown else words_of(k) for k in keys}
        yield batch_of(out, [[None, *keys.view(np.int64).tolist()], [seen, *sizes.tolist()], [None, *(shown[k] for k in keys.tolist())]])

    rows = parts.mapInArrow(count, "anchor long, n long, phrase binary").groupBy("anchor").agg(F.sum("n").alias("n"), F.max("phrase").alias("phrase"))
    rows = rows.orderBy(F.desc("n"), "anchor").limit(most + 1).collect()
    total = sum(r["n"] for r in rows if r["anchor"] is None)
    return {r["anchor"]: bytes(r["phrase"]) for r in rows if r["anchor"] is not None and r["n"] > least and r["n"] * most > total}


def recurring(found: DataFrame) -> DataFrame:
    """The rows (anchor, shard, n) of anchors that occur more than once in the corpus, with their total. One shuffle on the
    anchor; the heavy ones are not among them, so a task's share of one anchor is bounded."""
    total = F.sum("n").over(Window.partitionBy("anchor"))
    return found.withColumn("total", total).filter("total > 1")


def per_shard(docs: DataFrame, side: DataFrame, fn, schema: str) -> DataFrame:
    """fn(documents, side rows) for each shard; both are Arrow tables of bounded size.

    All calls over the same docs share one exchange of the texts.
    """
    return docs.groupBy("shard").cogroup(side.groupBy("shard")).applyInArrow(fn, schema)
