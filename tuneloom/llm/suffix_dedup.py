"""Repeated byte strings of a given length, by suffix arrays over shards of what can recur.

1. Anchors (see winnowing) that recur are found by one shuffle of their hashes. Every string of `length` bytes that recurs
   lies in a stretch around a recurring anchor: the strings that begin at first .. last of that anchor.
2. Equal stretches collapse: each distinct one is kept at its first place in the corpus, by an aggregation that combines
   before the shuffle, so thousands of copies cost one text. An anchor with one distinct stretch holds no string twice in it
   (its strings begin at different distances from the anchor), so its text is not looked at again.
3. The other distinct stretches are cut in two: the strings with many bytes before the anchor, and those with many behind it.
   All strings of a half hold the same bytes there, so halves are dealt by them; equal halves collapse again, and a half
   whose bytes no other has is done. The rest make the shards. A shard's suffix array comes from induced sorting, its common
   prefixes in permuted order; neighbours that share `length` bytes form groups, and all of a group but the earliest are
   repeats.
4. Of anchors with more occurrences than a shard has room for, and of the heavy ones, no task gets all stretches: their
   strings are dealt one by one, by the hash of their bytes, and an aggregation that combines before its shuffle finds the
   first of each.
5. Each document marks its repeats: the whole stretch where it is not the first copy, else what its shard has found.

Edges: a null or empty text has no bytes and is returned with zeros; rows with a null id count as later than all others, and
among themselves by a hash of their text; rows of equal id count as one document and are compared by place, so repeated rows
do not take from each other; texts shorter than `length` lose nothing; matches never cross documents; texts of any length are
read whole; an empty table gives no rows; ids must lie below 2^62.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import batch_of, column, pieces, stored
from .suffix_sort import common_prefixes, suffix_array
from .winnowing import Bytes, among, anchors, batches_of, given_id, heavy, per_shard, recurring, shard_of, sharded

ANCHOR_BYTES = 32


class _Runs:
    """The runs of one slice of texts whose anchors are wanted: as stretches, or as the single strings in them."""

    def __init__(self, text: Bytes, length: int, whole: np.ndarray, single: np.ndarray):
        h, place, first, last = anchors(text.units, text.owner, ANCHOR_BYTES, length)
        apart = among(h, single)
        keep = among(h, whole) & ~apart
        self.h, self.place, self.first, self.last = h[keep], place[keep], first[keep], last[keep]
        joined, digest = text.joined, xxhash.xxh3_64_intdigest
        self.mark = np.array([digest(joined[a:b]) for a, b in zip(self.first.tolist(), (self.last + length).tolist())], np.uint64)
        h, first, last = h[apart], first[apart], last[apart]
        self.at = np.concatenate([np.arange(a, b + 1) for a, b in zip(first.tolist(), last.tolist())]) if len(h) else np.empty(0, np.int64)
        self.string_h = np.repeat(h, last - first + 1)
        self.string_mark = np.array([digest(joined[a : a + length]) for a in self.at.tolist()], np.uint64)


def repeats_in_shard(texts: list[bytes], doc: np.ndarray, pos: np.ndarray, length: int) -> list[list[int]]:
    """For each distinct stretch (at pos of doc) the starts of its repeated strings, as pairs first, last."""
    size = np.fromiter(map(len, texts), np.int64, len(texts))
    base = np.concatenate([[0], np.cumsum(size + 1)])[:-1]
    data = np.frombuffer(b"\xff".join(texts), np.uint8)  # no UTF-8 text holds this byte
    sa = suffix_array(data)
    shared = common_prefixes(data, sa)[sa] >= length
    group = np.cumsum(~shared) - 1
    many = np.bincount(group)[group] > 1
    at, group = sa[many].astype(np.int64), group[many]
    own = np.searchsorted(base, at, side="right") - 1
    offset = at - base[own]
    inside = offset <= size[own] - length
    at, group, own, offset = at[inside], group[inside], own[inside], offset[inside]
    order = np.lexsort((pos[own] + offset, doc[own], group))
    group, own, offset = group[order], own[order], offset[order]
    later = np.concatenate([[False], group[1:] == group[:-1]]) if len(group) else np.empty(0, bool)
    own, offset = own[later], offset[later]
    order = np.lexsort((offset, own))
    own, offset = own[order], offset[order]
    new = np.concatenate([[True], (own[1:] != own[:-1]) | (offset[1:] != offset[:-1] + 1)]) if len(own) else np.empty(0, bool)
    heads = np.flatnonzero(new)
    tails = np.append(heads[1:] - 1, len(own) - 1) if len(heads) else heads
    out: list[list[int]] = [[] for _ in texts]
    for k, a, b in zip(own[heads].tolist(), offset[heads].tolist(), offset[tails].tolist()):
        out[k] += [a, b]
    return out


def _distinct(h, mark, doc) -> tuple[np.ndarray, np.ndarray]:
    """(rows, how many) of the distinct (h, mark, doc)."""
    order = np.lexsort((doc, mark, h))
    h, mark, doc = h[order], mark[order], doc[order]
    new = np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (mark[1:] != mark[:-1]) | (doc[1:] != doc[:-1])]))
    return order[new], np.diff(np.append(new, len(h)))


def cleaned(docs: DataFrame, length: int = 100, id_col: str = "doc_id", text_col: str = "text", shard_bytes: int = 2 << 20, most: int = 1000, least: int = 100_000) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept): each row of docs without the bytes covered by strings of `length` bytes that
    also start earlier. kept: the bytes left. most, least: see heavy()."""
    parts, n_shards = sharded(docs, id_col, text_col)
    hot = np.sort(np.array([k & ((1 << 64) - 1) for k in heavy(parts, Bytes, ANCHOR_BYTES, length, most, least)], np.uint64))  # at most `most`
    room = max(1, shard_bytes // (2 * length))  # stretches of one anchor that a shard can hold
    anchor_schema = pa.schema([("anchor", pa.int64()), ("shard", pa.int32()), ("n", pa.int32())])
    copy_schema = pa.schema([("shard", pa.int32()), ("anchor", pa.int64()), ("h", pa.int64()), ("doc", pa.int64()), ("n", pa.int32()), ("single", pa.bool_())])
    text_schema = pa.schema([("core", pa.int64()), ("anchor", pa.int64()), ("h", pa.int64()), ("doc", pa.int64()), ("pos", pa.int64()), ("at", pa.int32()), ("half", pa.binary())])
    repeat_schema = pa.schema([("anchor", pa.int64()), ("h", pa.int64()), ("owner", pa.int64()), ("starts", pa.list_(pa.int32()))])
    final_schema = pa.schema([("doc", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept", pa.binary())])

    def find_anchors(batches):
        for batch in pieces(batches, "body", 4 << 20):
            shard = np.array(column(batch, "shard"), np.int32)
            bodies = column(batch, "body")
            for a, b in batches_of(bodies):
                text = Bytes(bodies[a:b])
                h, place, _, _ = anchors(text.units, text.owner, ANCHOR_BYTES, length)
                cold = ~among(h, hot)
                h, place = h[cold], place[cold]
                if not len(h):
                    continue
                s = shard[a:b][text.owner[place]]
                order = np.lexsort((s, h))
                h, s = h[order], s[order]
                new = np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (s[1:] != s[:-1])]))
                yield batch_of(anchor_schema, [h[new].view(np.int64), s[new], np.diff(np.append(new, len(h))).astype(np.int32)])

    again = recurring(parts.mapInArrow(find_anchors, "anchor long, shard int, n int"))
    again = stored(again.select("shard", "anchor", (F.col("total") > room).alias("single")), "anchors")

    def wanted_of(side):
        """(anchors of stretches, anchors of single strings)"""
        anchor = np.asarray(side.column("anchor").combine_chunks()).view(np.uint64)
        single = side.column("single").combine_chunks().to_numpy(zero_copy_only=False).astype(bool)
        return np.unique(anchor[~single]), np.union1d(anchor[single], hot)

    def find_copies(docs_, side):
        (whole, single), out = wanted_of(side), []
        bodies, doc = docs_.column("body").to_pylist(), np.asarray(docs_.column("doc").combine_chunks())
        shard = docs_.column("shard")[0].as_py() if docs_.num_rows else 0
        for a, b in batches_of(bodies) if len(whole) or len(single) else ():
            text = Bytes(bodies[a:b])
            runs = _Runs(text, length, whole, single)
            for apart, h, mark, at in ((False, runs.h, runs.mark, runs.first), (True, runs.string_h, runs.string_mark, runs.at)):
                if len(h):
                    d = doc[a:b][text.owner[at]]
                    k, n = _distinct(h, mark, d)
                    out.append(batch_of(copy_schema, [np.full(len(k), shard, np.int32), h[k].view(np.int64), mark[k].view(np.int64), d[k], n.astype(np.int32), np.full(len(k), apart)]))
        return pa.Table.from_batches(out, copy_schema)

    copies = stored(per_shard(parts, again, find_copies, "shard int, anchor long, h long, doc long, n int, single boolean"), "copies")
    by_place = copies.filter("not single").groupBy("anchor", "h").agg(F.min("doc").alias("owner"))
    owned = stored(by_place.withColumn("alone", F.count(F.lit(1)).over(Window.partitionBy("anchor")) == 1), "owned")
    contested = owned.filter("not alone").select(shard_of(F.col("owner"), n_shards).alias("shard"), "anchor", "h", "owner", F.lit(False).alias("single"))

    def pairs_of(side):
        return zip(np.asarray(side.column("anchor").combine_chunks()).view(np.uint64).tolist(), np.asarray(side.column("h").combine_chunks()).view(np.uint64).tolist())

    def find_texts(docs_, side):
        whole, _ = wanted_of(side)
        owner_of, first = dict(zip(pairs_of(side), side.column("owner").to_pylist())), {}
        bodies, doc = docs_.column("body").to_pylist(), docs_.column("doc").to_pylist()
        for a, b in batches_of(bodies) if len(whole) else ():
            text = Bytes(bodies[a:b])
            runs = _Runs(text, length, whole, whole[:0])
            for x, y, place, lo, hi in zip(runs.h.tolist(), runs.mark.tolist(), runs.place.tolist(), runs.first.tolist(), runs.last.tolist()):
                own = int(text.owner[lo])
                pos = lo - int(text.base[own])
                if owner_of.get((x, y)) == doc[a + own] and ((x, y) not in first or pos < first[x, y][1]):  # only its first place
                    first[x, y] = (doc[a + own], pos, place - lo, hi - lo, text.joined[lo : hi + length])
        half, digest = (length - ANCHOR_BYTES) // 2, xxhash.xxh3_64_intdigest
        behind = length - ANCHOR_BYTES - half + 1
        out: list[list] = [[] for _ in text_schema]
        for (x, y), (d, pos, lead, last, stretch) in first.items():
            # starts up to lead - half have `half` bytes before the anchor, the others `behind` bytes behind it
            if lead >= half:
                rows = [(digest(stretch[lead - half : lead + ANCHOR_BYTES], 1), 0, stretch[: min(last, lead - half) + length])]
            else:
                rows = []
            if (r := max(0, lead - half + 1)) <= last:
                rows.append((digest(stretch[lead : lead + ANCHOR_BYTES + behind], 2), r, stretch[r:]))
            for core, at, text in rows:
                for c, v in zip(out, (core, x, y, d, pos + at, at, text)):
                    c.append(v)
        for i in range(3):
            out[i] = np.array(out[i], np.uint64).view(np.int64)
        return pa.Table.from_batches([batch_of(text_schema, out)], text_schema)

    texts = per_shard(parts, contested, find_texts, "core long, anchor long, h long, doc long, pos long, at int, half binary")

    def sort_shards(batches):
        # equal halves stand together, the first place first
        held, size, out, core, rows = [], 0, [[] for _ in repeat_schema], None, []

        def close():
            """The rows of one core: later copies of a half repeat it wholly; halves that differ go to the shard."""
            nonlocal size
            kept = []
            for row in rows:
                if kept and kept[-1][6] == row[6]:
                    add(row, [0, len(row[6]) - length])
                else:
                    kept.append(row)
            if len(kept) > 1:
                held.extend(kept)
                size += sum(len(r[6]) for r in kept)
            rows.clear()

        def add(row, starts):
            for c, v in zip(out, (row[1], row[2], row[3], [row[5] + s for s in starts])):
                c.append(v)

        def flush():
            nonlocal size, out
            if held:
                found = repeats_in_shard([r[6] for r in held], np.array([r[3] for r in held], np.int64), np.array([r[4] for r in held], np.int64), length)
                for row, starts in zip(held, found):
                    if starts:
                        add(row, starts)
                held.clear()
                size = 0
            done, out = out, [[] for _ in repeat_schema]
            return batch_of(repeat_schema, done)

        for batch in batches:
            for row in zip(*(column(batch, c) for c in text_schema.names)):
                if row[0] != core:
                    close()
                    core = row[0]
                    if size > shard_bytes or len(out[0]) > 1 << 16:  # the halves of one core stay together; they are at most `room`
                        yield flush()
                rows.append(row)
        close()
        yield flush()

    repeats = texts.repartition("core").sortWithinPartitions("core", "half", "doc", "pos").mapInArrow(sort_shards, "anchor long, h long, owner long, starts array<int>")
    nothing = F.array().cast("array<int>").alias("starts")
    repeats = repeats.unionByName(owned.select("anchor", "h", "owner", nothing))
    sent = copies.filter("not single").select("shard", "anchor", "h").distinct().join(repeats, ["anchor", "h"]).withColumn("single", F.lit(False))
    # a string that stands at several places, be it in one document
    strings = copies.filter("single").groupBy("anchor", "h").agg(F.min("doc").alias("owner"), F.sum("n").alias("n")).filter("n > 1").select("anchor", "h", "owner", nothing)
    sent = sent.unionByName(copies.filter("single").select("shard", "anchor", "h").distinct().join(strings, ["anchor", "h"]).withColumn("single", F.lit(True)))

    def remove(docs_, side):
        whole, single = wanted_of(side)
        known: dict[tuple, tuple] = {}
        for pair, owner, starts in zip(pairs_of(side), side.column("owner").to_pylist(), side.column("starts").to_pylist()):
            known[pair] = (owner, known[pair][1] + starts if pair in known else starts)
        bodies, doc = docs_.column("body").to_pylist(), docs_.column("doc").to_pylist()
        out = [doc, [len(b) for b in bodies], [0] * len(bodies), [0] * len(bodies), bodies]
        slices, first = [], {}
        for a, b in batches_of(bodies) if known else ():
            text = Bytes(bodies[a:b])
            runs = _Runs(text, length, whole, single)
            rows = []
            for h, mark, los, his in ((runs.h, runs.mark, runs.first, runs.last), (runs.string_h, runs.string_mark, runs.at, runs.at)):
                for x, y, lo, hi in zip(h.tolist(), mark.tolist(), los.tolist(), his.tolist()):
                    if (x, y) in known:
                        own = int(text.owner[lo])
                        pos = lo - int(text.base[own]) if known[x, y][0] == doc[a + own] else -1
                        if pos >= 0:
                            first[x, y] = min(pos, first.get((x, y), pos))
                        rows.append((x, y, lo, hi, pos))
            if rows:
                slices.append((a, text, rows))
        for a, text, rows in slices:
            edge = np.zeros(len(text.units) + 1, np.int32)
            lo_, hi_ = [], []
            for x, y, lo, hi, pos in rows:
                if pos >= 0 and pos == first[x, y]:
                    starts = known[x, y][1]
                    lo_ += [lo + s for s in starts[::2]]
                    hi_ += [lo + s + length for s in starts[1::2]]
                else:
                    lo_.append(lo)
                    hi_.append(hi + length)
            if not lo_:
                continue
            np.add.at(edge, np.array(lo_), 1)
            np.add.at(edge, np.array(hi_), -1)
            gone = np.cumsum(edge[:-1]) > 0
            begin = gone & np.concatenate([[True], ~gone[:-1] | (text.owner[1:] != text.owner[:-1])])
            for k in np.unique(text.owner[gone]).tolist():
                cut = slice(text.base[k], text.base[k + 1])
                out[2][a + k], out[3][a + k] = int(gone[cut].sum()), int(begin[cut].sum())
                out[4][a + k] = text.units[cut][~gone[cut]].tobytes()
        return pa.Table.from_batches([batch_of(final_schema, out)], final_schema)

    done = per_shard(parts, sent, remove, "doc long, n_bytes long, n_removed long, n_spans long, kept binary")
    return done.select(given_id(F.col("doc")).alias("doc_id"), "n_bytes", "n_removed", "n_spans", "kept")


def digest(docs: DataFrame, length: int = 100) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256."""
    return cleaned(docs, length).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def removed_by_brute_force(docs: list[tuple[int, str | None]], length: int = 100) -> list[tuple]:
    """The contract byte by byte, for small fixtures."""
    first: dict[bytes, tuple] = {}
    bodies = [(d, (t or "").encode()) for d, t in docs]
    for d, b in bodies:
        for i in range(len(b) - length + 1):
            key = b[i : i + length]
            first[key] = min((d, i), first.get(key, (d, i)))
    out = []
    for d, b in bodies:
        gone = bytearray(len(b))
        for i in range(len(b) - length + 1):
            if first[b[i : i + length]] < (d, i):
                gone[i : i + length] = b"\1" * length
        kept = bytes(c for c, g in zip(b, gone) if not g)
        spans = sum(1 for i, g in enumerate(gone) if g and (not i or not gone[i - 1]))
        out.append((d, len(b), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return out
