"""Near duplicates by 64-bit similarity fingerprints, searched with Golay-code keys.

A fingerprint is cut into three segments, each a shortened word of the perfect binary Golay code of
length 23. A word is decoded to the index of its nearest codeword and, when that lies three bits off, to
the five further codewords four bits off. Two words that differ in one bit: the nearest codeword of either
is among the keys of the other. Two words that differ in at most two bits share a key (the tests prove both
over all syndromes). Pigeonhole over three segments with four errors in all:

* a segment without error exists: another segment has at most two errors, so (exact segment, Golay key of
  the other) agrees for one of the six ordered choices;
* no segment is free of error: two segments have one error each, so the pair of nearest indices of one
  fingerprint is among the key pairs of the other.

No link is lost, and every candidate is verified by its Hamming distance. Equal fingerprints collapse before
the search, and a bucket gives a spanning forest of its links, never all pairs.

Nulls and edges: null and empty texts have fingerprint zero and link like any other; a row with a null id is
returned with a null component and links nothing; repeated rows give repeated results; an empty table gives
an empty result.
"""

from __future__ import annotations

from itertools import accumulate, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, column, pieces, stored

#: Generator polynomial of the binary Golay code of length 23, and how the 64 bits are cut.
GENERATOR, CODE_BITS, CHECK_BITS = 0xAE3, 23, 11
SEGMENTS = ((42, 22), (21, 21), (0, 21))


def fingerprint(text: bytes, width: int, seed: int = 42) -> int:
    words = text.lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) < width:
        return xxhash.xxh64_intdigest(joined, seed)
    ends = list(accumulate((len(w) + 1 for w in words)))
    starts = [0, *ends]
    digest, total = xxhash.xxh64_intdigest, np.zeros(64, np.int64)
    n = len(words) - width + 1
    for lo in range(0, n, 1 << 15):
        hi = min(n, lo + (1 << 15))
        h = np.array([digest(joined[a : b - 1], seed) for a, b in zip(starts[lo:hi], ends[lo + width - 1 : hi + width - 1])], dtype=np.uint64)
        total += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(total * 2 > n, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 4) -> DataFrame:
    """One row (doc_id, fp) for each row of docs."""
    out = pa.schema([("doc_id", pa.int64()), ("fp", pa.int64())])

    def run(batches):
        for batch in pieces(batches, "body"):
            fps = np.array([fingerprint(t or b"", width) for t in column(batch, "body")], dtype=np.uint64)
            yield batch_of(out, [column(batch, "doc_id"), fps.view(np.int64)])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("body")).mapInArrow(run, "doc_id long, fp long")


def _remainder(v: np.ndarray) -> np.ndarray:
    v = v.astype(np.int64)
    for bit in range(CODE_BITS - 1, CHECK_BITS - 1, -1):
        v = np.where(v >> bit & 1, v ^ (GENERATOR << (bit - CHECK_BITS)), v)
    return v


def golay_patterns() -> tuple[np.ndarray, np.ndarray]:
    """For each syndrome its error patterns of weight up to four, nearest first: (2048 x 6 patterns, how many)."""
    near = np.array([sum(1 << b for b in c) for w in range(4) for c in combinations(range(CODE_BITS), w)])
    far = np.array([sum(1 << b for b in c) for c in combinations(range(CODE_BITS), 4)])
    pattern = np.zeros((1 << CHECK_BITS, 6), np.int64)
    pattern[_remainder(near), 0] = near
    pattern[:, 1:] = pattern[:, :1]
    count = np.ones(1 << CHECK_BITS, np.int64)
    s = _remainder(far)
    order = np.argsort(s, kind="stable")
    s, far = s[order], far[order]
    rank = np.arange(len(s)) - np.searchsorted(s, s)
    pattern[s, rank + 1] = far
    np.add.at(count, s, 1)
    return pattern, count


_tables: list = []


def _decoder():
    if not _tables:
        low = _remainder(np.arange(1 << 12))
        high = _remainder(np.arange(1 << 11) << 12)
        _tables.extend([low, high, *golay_patterns()])
    return _tables


def golay_keys(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Indices of the nearby codewords of 23-bit words, nearest first: (n x 6 indices, how many)."""
    low, high, pattern, count = _decoder()
    s = low[words & 0xFFF] ^ high[words >> 12]
    return (words[:, None] ^ pattern[s]) >> CHECK_BITS, count[s]


def bucket_keys(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(position in fps, key, whether it is an indexing row) for all fingerprints (uint64)."""
    seg = [((fps >> np.uint64(at)) & np.uint64((1 << bits) - 1)).astype(np.int64) for at, bits in SEGMENTS]
    idx, cnt = zip(*(golay_keys(s) for s in seg))
    rows, keys, lead = [], [], []
    slot = np.arange(6)
    for z in range(3):
        for o in range(3):
            if z != o:
                at, j = np.nonzero(slot < cnt[o][:, None])
                rows.append(at)
                keys.append((np.int64(z * 3 + o) << 36) | (seg[z][at] << 12) | idx[o][at, j])
                lead.append(np.ones(len(at), bool))
    both = np.arange(36)
    for a, b in combinations(range(3), 2):
        at, j = np.nonzero((both // 6 < cnt[a][:, None]) & (both % 6 < cnt[b][:, None]))
        rows.append(at)
        keys.append((np.int64(16 + a * 3 + b) << 36) | (idx[a][at, j // 6] << 12) | idx[b][at, j % 6])
        lead.append(j == 0)
    return np.concatenate(rows), np.concatenate(keys), np.concatenate(lead)


def forest(fp: np.ndarray, lead: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning forest (a, b) of the links inside one bucket: each indexing row against all, the others not among themselves."""
    label, a, b = np.arange(len(fp)), [], []
    for i in np.flatnonzero(lead):
        close = np.flatnonzero((np.bitwise_count(fp ^ fp[i]) <= radius) & (label != label[i]))
        if len(close):
            other, at = np.unique(label[close], return_index=True)
            a.append(np.full(len(at), fp[i]))
            b.append(fp[close[at]])
            label[np.isin(label, other)] = label[i]
    none = fp[:0]
    return (np.concatenate(a), np.concatenate(b)) if a else (none, none)


def _links(key, fp, lead, radius, small=8):
    """Links among whole runs of equal keys (arrays sorted by key), as rows of two fingerprints."""
    n = len(key)
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    length = np.diff(np.append(first, n))
    useful = (length > 1) & np.logical_or.reduceat(lead, first)
    found = [(fp[:0], fp[:0])]
    size = np.repeat(np.where(useful & (length <= small), length, 0), length)
    place = np.arange(n) - np.repeat(first, length)
    for d in range(1, small):
        i = np.flatnonzero(place + d < size)
        if not len(i):
            break
        i = i[np.bitwise_count(fp[i] ^ fp[i + d]) <= radius]
        found.append((fp[i], fp[i + d]))
    for r in np.flatnonzero(useful & (length > small)):
        cut = slice(first[r], first[r] + length[r])
        found.append(forest(fp[cut], lead[cut], radius))
    a, b = (np.concatenate(x).view(np.int64) for x in zip(*found))
    pairs = np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1)
    return np.unique(pairs[a != b], axis=0)


def links(prints: DataFrame, radius: int = 4) -> DataFrame:
    """Links (src < dst) between distinct fingerprints (column fp of prints) that differ in at most `radius` bits.

    Buckets give spanning forests, so two fingerprints of one bucket may be joined by a path instead of a link.
    """
    if radius > 4:
        raise ValueError("the three Golay segments find up to four differing bits")
    key_schema = pa.schema([("key", pa.int64()), ("fp", pa.int64())])
    link_schema = pa.schema([("src", pa.int64()), ("dst", pa.int64())])

    def to_keys(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                fp = np.array(column(batch.slice(at, 4096), "fp"), np.int64)
                row, key, lead = bucket_keys(fp.view(np.uint64))
                yield batch_of(key_schema, [key << 1 | ~lead, fp[row]])  # the lowest bit: not an indexing row

    def to_links(batches):
        held = [np.empty(0, np.int64), np.empty(0, np.uint64)]
        for batch in batches:
            if not batch.num_rows:
                continue
            held = [np.concatenate([held[0], np.asarray(batch.column(0))]), np.concatenate([held[1], np.asarray(batch.column(1)).view(np.uint64)])]
            cut = np.searchsorted(held[0] >> 1, held[0][-1] >> 1)  # the last run may go on in the next batch
            if cut:
                out = _links(held[0][:cut] >> 1, held[1][:cut], held[0][:cut] & 1 == 0, radius)
                held = [x[cut:] for x in held]
                yield batch_of(link_schema, [out[:, 0], out[:, 1]])
        if len(held[0]):
            out = _links(held[0] >> 1, held[1], held[0] & 1 == 0, radius)
            yield batch_of(link_schema, [out[:, 0], out[:, 1]])

    keys = prints.select("fp").mapInArrow(to_keys, "key long, fp long")
    return keys.repartition(F.shiftright("key", 1)).sortWithinPartitions("key").mapInArrow(to_links, "src long, dst long").distinct()


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, root): each linked node, the roots too, with the smallest node it reaches, by alternating large and small stars.

    Each star is one aggregation and one join on the node; each round is stored, so lineage stays short.
    """
    now = stored(edges.select(F.col("src").alias("u"), F.col("dst").alias("v")), "links")
    seen = None
    for _ in range(rounds):
        both = now.union(now.select(F.col("v"), F.col("u"))).toDF("u", "v")
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        down = large.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        least = down.groupBy("u").agg(F.min("v").alias("m"))
        small = down.join(least, "u")
        now = stored(small.select(F.col("v").alias("u"), F.col("m").alias("v")).union(small.select("u", F.col("m").alias("v"))).filter("u <> v").distinct(), "stars")
        mark = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if mark == seen:
            return now.union(now.select("v", "v").distinct()).toDF("node", "root")  # a star has no row of its own centre
        seen = mark
    raise RuntimeError("components did not settle")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 4, radius: int = 4) -> DataFrame:
    """(doc_id, fingerprint, component_id) for each row of docs; component_id is the smallest id reachable."""
    prints = stored(fingerprints(docs, id_col, text_col, width), "fingerprints")
    nodes = stored(prints.filter("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("n")), "nodes")
    roots = components(links(nodes, radius)).toDF("fp", "root")
    linked = nodes.join(roots, "fp").select("fp", "least", "root")
    linked = linked.join(linked.groupBy("root").agg(F.min("least").alias("component_id")), "root").select("fp", "component_id")
    equal = nodes.filter("n > 1").join(roots, "fp", "left_anti").select("fp", F.col("least").alias("component_id"))
    # a fingerprint of one document that links nothing needs no row; a plain table on either side, so a hot fingerprint's part can be split
    label = stored(linked.unionByName(equal), "labels")
    return prints.join(label, "fp", "left").select(
        "doc_id",
        F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"),
        F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id")).alias("component_id"),
    )
