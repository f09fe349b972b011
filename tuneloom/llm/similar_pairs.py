"""Groups of texts whose sets of word shingles have a Jaccard similarity of at least a threshold, each link verified.

The operator of near duplicates by fingerprints (see simhash_dedup) sees at most four differing bits of 64; at a similarity of
0.8 some ten bits differ. So its links come first, and a second search adds what it cannot see:

1. Texts get a fingerprint of their shingles; Golay keys give the pairs of close fingerprints.
2. Each text gets 128 minimum hashes of its shingles. Five of them make a key, 25 keys in all, so two texts of similarity J
   share none with probability (1 - J^5)^25: 5e-5 at 0.8, 4e-7 at 0.85. One bit of each minimum makes a sketch of 128 bits.
3. Texts that share a key and whose sketches differ in at most 32 bits (at J = 0.8 13 are expected; more than 32 have a
   probability under 1e-6), and the pairs of close fingerprints, are compared by their whole shingle sets; only pairs that
   reach the threshold are linked.
4. Buckets of up to `small` texts give all their pairs. A larger one first gives the pairs with its most central texts, and
   after the links so found are joined to groups, its texts outside the largest group meet all its texts, in blocks of
   `block` texts on either side. So a large group of copies costs no square of its size, and no pair that could join two
   groups is left out.

Sets are compared as sets of 64-bit hashes. Texts equal but for case and white space collapse before the search.

Nulls and edges: null and empty texts are equal to each other; a text of fewer words than a shingle is one shingle; a row
with a null id links nothing and is not returned; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, column, pieces, stored
from .simhash_dedup import components, fingerprint, links
from .winnowing import among

HASHES, ROWS, BANDS, MOST_BITS = 128, 5, 25, 32
_B, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
_draw = np.random.default_rng(20231)
_XOR = _draw.integers(0, 1 << 64, HASHES, np.uint64)
_TIMES = _draw.integers(0, 1 << 64, HASHES, np.uint64) | np.uint64(1)


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * _MIX
    return h ^ (h >> np.uint64(29))


def normal(text: bytes | None) -> list[bytes]:
    return (text or b"").lower().split()


def digest(words: list[bytes]) -> int:
    return int(np.uint64(xxhash.xxh3_64_intdigest(b" ".join(words))).view(np.int64))


def shingles(words: list[bytes], width: int) -> np.ndarray:
    """64-bit hashes of all shingles, at least one."""
    if len(words) < width:
        return np.array([xxhash.xxh64_intdigest(b" ".join(words))], np.uint64)
    units = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))
    n = len(words) - width + 1
    h = units[:n].copy()
    for i in range(1, width):
        h = h * _B + units[i : i + n]
    return _mixed(h)


def signatures(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(keys, sketch): n x BANDS int64 and n x 2 int64."""
    flat = np.concatenate(sets)
    starts = np.concatenate([[0], np.cumsum([len(s) for s in sets])[:-1]])
    least = np.stack([np.minimum.reduceat((flat ^ x) * t, starts) for x, t in zip(_XOR, _TIMES)], axis=1)
    sketch = np.packbits((_mixed(least) & np.uint64(1)).astype(np.uint8), axis=1, bitorder="little").view(np.int64)
    key = np.tile(np.arange(BANDS, dtype=np.uint64), (len(sets), 1))
    for r in range(ROWS):
        key = _mixed(key * _B + least[:, r * BANDS : (r + 1) * BANDS])
    return key.view(np.int64), sketch


def _groups(sets: list[np.ndarray], limit: int = 1 << 14):
    """Index ranges of sets of about `limit` hashes, which stay in the processor's cache."""
    start = size = 0
    for i, s in enumerate(sets):
        if size and size + len(s) > limit:
            yield start, i
            start, size = i, 0
        size += len(s)
    if start < len(sets):
        yield start, len(sets)


def _close(sketch: np.ndarray, other: np.ndarray) -> np.ndarray:
    return np.bitwise_count((sketch ^ other).view(np.uint64)).sum(axis=1) <= MOST_BITS


def _centres(marks: np.ndarray, most: int = 8) -> list[int]:
    """The sketches nearest the majority of each bit."""
    bits = np.unpackbits(np.ascontiguousarray(marks).view(np.uint8), axis=1)
    far = (bits != (2 * bits.sum(axis=0, dtype=np.int64) > len(bits))).sum(axis=1)
    return np.argsort(far, kind="stable")[:most].tolist()


def _runs(key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    return first, np.diff(np.append(first, len(key)))


def _pairs(key, node, sketch, small: int):
    """Yields (a, b) arrays of pairs of whole runs of equal keys.

    Copies of one text resemble it more than each other: a large run's pairs are those of the few texts whose sketches lie
    nearest the bits most sketches have, so the text that was copied, if it is there, is among them.
    """
    first, length = _runs(key)
    size = np.repeat(np.where(length <= small, length, 0), length)
    place = np.arange(len(key)) - np.repeat(first, length)
    for d in range(1, small):
        i = np.flatnonzero(place + d < size)
        if not len(i):
            break
        i = i[_close(sketch[i], sketch[i + d])]
        yield node[i], node[i + d]
    for f, n in zip(first[length > small], length[length > small]):
        run, marks = node[f : f + n], sketch[f : f + n]
        for p in _centres(marks):
            hit = np.flatnonzero(_close(marks, marks[p]) & (run != run[p]))
            if len(hit):
                yield np.full(len(hit), run[p]), run[hit]


def _by_run(batches, names, fn, schema):
    """fn over arrays of whole runs of equal keys; batches are sorted by key."""
    held = None
    for batch in batches:
        if not batch.num_rows:
            continue
        new = [np.asarray(batch.column(batch.schema.get_field_index(n))) for n in names]
        held = new if held is None else [np.concatenate([a, b]) for a, b in zip(held, new)]
        cut = np.searchsorted(held[0], held[0][-1])  # the last run may go on in the next batch
        if cut:
            for out in fn(*(x[:cut] for x in held)):
                yield batch_of(schema, out)
            held = [x[cut:] for x in held]
    if held is not None:
        for out in fn(*held):
            yield batch_of(schema, out)


def _recurring(rows: DataFrame) -> DataFrame:
    """(key, node, s0, s1, n): the rows whose key n > 1 nodes have."""
    out = pa.schema([(c, pa.int64()) for c in ("key", "node", "s0", "s1", "n")])

    def keep(key, node, s0, s1):
        _, length = _runs(key)
        n = np.repeat(length, length)
        at = np.flatnonzero(n > 1)
        yield [key[at], node[at], s0[at], s1[at], n[at]]

    def run(batches):
        yield from _by_run(batches, ("key", "node", "s0", "s1"), keep, out)

    return rows.repartition("key").sortWithinPartitions("key").mapInArrow(run, "key long, node long, s0 long, s1 long, n long")


def _candidates(rows: DataFrame, small: int) -> DataFrame:
    """(a, b), a < b, of rows (key, node, s0, s1)."""
    out = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def find(key, node, s0, s1):
        for a, b in _pairs(key, node, np.stack([s0, s1], axis=1), small):
            yield [np.minimum(a, b), np.maximum(a, b)]

    def run(batches):
        yield from _by_run(batches, ("key", "node", "s0", "s1"), find, out)

    return rows.repartition("key").sortWithinPartitions("key").mapInArrow(run, "a long, b long").distinct()


def _sets(source: DataFrame, nodes: DataFrame, used: DataFrame, width: int) -> DataFrame:
    """(node, grams): the shingle sets of the used nodes."""
    out = pa.schema([("node", pa.int64()), ("grams", pa.binary())])

    def grams(batches):
        for batch in pieces(batches, "body"):
            rows = []
            for node, text in zip(column(batch, "node"), column(batch, "body")):
                words = normal(text)
                if digest(words) == node:  # rows of one id may have different texts
                    rows.append((node, np.unique(shingles(words, width)).tobytes()))
            if rows:
                yield batch_of(out, list(zip(*rows)))

    found = source.join(nodes.select("node", "doc_id").join(used, "node"), "doc_id").select("node", "body").mapInArrow(grams, "node long, grams binary")
    return stored(found.dropDuplicates(["node"]), "grams")


def _across(large: DataFrame, source: DataFrame, nodes: DataFrame, width: int, threshold: float, block: int) -> DataFrame:
    """Links (src, dst) between different groups inside large buckets. large: key, node, s0, s1, root.

    In each bucket the texts outside its largest group meet all its texts: both sides go in blocks, a pair of blocks is one
    task's work, and no pair becomes a row.
    """
    link = pa.schema([("src", pa.int64()), ("dst", pa.int64())])
    main = large.groupBy("key", "root").agg(F.count(F.lit(1)).alias("n")).groupBy("key").agg(F.max_by("root", F.struct("n", "root")).alias("main"), F.sum("n").alias("n"), F.max("n").alias("most"))
    main = stored(main.withColumn("others", F.col("n") - F.col("most")).filter("others > 0").select("key", "main", "n", "others"), "buckets")
    rows = large.join(main, "key")
    at = lambda n: F.pmod(F.xxhash64("node"), F.ceil(F.col(n) / block)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), (F.ceil(F.col(n) / block) - 1).cast("int")))
    sides = rows.select("key", "node", "s0", "s1", "root", F.lit(False).alias("other"), at("n").alias("x"), every("others").alias("y"))
    sides = sides.unionByName(rows.filter("root <> main").select("key", "node", "s0", "s1", "root", F.lit(True).alias("other"), every("n").alias("x"), at("others").alias("y")))
    sides = sides.join(_sets(source, nodes, rows.select("node").distinct(), width), "node")

    def compare(table: pa.Table) -> pa.Table:
        node, root = np.asarray(table["node"].combine_chunks()), np.asarray(table["root"].combine_chunks())
        sketch = np.stack([np.asarray(table[c].combine_chunks()) for c in ("s0", "s1")], axis=1)
        other = table["other"].combine_chunks().to_numpy(zero_copy_only=False).astype(bool)
        sets = [np.frombuffer(g, np.uint64) for g in table["grams"].to_pylist()]
        member, src, dst = np.flatnonzero(~other), [], []
        for i in np.flatnonzero(other):
            near = member[(root[member] != root[i]) & _close(sketch[member], sketch[i])]
            if not len(near):
                continue
            size = np.array([len(sets[k]) for k in near])
            start = np.concatenate([[0], np.cumsum(size)[:-1]])
            both = np.add.reduceat(among(np.concatenate([sets[k] for k in near]), sets[i]).astype(np.int64), start)
            hit = near[both >= threshold * (size + len(sets[i]) - both) - 1e-9]
            _, first = np.unique(root[hit], return_index=True)  # one link to each group
            src.append(np.full(len(first), node[i]))
            dst.append(node[hit[first]])
        a, b = (np.concatenate(x) if x else np.empty(0, np.int64) for x in (src, dst))
        return pa.Table.from_batches([batch_of(link, [np.minimum(a, b), np.maximum(a, b)])], link)

    return sides.groupBy("key", "x", "y").applyInArrow(compare, "src long, dst long").distinct()


def _verified(pairs: DataFrame, source: DataFrame, nodes: DataFrame, width: int, threshold: float) -> DataFrame:
    """The pairs (src, dst) whose shingle sets reach the threshold."""
    link = pa.schema([("src", pa.int64()), ("dst", pa.int64())])

    def compare(batches):
        for batch in batches:
            rows = []
            for a, b, x, y in zip(*(column(batch, c) for c in ("a", "b", "x", "y"))):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                if both >= threshold * (len(x) + len(y) - both) - 1e-9:
                    rows.append((a, b))
            if rows:
                yield batch_of(link, list(zip(*rows)))

    sets = _sets(source, nodes, pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct(), width)
    left, right = sets.toDF("a", "x"), sets.toDF("b", "y")
    return pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(compare, "src long, dst long")


def _close_prints(nodes: DataFrame) -> DataFrame:
    """(a, b), a < b: texts of equal or close fingerprints, each group of equal ones by its smallest text."""
    first = nodes.groupBy("fp").agg(F.min("node").alias("first"))
    equal = nodes.join(first, "fp").filter("node <> first").select(F.col("first").alias("a"), F.col("node").alias("b"))
    near = links(first.select("fp")).join(first.toDF("src", "x"), "src").join(first.toDF("dst", "y"), "dst")
    return equal.unionByName(near.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")))


def similar_groups(docs: DataFrame, width: int = 5, threshold: float = 0.8, small: int = 16, block: int = 2000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, component_id) for each row with an id; component_id is the smallest id that links of J >= threshold reach.

    The keys are laid out for thresholds of 0.8 and more.
    """
    if threshold < 0.8:
        raise ValueError("the keys find pairs of similarity 0.8 or more")
    out = pa.schema([("doc_id", pa.int64()), ("node", pa.int64()), ("fp", pa.int64()), ("s0", pa.int64()), ("s1", pa.int64()), ("keys", pa.list_(pa.int64()))])

    def sign(batches):
        for batch in pieces(batches, "body"):
            ids, bodies = column(batch, "doc_id"), column(batch, "body")
            words = [normal(t) for t in bodies]
            sets = [shingles(w, width) for w in words]
            fps = np.array([fingerprint(t or b"", width) for t in bodies], np.uint64).view(np.int64)
            for lo, hi in _groups(sets):
                keys, sketch = signatures(sets[lo:hi])
                yield batch_of(out, [ids[lo:hi], [digest(w) for w in words[lo:hi]], fps[lo:hi], sketch[:, 0], sketch[:, 1], list(keys)])

    source = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("body")).filter("doc_id is not null")
    signed = stored(source.mapInArrow(sign, "doc_id long, node long, fp long, s0 long, s1 long, keys array<long>"), "signed")
    nodes = stored(signed.groupBy("node").agg(F.min("doc_id").alias("doc_id"), F.first("fp").alias("fp"), F.first("s0").alias("s0"), F.first("s1").alias("s1"), F.first("keys").alias("keys")), "nodes")
    rows = stored(_recurring(nodes.select(F.explode("keys").alias("key"), "node", "s0", "s1")), "recurring")

    tried = _close_prints(nodes).unionByName(_candidates(rows, small)).distinct()
    tried = stored(tried, "candidates")
    similar = stored(_verified(tried, source, nodes, width, threshold), "similar")
    roots = components(similar)
    large = rows.filter(F.col("n") > small)
    if large.limit(1).count():
        named = large.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node")).select("key", "node", "s0", "s1", "root")
        found = stored(_across(named, source, nodes, width, threshold, block), "similar")
        if found.limit(1).count():
            roots = components(similar.unionAll(found))
    named = nodes.select("node", "doc_id").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    least = named.groupBy("root").agg(F.min("doc_id").alias("component_id"))
    label = named.join(least, "root").select("node", "component_id")
    return signed.select("doc_id", "node").join(label, "node").select("doc_id", "component_id")
