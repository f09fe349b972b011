"""Hierarchical multi-length packing of token sequences.

Documents go to context tiers by length. Whole windows of the longest tier are cut off long documents; what is left
is packed tier by tier, longest first: a window opens with a document of its tier, and its gap takes the largest
documents of the same or shorter tiers that fit, at last a cut of one more. A window of a shorter tier is full at its own length (a power of two), so nothing
is padded but a gap too small to be worth a cut. Leftovers of a partition go to ever shorter windows. Each partition
packs alone, block by block: no shuffle, bounded memory, and the same rows give the same sequences when a task runs again.

Edges: a null or empty text is a document of one token, the end mark; repeated rows are packed as separate documents;
an empty table gives no pieces; very long texts are cut.
"""

from __future__ import annotations

import os
import re
import zlib
from bisect import bisect_right, insort
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, column, pieces

TIERS = (512, 1024, 2048, 4096)
_BLANK = re.compile(r"[ \t\n\r\f\v]+")
#: str.split() parts at these, the vocabulary's splitter does not.
_NOT_BLANK = "\x1c\x1d\x1e\x1f"


class _Numbers(dict):
    """Chunk -> number; a chunk not seen before gets the next one and is noted."""

    def __init__(self):
        super().__init__()
        self.new: list[str] = []

    def __missing__(self, chunk: str) -> int:
        self[chunk] = n = len(self)
        self.new.append(chunk)
        return n


class Encoder:
    """Token ids (as little-endian 32-bit bytes) of whole texts.

    The vocabulary's splitter never joins text across white space, nor letters with what are not letters, so each
    blank-free chunk is encoded once and kept; the cache is emptied when full, which changes speed and not results. New
    chunks of Latin letters with plain marks behind them are put together from their lower-case letters and their marks;
    letter words are encoded many at a time and parted at the tokens that end a word.
    """

    MARKS = "!\"#$%&()*+,-./:;<=>?@[]^_{|}~"

    def __init__(self, path: str, end_id: int, cache: int = 1_000_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.model, self.limit = Tokenizer.from_file(path), cache
        vocab = self.model.get_vocab()
        self.ends = np.zeros(max(vocab.values(), default=0) + 1, bool)
        self.ends[[i for token, i in vocab.items() if token.endswith("</w>")]] = True
        self.end = np.uint32(end_id).astype("<u4").tobytes()
        self._clear()

    def _clear(self):
        self.number, self.ids = _Numbers(), []
        self.parts: dict[str, bytes] = {"": b""}

    def _plain(self, chunks: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.model.encode_batch_fast(chunks, add_special_tokens=False)]

    def _words(self, words: list[str]) -> list[bytes]:
        ids = np.array(self.model.encode_batch_fast([" ".join(words)], add_special_tokens=False)[0].ids, "<u4")
        stops = 4 * (np.flatnonzero(self.ends[ids]) + 1)
        if len(stops) != len(words):
            return self._plain(words)
        raw, stops = ids.tobytes(), stops.tolist()
        return [raw[a:b] for a, b in zip([0, *stops], stops)]

    def _learn(self, new: list[str]):
        parts, marks = self.parts, self.MARKS
        for at in range(0, len(new), 2048):
            chunks = new[at : at + 2048]
            heads = [w.rstrip(marks).lower() for w in chunks]
            for lo in range(0, len(chunks), 32):
                few = heads[lo : lo + 32]
                joined = "".join(few)
                if not (joined.isalpha() and max(joined) < "\u0100" and all(few)):
                    heads[lo : lo + 32] = [h if h.isalpha() and max(h) < "\u0100" else None for h in few]
            tails = [w if h is None else w[len(h) :] for w, h in zip(chunks, heads)]
            if words := list({h for h in heads if h is not None and h not in parts}):
                parts.update(zip(words, self._words(words)))
            if rest := list({t for t in tails if t not in parts}):
                parts.update(zip(rest, self._plain(rest)))
            self.ids += [parts[t] if h is None else parts[h] + parts[t] for h, t in zip(heads, tails)]

    def __call__(self, texts: list[str | None]) -> list[bytes]:
        if len(self.number) > self.limit:
            self._clear()
        number = self.number.__getitem__
        chunks = [[] if not t else _BLANK.split(t) if any(map(t.__contains__, _NOT_BLANK)) else t.split() for t in texts]
        numbers = [list(map(number, c)) for c in chunks]
        self._learn(self.number.new)
        self.number.new = []
        ids = self.ids.__getitem__
        return [b"".join(map(ids, n)) + self.end for n in numbers]


_encoders: dict[tuple, Encoder] = {}


def encoder(path: str, end_id: int) -> Encoder:
    """One encoder for each worker process, so that what a task has learnt serves the next."""
    if (path, end_id) not in _encoders:
        _encoders[path, end_id] = Encoder(path, end_id)
    return _encoders[path, end_id]


class Packer:
    """Packs documents of one partition; pieces come out in `rows`."""

    def __init__(self, tiers=TIERS, first_id: int = 0, block_tokens: int = 1 << 21, least_cut: int = 8, step_tokens: int = 1 << 16):
        self.tiers, self.ids, self.block, self.least, self.step = sorted(tiers), count(first_id), block_tokens, least_cut, step_tokens
        self.rows, self.held, self.tokens, self.serial = [], [], 0, count()
        self.groups, self.open, self.room = count(first_id), {}, {}

    def _emit(self, parts, tier):
        """parts: (doc, ids, start, length) in order make one sequence. Sequences of a tier fill step groups of equal tokens in turn."""
        seq, at, own = next(self.ids), 0, max(tier, self.tiers[0])
        if self.room.get(own, 0) < tier:
            self.open[own], self.room[own] = next(self.groups), self.step
        group = self.open[own]
        self.room[own] -= tier
        for doc, ids, start, n in parts:
            self.rows.append((doc, start, n, zlib.crc32(ids[4 * start : 4 * (start + n)]), len(ids) // 4, seq, at, tier, group))
            at += n

    def add(self, doc, ids: bytes):
        top, start, n = self.tiers[-1], 0, len(ids) // 4
        while n - start >= top:
            self._emit([(doc, ids, start, top)], top)
            start += top
        if start < n:
            self.held.append((n - start, next(self.serial), doc, ids, start))
            self.tokens += n - start
        if self.tokens >= self.block:
            self._pack(False)

    def _pack(self, last: bool):
        held = sorted(self.held)
        total = self.tokens
        for k in range(len(self.tiers) - 1, -1, -1):
            tier, below = self.tiers[k], self.tiers[k - 1] if k else 0
            while held and held[-1][0] > below and total >= tier:
                total -= self._window(held, tier)
        if last:
            while held:  # less than the shortest tier, or too little for one window of a longer tier
                size = 1 << (total.bit_length() - 1)
                total -= self._window(held, min(size, self.tiers[-1]))
        self.held, self.tokens = held, total

    def _window(self, held, tier) -> int:
        """Take documents out of held (sorted by length) to fill one window; returns the tokens taken."""
        parts, gap = [], tier
        while gap and held:
            at = bisect_right(held, gap, key=lambda x: x[0]) - 1
            if at >= 0:
                n, _, doc, ids, start = held.pop(at)
                parts.append((doc, ids, start, n))
                gap -= n
            elif gap < self.least and len(parts) and tier == self.tiers[-1]:
                break
            else:
                n, serial, doc, ids, start = held.pop(0)
                parts.append((doc, ids, start, gap))
                insort(held, (n - gap, serial, doc, ids, start + gap))
                gap = 0
        self._emit(parts, tier)
        return tier - gap

    def finish(self):
        self._pack(True)


_COLUMNS = (("doc_id", "long"), ("start", "long"), ("length", "long"), ("ids_crc32", "long"), ("doc_tokens", "long"), ("sequence_id", "long"), ("offset", "long"), ("tier", "long"), ("step_group", "long"))


def pack(docs: DataFrame, tokenizer_path: str, end_id: int = 2, tiers=TIERS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each piece of a document: where it lies in its document and in which sequence.

    tokenizer_path must exist on every executor. tier is the window the sequence was packed for; step_group is one training
    step: sequences of one tier whose windows make step_tokens together (the last group of a tier in a partition may be
    smaller). Sequence and group ids are unique over the whole result.
    """
    out = pa.schema([(c, pa.int64()) for c, _ in _COLUMNS])

    def run(batches):
        context = TaskContext.get()
        packer = Packer(tiers, (context.partitionId() if context else 0) << 34)
        encode = encoder(tokenizer_path, end_id)
        for batch in pieces(batches, "body", 2 << 20):
            for doc, ids in zip(column(batch, "doc_id"), encode(column(batch, "body"))):
                packer.add(doc, ids)
            if packer.rows:
                yield batch_of(out, list(zip(*packer.rows)))
                packer.rows = []
        packer.finish()
        if packer.rows:
            yield batch_of(out, list(zip(*packer.rows)))

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("body")).mapInArrow(run, ", ".join(f"{c} {t}" for c, t in _COLUMNS))
