"""Language identification by a bidirectional gated recurrent network over bytes.

The network reads the bytes of a word forwards and backwards and labels every byte position; the log-probabilities of all
positions of a document are summed and give its probabilities. A word is labelled alike wherever it stands, so each
distinct word is run once and counted as often as it occurs: whole texts at the price of their vocabulary. Training is
plain numpy, backpropagation through time with Adam, on a bounded sample of labelled rows.

Edges: a null text or one without a letter is `und` with score 0, as is every text when there is nothing to learn from;
long words are read in runs of MAX_BYTES bytes; ties go to the language that sorts first; repeated rows get equal results; a null
id stays null; an empty table gives no rows.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import batch_of, column, pieces

MAX_BYTES = 32
HASHES, SPARE = 1 << 31, 4
_GATES = ("z", "r", "h")


def _sigmoid(x):
    return 0.5 * (np.tanh(0.5 * x) + 1)


def padded(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(words x time bytes, mask); byte values are shifted by one so that zero pads."""
    length = np.fromiter(map(len, words), np.int64, len(words))
    wide = int(length.max())
    flat = np.frombuffer(b"".join(w.ljust(wide, b"\0") for w in words), np.uint8).reshape(len(words), wide)
    mask = np.arange(wide) < length[:, None]
    return np.where(mask, flat.astype(np.int64) + 1, 0), mask


class Network:
    """Weights of one embedding, two gated recurrent readers, and one labelling layer."""

    def __init__(self, classes: int, hidden: int = 12, embed: int = 12, seed: int = 7):
        rng = np.random.default_rng(seed)
        w = {"E": rng.normal(0, 0.3, (257, embed)), "O": rng.normal(0, 0.2, (2 * hidden, classes)), "o": np.zeros(classes)}
        for d in "fb":
            w |= {f"W{d}": rng.normal(0, embed**-0.5, (embed, 3 * hidden)), f"U{d}": rng.normal(0, hidden**-0.5, (hidden, 3 * hidden)), f"c{d}": np.zeros(3 * hidden)}
        self.w, self.h = {k: v.astype(np.float32) for k, v in w.items()}, hidden

    def read(self, x, mask, d, keep=False):
        """States of one reader at every position; padding leaves a state as it is."""
        n, time, h = *x.shape, self.h
        table = self.w["E"] @ self.w[f"W{d}"] + self.w[f"c{d}"]
        u = self.w[f"U{d}"]
        state, out, tape = np.zeros((n, h), np.float32), np.empty((n, time, h), np.float32), []
        for t in range(time) if d == "f" else range(time - 1, -1, -1):
            a = table[x[:, t]]
            zr = _sigmoid(a[:, : 2 * h] + state @ u[:, : 2 * h])
            z, r = zr[:, :h], zr[:, h:]
            c = np.tanh(a[:, 2 * h :] + (r * state) @ u[:, 2 * h :])
            live = mask[:, t, None]
            new = np.where(live, state + z * (c - state), state)
            if keep:
                tape.append((t, state, z, r, c, live))
            state = new
            out[:, t] = state
        return out, tape

    def labels(self, x, mask, keep=False):
        """Log-probabilities at every position."""
        f, tf = self.read(x, mask, "f", keep)
        b, tb = self.read(x, mask, "b", keep)
        both = np.concatenate([f, b], axis=2)
        logit = both @ self.w["O"] + self.w["o"]
        logit -= logit.max(axis=2, keepdims=True)
        logp = logit - np.log(np.exp(logit).sum(axis=2, keepdims=True))
        return logp, both, tf, tb

    def gradients(self, x, mask, y):
        logp, both, tf, tb = self.labels(x, mask, keep=True)
        n, h = mask.sum(), self.h
        p = np.exp(logp)
        p[np.arange(len(y)), :, y] -= 1
        p *= mask[:, :, None] / np.float32(n)
        g = {"O": np.einsum("nti,ntk->ik", both, p), "o": p.sum(axis=(0, 1)), "E": np.zeros_like(self.w["E"])}
        back = p @ self.w["O"].T
        for d, tape, part in (("f", tf, back[:, :, :h]), ("b", tb, back[:, :, h:])):
            u, w = self.w[f"U{d}"], self.w[f"W{d}"]
            gu, gtable, carry = np.zeros_like(u), np.zeros((257, 3 * h), np.float32), np.zeros((len(x), h), np.float32)
            for t, state, z, r, c, live in reversed(tape):
                carry = carry + part[:, t]
                through = np.where(live, carry, 0)
                dc = through * z * (1 - c * c)
                dz = through * (c - state) * z * (1 - z)
                drs = dc @ u[:, 2 * h :].T
                dr = drs * state * r * (1 - r)
                da = np.concatenate([dz, dr, dc], axis=1)
                gu[:, : 2 * h] += state.T @ da[:, : 2 * h]
                gu[:, 2 * h :] += (r * state).T @ dc
                np.add.at(gtable, x[:, t], da)
                carry = np.where(live, carry * (1 - z) + drs * r + da[:, : 2 * h] @ u[:, : 2 * h].T, carry)
            g |= {f"U{d}": gu, f"W{d}": self.w["E"].T @ gtable, f"c{d}": gtable.sum(axis=0)}
            g["E"] += gtable @ w.T
        loss = -float((logp[np.arange(len(y)), :, y] * mask).sum() / n)
        return loss, g


def train(samples: list[tuple[bytes, int]], classes: int, steps: int = 400, batch: int = 384, rate: float = 0.01, seed: int = 7, **shape) -> Network:
    """Fit on (word, class) pairs, every class drawn equally often."""
    net, rng = Network(classes, seed=seed, **shape), np.random.default_rng(seed)
    by = [[w for w, c in samples if c == k] for k in range(classes)]
    m = {k: np.zeros_like(v) for k, v in net.w.items()}
    s = {k: np.zeros_like(v) for k, v in net.w.items()}
    for step in range(1, steps + 1):
        words, y = [], []
        for k, own in enumerate(by):
            words += [own[i] for i in rng.integers(0, len(own), max(1, batch // classes))]
            y += [k] * max(1, batch // classes)
        _, g = net.gradients(*padded(words), np.array(y))
        now = rate * min(1.0, 3 * (1 - step / (steps + 1)))
        for k in net.w:
            m[k] = 0.9 * m[k] + 0.1 * g[k]
            s[k] = 0.99 * s[k] + 0.01 * g[k] ** 2
            net.w[k] -= (now * (m[k] / (1 - 0.9**step)) / (np.sqrt(s[k] / (1 - 0.99**step)) + 1e-7)).astype(np.float32)
    return net


def word_runs(text: str) -> list[bytes]:
    """All words, in lower case, cut into runs of at most MAX_BYTES bytes."""
    out = []
    for w in text.lower().split():
        b = w.encode()
        if len(b) <= MAX_BYTES:
            out.append(b)
        else:
            out += [b[i : i + MAX_BYTES] for i in range(0, len(b), MAX_BYTES)]
    return out


def has_letter(text: str | None) -> bool:
    return bool(text) and any(map(str.isalpha, text))


class Labeller:
    """Pools position probabilities over documents; sums of known words are kept between batches."""

    def __init__(self, net: Network, langs: list[str], cache: int = 400_000):
        self.net, self.langs, self.limit = net, langs, cache
        self.at: dict[bytes, int] = {}
        self.sums = np.zeros((1 << 16, len(langs) + 1), np.float32)

    def _learn(self, words):
        words = sorted(words, key=len)
        for lo in range(0, len(words), 2048):
            part = words[lo : lo + 2048]
            x, mask = padded(part)
            logp = self.net.labels(x, mask)[0]
            n = len(self.at)
            if n + len(part) > len(self.sums):
                self.sums = np.concatenate([self.sums, np.zeros_like(self.sums)])
            self.sums[n : n + len(part), :-1] = (logp * mask[:, :, None]).sum(axis=1)
            self.sums[n : n + len(part), -1] = mask.sum(axis=1)
            self.at.update(zip(part, range(n, n + len(part))))

    def __call__(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        if len(self.at) > self.limit:
            self.at, self.sums = {}, np.zeros((1 << 16, len(self.langs) + 1), np.float32)
        runs = [word_runs(t) if has_letter(t) else None for t in texts]
        new = set()
        for r in runs:
            new.update(r or ())
        new = [w for w in new if w not in self.at]
        if new:
            self._learn(new)
        langs, scores, at = [], [], self.at
        for r in runs:
            if r is None:
                langs.append("und")
                scores.append(0.0)
                continue
            total = self.sums[np.fromiter(map(at.__getitem__, r), np.int64, len(r))].sum(axis=0, dtype=np.float64)
            logit = total[:-1] - total[:-1].max()
            p = np.exp(logit)
            p /= p.sum()
            k = int(p.argmax())
            langs.append(self.langs[k])
            scores.append(float(p[k]))
        return langs, scores


_labellers: dict[bytes, Labeller] = {}


def labeller(net: Network, langs: list[str]) -> Labeller:
    """One labeller for each worker process and network, so that what a task has read serves the next."""
    mark = b"".join(v.tobytes() for v in net.w.values()) + repr(langs).encode()
    if mark not in _labellers:
        _labellers.clear()
        _labellers[mark] = Labeller(net, langs)
    return _labellers[mark]


def fit(labelled: DataFrame, text_col: str, lang_col: str, id_col: str, docs_per_lang: int = 250, max_chars: int = 20_000, words_per_lang: int = 30_000, max_langs: int = 1_000, **how) -> tuple[Network | None, list[str]]:
    """Train on at most docs_per_lang rows of each language, those of smallest hash whose text has at most max_chars.

    A count of each language tells below which hash SPARE times as many rows lie; only these are ranked, so that what is
    shuffled does not grow with the input. More than max_langs languages are refused.
    """
    rows = labelled.select(F.col(lang_col).cast("string").alias("lang"), F.col(text_col).cast("string").alias("body"), F.pmod(F.xxhash64(F.col(id_col)), F.lit(HASHES)).alias("h"))
    rows = rows.filter(F.col("lang").isNotNull() & F.length("body").between(1, max_chars))
    sizes = rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.min("h").alias("least")).limit(max_langs + 1).collect()
    if len(sizes) > max_langs:
        raise ValueError(f"more than {max_langs} languages")
    if not sizes:
        return None, []
    # the smallest hash always passes, should ids repeat
    upto = labelled.sparkSession.createDataFrame([(lang, max(least, min(HASHES, SPARE * docs_per_lang * HASHES // n))) for lang, n, least in sizes], "lang string, upto long")
    rank = Window.partitionBy("lang").orderBy("h", "body")
    rows = (
        rows.join(F.broadcast(upto), "lang")  # at most max_langs rows
        .filter(F.col("h") <= F.col("upto"))
        .withColumn("n", F.row_number().over(rank))
        .filter(F.col("n") <= docs_per_lang)
        .select("lang", "body")
        .collect()
    )
    words: dict[str, Counter] = {}
    for lang, body in sorted(map(tuple, rows)):
        if has_letter(body):
            words.setdefault(lang, Counter()).update(word_runs(body))
    langs = sorted(words)
    if not langs:
        return None, []
    samples = [(w, k) for k, lang in enumerate(langs) for w in list(words[lang].elements())[:: max(1, sum(words[lang].values()) // words_per_lang)]]
    return train(samples, len(langs), **how), langs


def predict(docs: DataFrame, net: Network | None, langs: list[str], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score) for each row of docs."""
    out = pa.schema([("doc_id", pa.int64()), ("lang_pred", pa.string()), ("score", pa.float64())])
    shared = docs.sparkSession.sparkContext.broadcast((net, langs))  # a few thousand weights

    def run(batches):
        label = labeller(*shared.value) if shared.value[1] else lambda t: (["und"] * len(t), [0.0] * len(t))
        for batch in pieces(batches, "body", 4 << 20):
            yield batch_of(out, [column(batch, "doc_id"), *label(column(batch, "body"))])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("body")).mapInArrow(run, "doc_id long, lang_pred string, score double")


def identify(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", **how) -> DataFrame:
    """Train on rows whose crc32(id) mod 3 is not 1, predict all; held_out marks the others."""
    fold = F.crc32(F.col(id_col).cast("string")) % 3
    net, langs = fit(docs.filter(fold != 1), text_col, lang_col, id_col, **how)
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False))
    return predict(docs, net, langs, id_col, text_col).select("doc_id", held.alias("held_out"), "lang_pred", "score")
