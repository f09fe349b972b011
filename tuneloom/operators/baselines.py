"""The methods to compare with."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import prompt, reason


class Classifier:
    """One logistic output for each knob over a frozen vector."""

    def __init__(self, knobs: list[str], weights: np.ndarray):
        self.knobs, self.weights = knobs, weights


#: Rows of a block of training data, and its columns.
BLOCK, BLOCKS = 1024, "part int, n int, at binary, x binary, y binary"
#: What is left out or rounded in a step moves no weight by more than this over all steps; sums in double precision may be off by as much.
SLACK = 1e-12


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    """The rows of an Arrow column of lists that has no nulls."""
    if len(column) and not (np.diff(column.offsets.to_numpy()) == dim).all():
        raise ValueError(f"a vector has not {dim} places")
    return column.flatten().to_numpy(zero_copy_only=False).astype(float, copy=False).reshape(len(column), dim)


def _blocks(rows: DataFrame, part: int, catalog: list[str], dim: int) -> DataFrame:
    """vec, knobs as blocks of rows: the places (in rows of dim + 1) and values of the vectors that are not zero, and the places of the labels. Rows without a vector are left out."""

    def run(batches):
        names = pa.array(catalog, pa.string())
        for batch in batches:
            batch = batch.filter(batch.column("vec").is_valid())
            for lo in range(0, batch.num_rows, BLOCK):
                some = batch.slice(lo, BLOCK)
                x, knobs = _matrix(some.column("vec"), dim).ravel(), some.column("knobs")
                of = pc.index_in(knobs.flatten(), value_set=names)
                known = of.is_valid().to_numpy(zero_copy_only=False)
                row, col = pc.list_parent_indices(knobs).to_numpy()[known], of.drop_null().to_numpy()
                at, y = np.flatnonzero(x), np.unique(row.astype(np.int64) * len(catalog) + col)
                yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "n": pa.array([some.num_rows], pa.int32()), "at": [(at + at // dim).astype(np.int32).tobytes()], "x": [x[at].tobytes()], "y": [y.astype(np.int32).tobytes()]})

    return rows.select(F.col("vec").cast("array<double>").alias("vec"), F.col("knobs").cast("array<string>").alias("knobs")).mapInArrow(run, BLOCKS)


def _opened(some, dim: int):
    """(part, rows with a last place of one, labels) of packed blocks; the rows are good until the next block."""
    whole = np.zeros((BLOCK, dim + 1))
    for part, size, at, values, y in some:
        at = np.frombuffer(at, np.int32)
        whole[:, :-1] = 0
        whole[:size, -1] = 1
        whole.ravel()[at] = np.frombuffer(values)
        yield part, whole[:size], np.frombuffer(y, np.int32)


def _totals(some, parts: int, k: int, dim: int):
    """Of each part the number of rows, their sum, and the sum of the rows of each label; the longest vector and the least value of all."""
    n, rows, labelled, far, least = np.zeros(parts, np.int64), np.zeros((parts, dim + 1)), np.zeros((parts, k, dim + 1)), 0.0, 0.0
    for part, x, y in _opened(some, dim):
        n[part] += len(x)
        rows[part] += x.sum(axis=0)
        if len(y):
            row, col = np.divmod(y, k)
            order = np.argsort(col, kind="stable")
            first = np.flatnonzero(np.r_[True, np.diff(col[order]) > 0])
            labelled[part, col[order[first]]] += np.add.reduceat(x[row[order]], first, axis=0)
        far, least = max(far, float(np.sqrt((x[:, :-1] ** 2).sum(axis=1)).max())), min(least, float(x[:, :-1].min(initial=0)))
    return n, rows, labelled, far, least


def _graded(w: np.ndarray, far: float, least: float, moves: float) -> tuple[np.ndarray, np.ndarray]:
    """(fine, coarse): the outputs whose scores need double precision, and those for which single precision does.

    No row's score is over that of a vector of the greatest length along the weights (along the positive ones where no value is
    negative). Outputs in neither have scores so near zero on every row that their sum moves no weight by SLACK over all steps.
    moves: what an error of one in the score of every row moves a weight over all steps."""
    slope = w[:, :-1]
    most = far * np.linalg.norm(np.maximum(slope, 0) if least >= 0 else slope, axis=1)
    p = np.exp(np.minimum(w[:, -1] + most, 0))
    heard = ~(moves * p <= SLACK)
    error = 2.0**-24 * ((slope.shape[1] + 4) * far * np.linalg.norm(slope, axis=1) + BLOCK + 8) + p
    small = (moves * p * error <= SLACK) & (most < 60)
    return np.flatnonzero(heard & ~small), np.flatnonzero(heard & small)


def _scored(some, starts, fine: np.ndarray, coarse: np.ndarray):
    """The sums of the rows by their scores, for outputs in double precision and, without their bias, for those in single precision.

    fine: negative weights, coarse: weights; starts: of each part the first output of each that learns from it."""
    g, h = np.zeros(fine.shape[::-1]), np.zeros(coarse.shape[::-1])
    room, room32 = np.empty(BLOCK * fine.shape[1]), np.empty(BLOCK * coarse.shape[1], np.float32)
    for part, x, _ in _opened(some, len(fine) - 1):
        i, j = starts[part]
        if i < len(g):
            p = room[: len(x) * (len(g) - i)].reshape(len(x), -1)
            np.matmul(x, fine[:, i:], out=p)
            with np.errstate(over="ignore"):
                np.exp(p, out=p)
            p += 1
            np.reciprocal(p, out=p)
            g[i:] += p.T @ x
        if j < len(h):
            x = x.astype(np.float32)
            p = room32[: len(x) * (len(h) - j)].reshape(len(x), -1)
            np.matmul(x, coarse[:, j:], out=p)
            np.exp(p, out=p)
            h[j:] += p.T @ x
    return g, h


def plm_fit_nested(parts: list[DataFrame], catalog: list[str], dim: int, iters: int = 60, rate: float = 2.0, l2: float = 1e-4) -> list[Classifier]:
    """A classifier for each part, trained on it and all before it; the steps of all are taken together, so that a step reads each row once.

    Full-batch steps from zero; each is one job of partial sums, added in partition order. The labels' share of a gradient is the
    same in each step and summed once; a step whose scores are all too near zero to move a weight needs no job. parts: vec, knobs."""
    k, m = len(catalog), len(parts)
    w = np.zeros((m * k, dim + 1))
    blocks = reduce(DataFrame.unionByName, [_blocks(p, i, catalog, dim) for i, p in enumerate(parts)]).rdd.map(tuple)
    sc = blocks.context
    # whole waves, as each step waits for its last task; few, as each task returns a sum for each output
    rows = blocks.repartition(min(4, -(-max(1, blocks.getNumPartitions()) // sc.defaultParallelism)) * sc.defaultParallelism).persist(StorageLevel.MEMORY_AND_DISK)
    found = rows.mapPartitions(lambda some: [_totals(some, m, k, dim)]).collect()
    n, total, labelled = (np.repeat(np.cumsum(sum(f[i] for f in found), axis=0), [k, k, 1][i], axis=0) for i in range(3))
    n, labelled = n[:, None], labelled.reshape(m * k, dim + 1)
    far, least = max(f[3] for f in found), min(f[4] for f in found)
    for step in range(iters if n.any() else 0):
        scores = total / 2  # with weights of zero every score is one half
        if step:
            scores, (fine, coarse) = np.zeros_like(w), _graded(w, far, least, rate * iters * max(1.0, far))
            if len(fine) + len(coarse):
                starts = [(int(np.searchsorted(fine, p * k)), int(np.searchsorted(coarse, p * k))) for p in range(m)]
                slope = w[coarse].astype(np.float32)
                slope[:, -1] = 0
                shared = sc.broadcast((starts, np.ascontiguousarray(-w[fine].T), np.ascontiguousarray(slope.T)))
                sums = rows.mapPartitions(lambda some, shared=shared: [_scored(some, *shared.value)]).collect()
                shared.destroy()
                scores[fine] = sum(g for g, _ in sums)
                scores[coarse] = sum(h for _, h in sums) * np.exp(w[coarse, -1:])
        w = np.where(n > 0, w - rate * ((scores - labelled) / np.maximum(n, 1) + l2 * w), w)
    rows.unpersist()
    return [Classifier(catalog, x) for x in w.reshape(m, k, dim + 1)]


def plm_fit(train: DataFrame, catalog: list[str], dim: int, **how) -> Classifier:
    return plm_fit_nested([train], catalog, dim, **how)[0]


def plm_predict_all(models: dict[str, Classifier], queries: DataFrame, threshold: float = 0.5) -> DataFrame:
    """(model, qid, knob, p) with p strictly over the threshold; each query is read once for all models."""
    shared = queries.sparkSession.sparkContext.broadcast([(name, m.knobs, m.weights) for name, m in models.items()])
    kind = queries.select("qid").schema["qid"].dataType
    schema = T.StructType([T.StructField("model", T.StringType()), T.StructField("qid", kind), T.StructField("knob", T.StringType()), T.StructField("p", T.DoubleType())])

    def run(batches):
        for batch in batches:
            batch = batch.filter(batch.column("vec").is_valid())
            for lo in range(0, batch.num_rows, BLOCK):
                some = batch.slice(lo, BLOCK)
                for name, knobs, w in shared.value:
                    with np.errstate(over="ignore"):
                        p = 1 / (1 + np.exp(-(_matrix(some.column("vec"), w.shape[1] - 1) @ w[:, :-1].T + w[:, -1])))
                    row, col = np.nonzero(p > threshold - 1e-8)  # what counts is p as it is rounded below
                    found = [pa.array([name] * len(row), pa.string()), some.column("qid").take(pa.array(row)), pa.array(knobs, pa.string()).take(pa.array(col)), pa.array(p[row, col])]
                    yield pa.RecordBatch.from_arrays(found, ["model", "qid", "knob", "p"])

    scored = queries.select("qid", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(run, schema)
    return scored.withColumn("p", F.round("p", 9)).filter(F.col("p") > threshold)


def plm_predict(model: Classifier, queries: DataFrame, threshold: float = 0.5) -> DataFrame:
    """(qid, knob, p) with p strictly over the threshold."""
    return plm_predict_all({"": model}, queries, threshold).drop("model")


def plm_fit_augmented(train: DataFrame, augmented: DataFrame, catalog: list[str], dim: int, **how) -> Classifier:
    return plm_fit(train.select("vec", "knobs").unionByName(augmented.select("vec", "knobs")), catalog, dim, **how)


def llm(questions: DataFrame, reasoner, style: str = "plain", **how) -> DataFrame:
    """Plain, step-by-step or task-decomposition prompting: no evidence."""
    return reason.run(lambda phase, chosen: prompt.build(questions, phase=phase, style=style, chosen=chosen), reasoner, **how)


def llm_all_knobs(questions: DataFrame, knobs: DataFrame, reasoner) -> DataFrame:
    return reason.parse(reasoner(prompt.build_all_knobs(questions, knobs)), "list")


def llm_decomposed(questions: DataFrame, reasoner, parts: int = 3) -> DataFrame:
    """Task decomposition: a question's sentences are dealt to `parts` sub-problems, each is asked by itself, and the knobs named
    in any of them are the answer (qid, ok, knobs); ok where all parts could be read."""
    from .corpus import SENTENCE_END

    pieces = F.filter(F.split("text", SENTENCE_END), lambda s: F.trim(s) != "")
    dealt = questions.select("qid", F.posexplode(pieces).alias("at", "s")).withColumn("part", F.col("at") % parts)
    dealt = dealt.groupBy("qid", "part").agg(F.concat_ws(". ", F.transform(F.array_sort(F.collect_list(F.struct("at", "s"))), lambda x: x["s"])).alias("text"))
    # a sub-problem is a question of its own; its number leads back
    asked = prompt.build(dealt.select((F.col("qid") * parts + F.col("part")).alias("qid"), "text"), style="decompose")
    read = reason.parse(reasoner(asked), "list").withColumn("qid", F.floor(F.col("qid") / parts))
    return read.groupBy("qid").agg(F.min("ok").alias("ok"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("knobs")))).alias("knobs"))


def sft_pairs(train: DataFrame) -> DataFrame:
    """(qid, line): one JSON line for each labelled question. train: qid, text, knobs. Tuning itself happens elsewhere."""
    line = F.to_json(F.struct(F.lit(prompt.ASK[1]).alias("instruction"), F.col("text").alias("input"), F.to_json("knobs").alias("output")))
    return train.select("qid", line.alias("line"))
