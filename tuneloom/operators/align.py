"""Pair mining and contrastive training of alignment heads over frozen base vectors."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import unit
from ..sources.tables import stored
from .vindex import topk_blocked, topk_exact

TYPES = {"qm": ("question", "question", "manual"), "qq": ("question", "question", "question"), "mm": ("manual", "manual", "manual")}


def mine(queries: DataFrame, docs: DataFrame, kind: str, top_m: int = 20) -> DataFrame:
    """(qid, doc_id, dist, rank): near documents that share a knob (pos) or share none (neg, hard by nearness).

    queries: qid, vec, knobs; docs: doc_id, source, vec, knobs."""
    near = topk_blocked(queries.select("qid", "vec"), docs, top_m)
    return _agreeing(near.join(queries.select("qid", F.col("knobs").alias("want")), "qid"), kind)


def _agreeing(both: DataFrame, kind: str) -> DataFrame:
    share = F.arrays_overlap("knobs", "want")
    return both.filter(share if kind == "pos" else ~share).filter(F.col("qid") != F.col("doc_id")).select("qid", "doc_id", "dist", "rank")


def anchors(docs: DataFrame, source: str, most: int) -> DataFrame:
    """At most `most` documents of a source as anchors (qid, source, vec, knobs): a bounded training sample, by the md5 of the id."""
    return docs.filter(F.col("source") == source).orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id").limit(most).select(F.col("doc_id").alias("qid"), "source", "vec", "knobs")


def balance(pos: DataFrame, neg: DataFrame, keys: list[str], step: float = 0.001) -> tuple[DataFrame, DataFrame]:
    """Equally many positives and negatives for each key, the nearest first; ties by qid, then doc_id.

    Pairs are counted by steps of distance, so only the step in which a key's last pair falls is ranked, and no task sorts a
    whole key. A pair without a distance comes last."""
    cell = F.floor(F.coalesce("dist", F.lit(1e9)) / step)
    counted = lambda df, n: df.groupBy(*keys).agg(F.count(F.lit(1)).alias(n))
    least = counted(pos, "np").join(counted(neg, "nn"), keys).select(*keys, F.least("np", "nn").alias("m"))

    def cut(df: DataFrame) -> DataFrame:
        df = df.withColumn("_cell", cell)
        per = df.groupBy(*keys, "_cell").agg(F.count(F.lit(1)).alias("_own"))
        upto = F.sum("_own").over(Window.partitionBy(*keys).orderBy("_cell"))  # some 2,000 steps a key
        room = per.withColumn("_upto", upto).join(least, keys).select(*keys, "_cell", "_own", (F.col("m") - F.col("_upto") + F.col("_own")).alias("_room")).filter("_room > 0")
        near = df.join(room, [*keys, "_cell"])
        last = near.filter("_room < _own").withColumn("_r", F.row_number().over(Window.partitionBy(*keys, "_cell").orderBy("dist", "qid", "doc_id"))).filter("_r <= _room")
        return near.filter("_room >= _own").select(df.columns).unionByName(last.select(df.columns)).drop("_cell")

    return cut(pos), cut(neg)


def build_pairs(queries: DataFrame, docs: DataFrame, types=("qm", "qq", "mm"), top_m: int = 20, negatives: int = 4) -> DataFrame:
    """(qid, pos_id, neg_ids, pair_type, q_source, pos_source, neg_source): what fit() takes, as many positives as negatives of each
    type. queries carry their own source; the three types say which source anchors, agrees, differs.

    The documents near the anchors of a source are searched once, for each source, and stored; all types choose from them."""
    near = {}
    for anchor in sorted({TYPES[t][0] for t in types}):
        q = queries.filter(F.col("source") == anchor)
        both = topk_exact(q.select("qid", "vec"), docs, top_m, per_source=True, sources={s for t in types if TYPES[t][0] == anchor for s in TYPES[t][1:]})
        near[anchor] = stored(both.join(q.select("qid", F.col("knobs").alias("want")), "qid"), "near")
    out = None
    for t in types:
        anchor, agree, differ = TYPES[t]
        pos = _agreeing(near[anchor].filter(F.col("source") == agree), "pos").withColumn("pair_type", F.lit(t))
        neg = _agreeing(near[anchor].filter(F.col("source") == differ), "neg").withColumn("pair_type", F.lit(t))
        pos, neg = balance(pos, neg, ["pair_type"])
        near_neg = neg.withColumn("r", F.row_number().over(Window.partitionBy("qid").orderBy("dist", "doc_id"))).filter(F.col("r") <= negatives)
        lists = near_neg.groupBy("qid").agg(F.transform(F.array_sort(F.collect_list(F.struct("r", "doc_id"))), lambda s: s["doc_id"]).alias("neg_ids"))
        part = pos.join(lists, "qid").select("qid", F.col("doc_id").alias("pos_id"), "neg_ids", "pair_type", F.lit(anchor).alias("q_source"), F.lit(agree).alias("pos_source"), F.lit(differ).alias("neg_source"))
        out = part if out is None else out.unionByName(part)
    return out


class Head:
    """f(x) = normalise(x + W2 tanh(W1 x + b1) + b2); W2 = 0 at the start, so zero epochs leave the base vectors."""

    def __init__(self, dim: int, hidden: int, seed: int):
        rng = np.random.default_rng(seed)
        self.w = {"W1": rng.normal(0, dim**-0.5, (hidden, dim)), "b1": np.zeros(hidden), "W2": np.zeros((dim, hidden)), "b2": np.zeros(dim)}

    def __call__(self, x):
        return self.forward(x)[0]

    def forward(self, x):
        h = np.tanh(x @ self.w["W1"].T + self.w["b1"])
        z = x + h @ self.w["W2"].T + self.w["b2"]
        size = np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-12)
        return z / size, (x, h, z / size, size)

    def backward(self, grad, tape):
        x, h, f, size = tape
        dz = (grad - f * (grad * f).sum(axis=1, keepdims=True)) / size
        dh = (dz @ self.w["W2"]) * (1 - h * h)
        return {"W2": dz.T @ h, "b2": dz.sum(axis=0), "W1": dh.T @ x, "b1": dh.sum(axis=0)}


def info_nce(q, pos, neg, tau: float = 0.1, form: str = "attract"):
    """Loss and its gradients to the unit vectors q (n x d), pos (n x d), neg (n x m x d).

    attract: -log(exp(-d+/tau) / sum exp(-d-/tau)); standard: the positive is in the sum as well; as_printed: the sign of the
    distances turned round, which drives positives away and is here only to show that."""
    sign = 1.0 if form == "as_printed" else -1.0
    dp, dn = ((q - pos) ** 2).sum(-1), ((q[:, None] - neg) ** 2).sum(-1)
    a, b = sign * dp / tau, sign * dn / tau
    logits = np.concatenate([a[:, None], b], axis=1) if form == "standard" else b
    top = logits.max(axis=1, keepdims=True)
    e = np.exp(logits - top)
    total = e.sum(axis=1, keepdims=True)
    loss = -a + top[:, 0] + np.log(total[:, 0])
    share = e / total
    ga = -np.ones(len(q)) + (share[:, 0] if form == "standard" else 0)
    gb = share[:, 1:] if form == "standard" else share
    cp, cn = (ga * sign * 2 / tau)[:, None], (gb * sign * 2 / tau)[:, :, None]
    gq = cp * (q - pos) + (cn * (q[:, None] - neg)).sum(axis=1)
    return loss, gq, -cp * (q - pos), -cn * (q[:, None] - neg)


def fit(pairs: DataFrame, vecs: DataFrame, dim: int, hidden: int | None = None, tau: float = 0.1, rate: float = 0.02, epochs: int = 20, schedule=("mm", "qm", "qq"), form: str = "attract", seed: int = 7, freeze_base: bool = True, max_pairs: int = 200_000):
    """({source: Head}, losses). pairs: qid, pos_id, neg_ids, pair_type, q_source, pos_source, neg_source; vecs: id, source, vec.

    Vectors are joined to a bounded sample of pairs once and stored; each epoch is one job that sums partial gradients on the
    executors, partition by partition, and the driver adds them in partition order."""
    if not freeze_base:
        raise ValueError("the base encoder is frozen; only the heads learn")
    hidden = hidden or 2 * dim
    sample = stored(pairs.orderBy(F.xxhash64("qid", "pos_id")).limit(max_pairs), "pairs")
    ends = [sample.select(F.col(i).alias("id"), F.col(s).alias("source")) for i, s in (("qid", "q_source"), ("pos_id", "pos_source"))]
    ends.append(sample.select(F.explode("neg_ids").alias("id"), F.col("neg_source").alias("source")))
    ends = ends[0].unionByName(ends[1]).unionByName(ends[2]).distinct()
    # only the vectors that the sample names are moved, at most a few for each of its pairs
    v = vecs.select("id", "source", "vec").join(F.broadcast(ends), ["id", "source"], "left_semi")
    v = stored(v.select("id", "source", unit(F.col("vec")).alias("vec")).filter("vec is not null").dropDuplicates(["id", "source"]), "vectors")
    rows = sample.join(v.select(F.col("id").alias("qid"), F.col("source").alias("q_source"), F.col("vec").alias("q")), ["qid", "q_source"])
    rows = rows.join(v.select(F.col("id").alias("pos_id"), F.col("source").alias("pos_source"), F.col("vec").alias("p")), ["pos_id", "pos_source"])
    neg = sample.select("qid", "pos_id", "pair_type", "neg_source", F.posexplode("neg_ids").alias("r", "neg_id")).join(v.select(F.col("id").alias("neg_id"), F.col("source").alias("neg_source"), F.col("vec").alias("n")), ["neg_id", "neg_source"])
    neg = neg.groupBy("qid", "pos_id", "pair_type").agg(F.transform(F.array_sort(F.collect_list(F.struct("r", "n"))), lambda s: s["n"]).alias("n"))
    rows = stored(rows.join(neg, ["qid", "pos_id", "pair_type"]).select("pair_type", "q_source", "pos_source", "neg_source", "q", "p", "n"), "rows").persist()
    heads = {"question": Head(dim, hidden, seed), "manual": Head(dim, hidden, seed + 1)}
    losses = []
    state = {(s, k): (np.zeros_like(w), np.zeros_like(w)) for s, h in heads.items() for k, w in h.w.items()}
    step = 0
    for phase in schedule:
        part = rows.filter(F.col("pair_type") == phase)  # from here on all jobs read the stored sample
        for epoch in range(epochs):
            shared = part.sparkSession.sparkContext.broadcast(({s: h.w for s, h in heads.items()}, dim, hidden, tau, form))

            def run(batches, shared=shared):
                weights, d, hid, t, f = shared.value
                local = {s: Head(d, hid, 0) for s in weights}
                for s in weights:
                    local[s].w = weights[s]
                loss, n, grads = 0.0, 0, {(s, k): np.zeros_like(w) for s in weights for k, w in weights[s].items()}
                for pdf in batches:
                    for (qs, ps, ns, m), g in pdf.assign(m=pdf["n"].map(len)).groupby(["q_source", "pos_source", "neg_source", "m"]):
                        q, tq = local[qs].forward(np.stack(g["q"]))
                        p, tp = local[ps].forward(np.stack(g["p"]))
                        x, tn = local[ns].forward(np.concatenate([np.stack(z) for z in g["n"]]))
                        ls, gq, gp, gn = info_nce(q, p, x.reshape(len(g), m, d), t, f)
                        loss, n = loss + ls.sum(), n + len(g)
                        for src, grad, tape in ((qs, gq, tq), (ps, gp, tp), (ns, gn.reshape(-1, d), tn)):
                            for k, w in local[src].backward(grad, tape).items():
                                grads[src, k] += w
                if n:
                    flat = np.concatenate([grads[k].ravel() for k in sorted(grads)])
                    yield pd.DataFrame({"n": [n], "loss": [loss], "grad": [flat]})

            parts = sorted(part.mapInPandas(run, "n long, loss double, grad array<double>").withColumn("pid", F.spark_partition_id()).collect(), key=lambda r: r["pid"])  # a sort in Spark would run the job twice
            n = sum(r["n"] for r in parts)
            if not n:
                break
            total = np.sum([np.asarray(r["grad"]) for r in parts], axis=0) / n
            losses.append((epoch, phase, sum(r["loss"] for r in parts) / n))
            step, at = step + 1, 0
            for s, k in sorted(state):
                w = heads[s].w[k]
                g = total[at : at + w.size].reshape(w.shape)
                at += w.size
                m1, m2 = state[s, k]
                m1 = 0.9 * m1 + 0.1 * g
                m2 = 0.999 * m2 + 0.001 * g * g
                state[s, k] = (m1, m2)
                heads[s].w[k] = w - rate * (m1 / (1 - 0.9**step)) / (np.sqrt(m2 / (1 - 0.999**step)) + 1e-8)
    rows.unpersist()
    return heads, losses


def apply(df: DataFrame, heads: dict, vec: str = "vec", source: str = "source") -> DataFrame:
    """df with vec moved into the shared space; one matrix product for each Arrow batch and source."""
    shared = df.sparkSession.sparkContext.broadcast({s: h.w for s, h in heads.items()})  # a few weights for each dimension
    df = df.withColumn(vec, F.col(vec).cast("array<double>"))

    def run(batches):
        local = {}
        for name, w in shared.value.items():
            local[name] = Head(w["W1"].shape[1], w["W1"].shape[0], 0)
            local[name].w = w
        for batch in batches:
            place = batch.schema.get_field_index(vec)
            column, sources = batch.column(place), batch.column(batch.schema.get_field_index(source))
            known = np.flatnonzero(column.is_valid().to_numpy(zero_copy_only=False))
            if not len(known):
                yield batch
                continue
            x = column.drop_null().flatten().to_numpy(zero_copy_only=False).reshape(len(known), -1).copy()
            names = sources.take(pa.array(known))
            for name, head in local.items():
                at = np.flatnonzero(pc.fill_null(pc.equal(names, name), False).to_numpy(zero_copy_only=False))
                if len(at):
                    x[at] = head(x[at] / np.maximum(np.linalg.norm(x[at], axis=1, keepdims=True), 1e-12))
            size = np.zeros(batch.num_rows + 1, np.int32)
            size[known + 1] = x.shape[1]
            moved = pa.ListArray.from_arrays(pa.array(np.cumsum(size), pa.int32()), pa.array(x.ravel()), mask=pa.array(~column.is_valid().to_numpy(zero_copy_only=False)))
            yield batch.set_column(place, batch.schema.field(place), moved.cast(batch.schema.field(place).type))

    return df.mapInArrow(run, df.schema)


def train(questions: DataFrame, docs: DataFrame, dim: int, most: int = 500, **how):
    """({source: Head}, losses): pairs mined around the questions and a sample of manuals and history, manual pairs first.

    questions: qid, vec, knobs; docs: doc_id, source, vec, knobs. `most` bounds the anchors of each source."""
    own = questions.withColumn("source", F.lit("question")).withColumnRenamed("qid", "doc_id")
    queries = stored(anchors(own, "question", most).unionByName(anchors(docs, "manual", most)), "anchors")
    vecs = docs.select(F.col("doc_id").alias("id"), "source", "vec")
    # anchors that are no documents, as synthetic questions are, bring their own vector
    other = queries.filter("source = 'question'").select(F.col("qid").alias("id"), "source", "vec")
    return fit(build_pairs(queries, docs), vecs.unionByName(other), dim, **how)
