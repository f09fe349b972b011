"""Measures over predicted and true knob sets, retrieval hits, answers and costs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _share(a, b):
    return F.when(b > 0, a / b).otherwise(F.lit(0.0))


def prf(pred: DataFrame, truth: DataFrame, qid: str = "qid", item: str = "knob") -> DataFrame:
    """(qid, n_pred, n_true, n_hit, precision, recall, f1) from distinct (qid, item) rows, one full join on both.

    Every question of either side appears; 0/0 counts as 0. Questions without truth have n_true = 0."""
    p = pred.select(qid, item).distinct().withColumn("p", F.lit(1))
    t = truth.select(qid, item).distinct().withColumn("t", F.lit(1))
    both = p.join(t, [qid, item], "full").groupBy(qid).agg(F.count("p").alias("n_pred"), F.count("t").alias("n_true"), F.count(F.col("p") + F.col("t")).alias("n_hit"))
    precision, recall = _share(F.col("n_hit"), F.col("n_pred")), _share(F.col("n_hit"), F.col("n_true"))
    f1 = F.when(F.col("n_hit") > 0, 2.0 * F.col("n_hit") / (F.col("n_pred") + F.col("n_true"))).otherwise(F.lit(0.0))
    return both.select(qid, "n_pred", "n_true", "n_hit", precision.alias("precision"), recall.alias("recall"), f1.alias("f1"))


def macro(scores: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Means over questions that have a truth; those without are counted apart. Mean F1, not the F1 of means."""
    has = F.col("n_true") > 0
    mean = lambda c: F.round(F.avg(F.when(has, F.col(c))), 6).alias(c)
    return scores.groupBy(*(by or [])).agg(F.count(F.when(has, 1)).alias("questions"), F.count(F.when(~has, 1)).alias("without_truth"), mean("precision"), mean("recall"), mean("f1"))


def micro(scores: DataFrame) -> DataFrame:
    s = scores.filter("n_true > 0").agg(F.sum("n_pred").alias("p"), F.sum("n_true").alias("t"), F.sum("n_hit").alias("h"))
    return s.select(F.round(_share(F.col("h"), F.col("p")), 6).alias("precision"), F.round(_share(F.col("h"), F.col("t")), 6).alias("recall"), F.round(_share(2.0 * F.col("h"), F.col("p") + F.col("t")), 6).alias("f1"))


def doc_recall(hits: DataFrame, truth: DataFrame, ks=(1, 3, 5, 10)) -> DataFrame:
    """(k, recall): mean share of a question's knobs that its k best documents carry.

    hits: qid, rank, knobs; truth: qid, knob. The least rank of each (question, knob) serves every k in one pass."""
    least = hits.select("qid", "rank", F.explode("knobs").alias("knob")).groupBy("qid", "knob").agg(F.min("rank").alias("rank"))
    per = truth.select("qid", "knob").distinct().join(least, ["qid", "knob"], "left").groupBy("qid").agg(*(F.avg(F.when(F.col("rank") <= k, 1.0).otherwise(0.0)).alias(f"r{k}") for k in ks))
    wide = per.agg(*(F.round(F.avg(f"r{k}"), 6).alias(f"r{k}") for k in ks))
    return wide.select(F.explode(F.array(*(F.struct(F.lit(k).alias("k"), F.col(f"r{k}").alias("recall")) for k in ks))).alias("s")).select("s.*")


def frequency_buckets(history: DataFrame, knob: str = "knob", buckets: int = 3) -> DataFrame:
    """(knob, uses, bucket): knobs from frequent (1) to rare, equal in number, ties by name.

    How many knobs are used more often follows from the numbers of uses that occur, which are few; only knobs of equal use are
    ranked among themselves."""
    per = history.groupBy(knob).agg(F.count(F.lit(1)).alias("uses"))
    sizes = per.groupBy("uses").agg(F.count(F.lit(1)).alias("k"))
    more = sizes.alias("a").join(F.broadcast(sizes.alias("b")), F.col("b.uses") > F.col("a.uses"), "left").groupBy(F.col("a.uses").alias("uses")).agg(F.coalesce(F.sum("b.k"), F.lit(0)).alias("before"))
    total = sizes.agg(F.sum("k").alias("n"))
    ranked = per.join(F.broadcast(more), "uses").crossJoin(F.broadcast(total))  # as many rows as there are numbers of uses, and one row
    place = F.col("before") + F.row_number().over(Window.partitionBy("uses").orderBy(knob)) - 1
    size, extra = F.floor(F.col("n") / buckets), F.col("n") % buckets  # the first `extra` buckets hold one more
    bucket = F.when(place < extra * (size + 1), F.floor(place / (size + 1))).otherwise(extra + F.floor((place - extra * (size + 1)) / F.greatest(size, F.lit(1))))
    return ranked.select(knob, "uses", (bucket + 1).cast("int").alias("bucket"))


def by_frequency(pred: DataFrame, truth: DataFrame, history: DataFrame, qid: str = "qid", knob: str = "knob", buckets: int = 3) -> DataFrame:
    """Macro measures with prediction and truth both restricted to the knobs of a bucket."""
    b = frequency_buckets(history, knob, buckets).select(knob, "bucket")
    key = F.concat_ws("/", F.col(qid).cast("string"), F.col("bucket").cast("string"))
    on = lambda df: df.select(qid, knob).join(b, knob).select(key.alias("qid"), F.col(knob).alias("knob"))
    scores = prf(on(pred), on(truth)).withColumn("bucket", F.substring_index("qid", "/", -1).cast("int"))
    return macro(scores, ["bucket"])


def solved(pred: DataFrame, truth: DataFrame, qid: str = "qid", item: str = "knob") -> DataFrame:
    """(qid, solved): a stand-in for the judges; solved when every true item is predicted (items may carry values)."""
    t = truth.select(qid, item).distinct()
    p = pred.select(qid, item).distinct().withColumn("hit", F.lit(1))
    return t.join(p, [qid, item], "left").groupBy(qid).agg((F.count("hit") == F.count(F.lit(1))).alias("solved"))


def success_rate(pred: DataFrame, truth: DataFrame, **on) -> DataFrame:
    return solved(pred, truth, **on).agg(F.count(F.lit(1)).alias("questions"), F.round(F.avg(F.col("solved").cast("double")), 6).alias("success_rate"))


def by_kind(pred: DataFrame, truth: DataFrame, kinds: DataFrame, qid: str = "qid", item: str = "knob") -> DataFrame:
    """(kind, questions, success_rate): a question counts in each kind its truth has."""
    s = solved(pred, truth, qid, item)
    has = truth.select(qid, item).distinct().join(kinds.select(item, "kind"), item).select(qid, "kind").distinct()
    return has.join(s, qid).groupBy("kind").agg(F.count(F.lit(1)).alias("questions"), F.round(F.avg(F.col("solved").cast("double")), 6).alias("success_rate"))


def recall_by_frequency(hits: DataFrame, truth: DataFrame, history: DataFrame, ks=(1, 3, 5, 10), buckets: int = 3) -> DataFrame:
    """(bucket, k, recall): doc_recall with each question's knobs restricted to those of one frequency bucket of the history."""
    b = frequency_buckets(history, "knob", buckets).select("knob", "bucket")
    own = truth.join(b, "knob").select(F.struct("bucket", "qid").alias("qid"), "knob")
    least = hits.select("qid", "rank", F.explode("knobs").alias("knob")).groupBy("qid", "knob").agg(F.min("rank").alias("rank")).join(b, "knob").select(F.struct("bucket", "qid").alias("qid"), "knob", "rank")
    per = own.distinct().join(least, ["qid", "knob"], "left").groupBy("qid").agg(*(F.avg(F.when(F.col("rank") <= k, 1.0).otherwise(0.0)).alias(f"r{k}") for k in ks))
    wide = per.groupBy(F.col("qid.bucket").alias("bucket")).agg(*(F.round(F.avg(f"r{k}"), 6).alias(f"r{k}") for k in ks))
    return wide.select("bucket", F.explode(F.array(*(F.struct(F.lit(k).alias("k"), F.col(f"r{k}").alias("recall")) for k in ks))).alias("s")).select("bucket", "s.*")


def audit(sample: DataFrame, automatic: str, checked: str) -> DataFrame:
    """(checked, agreement): how many sampled labels a person looked at, and the share that agrees with the automatic one."""
    seen = sample.filter(F.col(checked).isNotNull())
    return seen.agg(F.count(F.lit(1)).alias("checked"), F.round(F.avg(F.col(automatic).eqNullSafe(F.col(checked)).cast("double")), 6).alias("agreement"))


def mean_set_size(answers: DataFrame, knobs: str = "knobs") -> DataFrame:
    return answers.agg(F.round(F.avg(F.size(knobs)), 6).alias("mean_size"))


def coverage(labelled: DataFrame, knobs: DataFrame) -> DataFrame:
    """Share of the catalogue that a labelled set uses."""
    used = labelled.select(F.explode("knobs").alias("knob")).distinct().join(knobs.select("knob").distinct(), "knob", "left_semi").agg(F.count(F.lit(1)).alias("used"))
    size = knobs.agg(F.count_distinct("knob").alias("catalog"))
    return used.crossJoin(size).withColumn("coverage", F.round(F.col("used") / F.nullif(F.col("catalog"), F.lit(0)), 6))


def cost(prompts: DataFrame, prices: DataFrame, text: str = "text") -> DataFrame:
    """(model, prompts, mean_tokens, usd): white-space tokens times price; prices is a few rows."""
    n = F.size(F.filter(F.split(F.trim(F.col(text)), r"\s+"), lambda w: w != ""))
    per = prompts.select(n.alias("tokens")).crossJoin(F.broadcast(prices))
    return per.groupBy("model").agg(F.count(F.lit(1)).alias("prompts"), F.round(F.avg("tokens"), 6).alias("mean_tokens"), F.round(F.avg(F.col("tokens") * F.col("usd_per_1k_in") / 1000), 9).alias("usd"))


def failure_rates(answers: DataFrame, knobs: DataFrame) -> DataFrame:
    """Share of unparsed answers and of predicted knobs that do not exist. answers: ok, knobs."""
    bad = answers.agg(F.round(F.avg((~F.col("ok")).cast("double")), 6).alias("format_failures"))
    named = answers.select(F.explode("knobs").alias("knob")).join(knobs.select("knob").distinct().withColumn("known", F.lit(1)), "knob", "left")
    return bad.crossJoin(named.agg(F.round(F.avg(F.when(F.col("known").isNull(), 1.0).otherwise(0.0)), 6).alias("hallucinated")))


def detection(pred: DataFrame, truth: DataFrame, keys: list[str]) -> DataFrame:
    """Precision, recall, F1 of anomalous (series, time) pairs."""
    one = lambda df, c: df.select(*keys).distinct().withColumn(c, F.lit(1))
    n = one(pred, "p").join(one(truth, "t"), keys, "full").agg(F.count("p").alias("p"), F.count("t").alias("t"), F.count(F.col("p") + F.col("t")).alias("h"))
    return n.select(_share(F.col("h"), F.col("p")).alias("precision"), _share(F.col("h"), F.col("t")).alias("recall"), _share(2.0 * F.col("h"), F.col("p") + F.col("t")).alias("f1"))


def diversity(texts: DataFrame, text: str = "text") -> DataFrame:
    """distinct-1 and distinct-2: distinct word n-grams over all n-grams."""
    w = F.split(F.lower(F.trim(F.col(text))), r"\s+")
    uni = texts.select(F.explode(w).alias("g")).agg(F.round(F.count_distinct("g") / F.count("g"), 6).alias("distinct_1"))
    pairs = F.when(F.size(w) > 1, F.zip_with(F.slice(w, 1, F.size(w) - 1), F.slice(w, 2, F.size(w) - 1), lambda a, b: F.concat_ws(" ", a, b)))
    two = texts.select(F.explode(pairs).alias("g")).agg(F.round(F.count_distinct("g") / F.nullif(F.count("g"), F.lit(0)), 6).alias("distinct_2"))
    return uni.crossJoin(two)


def nearest_distance(texts: DataFrame, key: str = "doc_id", text: str = "text", dim: int = 64) -> DataFrame:
    """(mean_distance): how far the nearest other text lies from each, on average; little means little variety."""
    from .vindex import hashed_vector, topk_blocked

    v = texts.select(F.col(key).alias("doc_id"), F.lit("text").alias("source"), F.array(F.lit("")).alias("knobs"), hashed_vector(F.col(text), dim).alias("vec"))
    near = topk_blocked(v.select(F.col("doc_id").alias("qid"), "vec"), v, 2).filter("qid <> doc_id").groupBy("qid").agg(F.min("dist").alias("dist"))
    return near.agg(F.round(F.avg("dist"), 6).alias("mean_distance"))
