"""Prompts of three parts: instruction, evidence, question."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

STYLES = {
    "plain": "You advise on database settings.",
    "cot": "You advise on database settings. Reason in small steps before you answer.",
    "decompose": "You advise on database settings. Split the problem into parts, solve each, then combine.",
}
ASK = {1: "Name the settings to change as a JSON list of strings.", 2: "Give a value for each of these settings as a JSON object: ", 0: "Answer with one JSON object from setting to value."}


def _lines(df: DataFrame, order: str, text: str, out: str) -> DataFrame:
    lines = F.transform(F.array_sort(F.collect_list(F.struct(order, text))), lambda s: F.concat(F.lit("- "), s[text]))
    return df.groupBy("qid").agg(F.concat_ws("\n", lines).alias(out))


def build(questions: DataFrame, hits: DataFrame | None = None, desc: DataFrame | None = None, phase: int = 1, style: str = "plain", budget: int | None = None, chosen: DataFrame | None = None) -> DataFrame:
    """prompts (qid, phase, text, n_tokens, prompt_hash). questions: qid, text; hits: qid, rank, text; desc: qid, rank, text.

    Absent sources vanish. budget cuts the evidence, never instruction or question, to so many characters."""
    out = questions.select("qid", F.col("text").alias("question"))
    evidence = F.lit("")
    for df, name, title in ((hits, "docs", "Retrieved:"), (desc, "metrics", "Telemetry:")):
        if df is not None:
            out = out.join(_lines(df, "rank", "text", name), "qid", "left")
            evidence = F.concat(evidence, F.when(F.col(name).isNotNull(), F.concat(F.lit(title + "\n"), F.col(name), F.lit("\n"))).otherwise(F.lit("")))
    if budget is not None:
        evidence = F.left(evidence, F.lit(budget))
    ask = F.lit(ASK[phase])
    if phase == 2:
        out = out.join(chosen.select("qid", F.concat_ws(", ", "knobs").alias("chosen")), "qid")
        ask = F.concat(ask, F.col("chosen"))
    text = F.concat(F.lit(STYLES[style] + "\n"), evidence, F.lit("Question: "), F.col("question"), F.lit("\n"), ask)
    tokens = F.size(F.filter(F.split(F.col("text"), r"\s+"), lambda w: w != ""))
    return out.select("qid", F.lit(phase).alias("phase"), text.alias("text")).withColumn("n_tokens", tokens).withColumn("prompt_hash", F.sha2("text", 256))


def build_all_knobs(questions: DataFrame, knobs: DataFrame, style: str = "plain") -> DataFrame:
    """The whole catalogue in the prompt; it is one string of some thousand characters."""
    names = knobs.agg(F.concat_ws(", ", F.array_sort(F.collect_set("knob"))).alias("names"))
    text = F.concat(F.lit(STYLES[style] + "\nChoose among: "), F.col("names"), F.lit("\nQuestion: "), F.col("text"), F.lit("\n" + ASK[1]))
    return questions.crossJoin(F.broadcast(names)).select("qid", F.lit(1).alias("phase"), text.alias("text")).withColumn("prompt_hash", F.sha2("text", 256))
