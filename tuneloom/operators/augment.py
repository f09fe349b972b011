"""Synthetic questions: backward logic chains, step-by-step, and direct, through a pluggable generator."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

CHAIN = "knob string, func string, issue string, behaviour string"
QUESTION = "doc_id long, dbms string, text string, knobs array<string>, method string"


class TemplateGenerator:
    """Deterministic stand-in for a language model: each sub-task is a table lookup or a sentence frame."""

    def __init__(self, functions: dict[str, list[str]], issues: dict[str, list[str]], behaviours: dict[str, list[str]]):
        self.tables = {"func": functions, "issue": issues, "behaviour": behaviours}

    def edge(self, task: str, pdf: pd.DataFrame, given: str, fanout: int) -> pd.DataFrame:
        """One row for each continuation of a chain."""
        rows = [{**r, task: v} for r in pdf.to_dict("records") for v in (self.tables[task].get(r[given]) or [f"{r[given]} misbehaves"])[:fanout]]
        return pd.DataFrame(rows, columns=[*pdf.columns, task])

    def fuse(self, pdf: pd.DataFrame) -> pd.Series:
        return "While " + pdf["func"] + " is at work I see that " + pdf["behaviour"] + "; it looks like " + pdf["issue"] + ". Which settings should I look at?"

    def stepwise(self, pdf: pd.DataFrame) -> pd.Series:
        return "Step by step: the setting described as '" + pdf["description"] + "' may be wrong, case " + pdf["n"].astype(str) + ". What should I change?"

    def direct(self, pdf: pd.DataFrame) -> pd.Series:
        return "How do I use the setting described as '" + pdf["description"] + "', variant " + pdf["n"].astype(str) + "?"


class CallableGenerator(TemplateGenerator):
    """A user's function from instructions to texts, asked once for each row of a batch; the tables only say which chains exist."""

    ASK = {
        "fuse": "Write a user's question. Setting at work: {func}. Seen: {behaviour}. Cause: {issue}.",
        "stepwise": "Think step by step, then write a user's question about the setting described as: {description} (case {n}).",
        "direct": "Write a user's question about the setting described as: {description} (variant {n}).",
    }

    def __init__(self, fn: Callable[[list[str]], list[str]], functions, issues, behaviours):
        super().__init__(functions, issues, behaviours)
        self.fn = fn

    def _ask(self, task: str, pdf: pd.DataFrame) -> pd.Series:
        return pd.Series(self.fn([self.ASK[task].format(**r) for r in pdf.to_dict("records")]) if len(pdf) else [], index=pdf.index, dtype=object)

    def fuse(self, pdf: pd.DataFrame) -> pd.Series:
        return self._ask("fuse", pdf)

    def stepwise(self, pdf: pd.DataFrame) -> pd.Series:
        return self._ask("stepwise", pdf)

    def direct(self, pdf: pd.DataFrame) -> pd.Series:
        return self._ask("direct", pdf)


def none(questions: DataFrame) -> DataFrame:
    return questions


def _ask(df: DataFrame, call: Callable[[pd.DataFrame], pd.DataFrame], schema: str) -> DataFrame:
    def run(batches: Iterator[pd.DataFrame]):
        for pdf in batches:
            yield call(pdf)

    return df.mapInPandas(run, schema)


def logic_chain(knobs: DataFrame, gen, fanout=(2, 2, 1)) -> tuple[DataFrame, DataFrame]:
    """(chain, questions): knob -> function -> issue -> behaviour, one generator task for each edge, then one question a chain."""
    chain = knobs.select("dbms", "knob")
    schema = "dbms string, knob string"
    for task, given, n in (("func", "knob", fanout[0]), ("issue", "func", fanout[1]), ("behaviour", "issue", fanout[2])):
        schema += f", {task} string"
        chain = _ask(chain, lambda pdf, t=task, g=given, m=n: gen.edge(t, pdf, g, m), schema)
    questions = _ask(chain, lambda pdf: pdf.assign(text=gen.fuse(pdf)), schema + ", text string")
    return chain, _finish(questions, "chain")


def _finish(df: DataFrame, method: str) -> DataFrame:
    ident = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(method), "knob", "text")), 1, 15), 16, 10).cast("long")
    return df.select(ident.alias("doc_id"), "dbms", "text", F.array("knob").alias("knobs"), F.lit(method).alias("method"))


def _per_knob(knobs: DataFrame, volume: int) -> DataFrame:
    """volume rows dealt evenly over the knobs, in the order of their md5."""
    total = knobs.count()
    each = knobs.select("dbms", "knob", "description", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(max(0, -(-volume // max(1, total)) - 1)).cast("long"))).alias("n"))
    return each.orderBy("n", F.md5("knob"), "knob").limit(volume).select("dbms", "knob", "description", "n")


def cot(knobs: DataFrame, gen, volume: int) -> DataFrame:
    return _finish(_ask(_per_knob(knobs, volume), lambda pdf: pdf.assign(text=gen.stepwise(pdf)), "dbms string, knob string, description string, n long, text string"), "cot")


def direct(knobs: DataFrame, gen, volume: int) -> DataFrame:
    return _finish(_ask(_per_knob(knobs, volume), lambda pdf: pdf.assign(text=gen.direct(pdf)), "dbms string, knob string, description string, n long, text string"), "direct")
