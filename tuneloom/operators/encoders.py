"""Frozen base encoders, one interface: encode(df) -> df with a vector column."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .vindex import hashed_vector


class HashedEncoder:
    """Token counts at places by md5: the offline stand-in for a sentence encoder."""

    def __init__(self, dim: int = 64):
        self.dim = dim

    def encode(self, df: DataFrame, text: str = "text", out: str = "vec") -> DataFrame:
        return df.withColumn(out, hashed_vector(F.col(text), self.dim))


class TableEncoder:
    """Vectors made elsewhere, joined by id; rows without one get null and are never retrieved."""

    def __init__(self, table: DataFrame, key: str, vec: str):
        self.table = table.select(F.col(key).alias("_key"), F.col(vec).cast("array<double>").alias("_vec"))

    def encode(self, df: DataFrame, key: str = "doc_id", out: str = "vec") -> DataFrame:
        return df.join(self.table, F.col(key) == F.col("_key"), "left").drop("_key").withColumnRenamed("_vec", out)


class CallableEncoder:
    """A user's function from texts to a matrix, called once for each Arrow batch on the executors; null texts stay null."""

    def __init__(self, fn: Callable[[list[str]], np.ndarray]):
        self.fn = fn

    def encode(self, df: DataFrame, text: str = "text", out: str = "vec") -> DataFrame:
        fn = self.fn

        def call(t: pd.Series) -> pd.Series:
            known = t.notna()
            rows = iter(np.asarray(fn(t[known].tolist()), float) if known.any() else [])
            return pd.Series([next(rows) if k else None for k in known], index=t.index, dtype=object)

        return df.withColumn(out, F.pandas_udf(call, "array<double>")(F.col(text)))
