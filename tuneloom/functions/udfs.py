"""Functions that Spark lacks, for DataFrames and SQL: vectorised, aggregating, and table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .vectors import register as register_vectors


def _row(**fields) -> T.StructType:
    """Types as objects: the module can be imported without a session."""
    return T.StructType([T.StructField(k, t) for k, t in fields.items()])


@F.pandas_udf(T.DoubleType())
def mad(v: pd.Series) -> float:
    """Median absolute deviation of a group, nulls aside."""
    v = v.dropna().to_numpy(float)
    return float(np.median(np.abs(v - np.median(v)))) if len(v) else None


@F.pandas_udf(T.DoubleType())
def trimmed_mean(v: pd.Series) -> float:
    """Mean without the lowest and highest tenth."""
    v = np.sort(v.dropna().to_numpy(float))
    k = len(v) // 10
    return float(v[k : len(v) - k].mean()) if len(v) else None


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def l2_normalise(v: pd.Series) -> pd.Series:
    return v.map(lambda x: None if x is None or not np.any(x) else (np.asarray(x, float) / np.linalg.norm(x)).tolist())


@F.udtf(returnType=_row(k=T.IntegerType(), place=T.IntegerType(), value=T.DoubleType(), score=T.DoubleType(), **{"lambda": T.DoubleType()}, is_anomaly=T.BooleanType()))
class EsdTable:
    """esd(values): one row for each test of a series."""

    def eval(self, values: list):
        from ..operators.esd import esd_steps

        x = [float(v) for v in values or [] if v is not None]
        for i, (p, score, lam, bad) in enumerate(esd_steps(x)):
            yield i + 1, p, x[p], float(score), float(lam), bool(bad)


@F.udtf(returnType=_row(place=T.IntegerType(), value=T.DoubleType(), seasonal=T.DoubleType(), trend=T.DoubleType(), resid=T.DoubleType()))
class StlTable:
    """stl_components(values, period)."""

    def eval(self, values: list, period: int):
        from ..operators.stl import stl

        for i, row in enumerate(zip(values, *stl(values, period))):
            yield (i, *map(float, row))


def register(spark: SparkSession) -> None:
    register_vectors(spark)
    spark.udtf.register("esd", EsdTable)
    spark.udtf.register("stl_components", StlTable)
    spark.udf.register("mad", mad)
