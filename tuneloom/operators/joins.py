"""Joins on time that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def interval_join(left: DataFrame, right: DataFrame, keys: list[str], lt: str, rt: str, seconds: int) -> DataFrame:
    """Rows of equal keys whose times differ by at most `seconds`: an equi-join on time cells, each left row in three of them."""
    width = seconds * 1_000_000
    cell = lambda c: F.floor(F.unix_micros(c) / width)
    a = left.withColumn("_cell", F.explode(F.array(*(cell(F.col(lt)) + d for d in (-1, 0, 1)))))
    b = right.withColumn("_cell", cell(F.col(rt)))
    return a.join(b, [*keys, "_cell"]).filter(F.abs(F.unix_micros(F.col(lt)) - F.unix_micros(F.col(rt))) <= width).drop("_cell")


def as_of(left: DataFrame, right: DataFrame, keys: list[str], time: str) -> DataFrame:
    """Each left row with the last right row of its keys at or before its time; nulls where there is none.

    Both sides go through one window by keys and time, so nothing multiplies."""
    carried = [c for c in right.columns if c not in (*keys, time)]
    own = [c for c in left.columns if c not in (*keys, time)]
    a = left.select(*keys, time, F.struct(*own).alias("_l"), F.lit(None).alias("_r"), F.lit(1).alias("_side"))
    b = right.select(*keys, time, F.lit(None).alias("_l"), F.struct(*carried).alias("_r"), F.lit(0).alias("_side"))
    w = Window.partitionBy(*keys).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("_r", F.last("_r", ignorenulls=True).over(w)).filter("_side = 1")
    return both.select(*keys, time, "_l.*", *(F.col(f"_r.{c}").alias(c) for c in carried))
