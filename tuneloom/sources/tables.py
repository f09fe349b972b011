"""Readers and writers. Columns and filters stay declarative, so that they reach the files."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, where=None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if where is not None:
        df = df.filter(where)
    return df if columns is None else df.select(*columns)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events with a zoned timestamp, as watermarks need one."""
    return read(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


READERS = {
    "parquet": lambda spark, path, schema=None: spark.read.parquet(path),
    "orc": lambda spark, path, schema=None: spark.read.orc(path),
    "csv": lambda spark, path, schema=None: spark.read.schema(schema).option("header", True).csv(path),
    "jsonl": lambda spark, path, schema=None: spark.read.schema(schema).json(path),
    "text": lambda spark, path, schema=None: spark.read.text(path),
}


_local_root: list[str] = []


def scratch(spark: SparkSession, label: str) -> str:
    """A new path in the folder that driver and executors share (spark.checkpoint.dir); on one machine without it, a private one."""
    shared = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not shared:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        if not _local_root:
            _local_root.append(tempfile.mkdtemp(prefix="tuneloom-"))
            atexit.register(shutil.rmtree, _local_root[0], True)
        shared = "file://" + _local_root[0]
    return f"{shared.rstrip('/')}/{label}-{uuid.uuid4().hex}"


def stored(df: DataFrame, label: str) -> DataFrame:
    """df written into the shared folder and read again: its lineage is cut, and what uses it several times computes it once."""
    path = scratch(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def load(spark: SparkSession, kind: str, path: str, schema: str | None = None) -> DataFrame:
    if kind in ("csv", "jsonl") and schema is None:
        raise ValueError("csv and jsonl need a schema; guessing one reads the data twice")
    return READERS[kind](spark, path, schema)


def save(df: DataFrame, kind: str, path: str, partition_by: tuple[str, ...] = ()) -> None:
    w = df.write.mode("overwrite").partitionBy(*partition_by)
    {"parquet": w.parquet, "orc": w.orc, "jsonl": w.json, "text": w.text, "csv": lambda p: w.option("header", True).csv(p)}[kind](path)
