"""The stages of corpus preparation; corpus_pipeline.py at the repository's top runs them.

Each stage takes documents with any columns besides doc_id and text and, but for packing, returns the same columns. Null and
empty texts fail the quality rules, so later stages see them only where they are called alone: there they are near duplicates
of each other, hold no benchmark item and no secret, and pack as one token. Rows with a null id are duplicates of nothing.
Repeated rows have equal ids: they stay or go together. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import decontamination, packing, quality_rules, secret_scan, similar_pairs
from .common import stored, table


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    """Where a public vocabulary lies on this machine; every node has it installed."""
    import public_tokenizers

    return public_tokenizers.path(name)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the repetition rules reject go."""
    return quality_rules.keep_good(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five-word similarity 0.8 or more) stays, that of smallest id."""
    groups = similar_pairs.similar_groups(docs, width=5, threshold=0.8)
    gone = groups.filter("component_id <> doc_id").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item within the edit budget go."""
    return decontamination.without_leaks(docs, table(spark, sf_dir, "benchmark"))


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents stay; the secrets in their texts are blanked out."""
    return secret_scan.redacted(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents in sequences."""
    return packing.pack(docs, tokenizer_path())


STAGES = [("quality_rules", quality), ("simhash_dedup", near_duplicates), ("decontamination", benchmark_leaks), ("secret_scan", secrets), ("packing", pack)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
