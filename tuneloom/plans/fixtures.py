"""Small literal tables: knobs in our own words, chains, answers, prices, expert results. Values are invented."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

KNOBS = [
    ("max_connections", "numeric", 1.0, 100000.0, None, "limits how many clients may connect"),
    ("innodb_buffer_pool_size", "numeric", 5242880.0, 1e15, None, "memory that keeps table and index pages"),
    ("sort_buffer_size", "numeric", 32768.0, 4294967295.0, None, "memory for one sort"),
    ("bulk_insert_buffer_size", "numeric", 0.0, 1e15, None, "memory for many rows inserted at once"),
    ("innodb_flush_log_at_trx_commit", "categorical", None, None, ["0", "1", "2"], "when the log goes to disk"),
    ("binlog_format", "categorical", None, None, ["row", "statement", "mixed"], "how changes are logged"),
    ("transaction_isolation", "categorical", None, None, ["read-committed", "repeatable-read", "serializable"], "what a transaction sees of others"),
    ("innodb_flush_method", "categorical", None, None, ["fsync", "o_direct", "o_dsync"], "how files are flushed"),
    ("autocommit", "boolean", None, None, ["0", "1", "on", "off", "true", "false"], "whether each statement commits alone"),
    ("unique_checks", "boolean", None, None, ["0", "1", "on", "off", "true", "false"], "whether uniqueness is tested at once"),
    ("foreign_key_checks", "boolean", None, None, ["0", "1", "on", "off", "true", "false"], "whether references are tested at once"),
    ("slow_query_log", "boolean", None, None, ["0", "1", "on", "off", "true", "false"], "whether slow statements are noted"),
]
FUNCTIONS = {"bulk_insert_buffer_size": ["bulk loading", "index building"], "autocommit": ["committing", "bulk loading"], "max_connections": ["client admission", "session memory"]}
ISSUES = {"bulk loading": ["too little memory per batch", "a commit for every row"], "index building": ["index pages written twice", "random page writes"], "committing": ["a log write for every row", "locks kept too long"], "client admission": ["too few slots", "slots never freed"], "session memory": ["too many sessions", "large session buffers"]}
BEHAVIOURS = {}
ANSWERS = [
    (1, '["autocommit", "unique_checks"]', "list"),
    (2, '{"autocommit": "0", "bulk_insert_buffer_size": 268435456}', "dict"),
    (3, "Try to lower autocommit.", "dict"),
    (4, '{"autocommit": "0"} hope this helps', "dict"),
    (5, '{"autocommit": ["0"]}', "dict"),
    (6, '{"warp_speed": "on"}', "dict"),
    (7, '{"max_connections": "0"}', "dict"),
    (8, "", "dict"),
    (9, '{"binlog_format": "ROW"}', "dict"),
]
PRICES = [("small", 0.5, 1.5), ("large", 10.0, 30.0)]
METRIC_WORDS = {"click": ("clicks of users", ["autocommit"]), "view": ("pages seen", ["max_connections", "slow_query_log"]), "purchase": ("orders placed", ["innodb_flush_log_at_trx_commit"]), "signup": ("accounts opened", ["max_connections"])}


def values(rows) -> str:
    """Rows as the body of a VALUES clause."""
    show = lambda v: "NULL" if v is None else repr(float(v)) if isinstance(v, float) else str(v) if isinstance(v, int) else "'" + str(v).replace("'", "''") + "'"
    return ", ".join("(" + ", ".join(map(show, r)) + ")" for r in rows)


def knobs(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(KNOBS, "knob string, kind string, lo double, hi double, choices array<string>, description string")


def answers(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(ANSWERS, "qid long, raw string, kind string")
