"""Corpus preparation: quality rules, near duplicates, benchmark leaks, secrets, packing.

STAGES are applied in order; each result is written as Parquet and read again as the next stage's documents. All stages but
the last return the columns of documents. What each does is in tuneloom/llm/stages.py.
"""

from tuneloom.llm.stages import STAGES, run

#: Edit distances, forests and tokenizers have no SQL form; tests/llm/test_pipeline.py holds every stage against a plain version.
ORACLE_SQL = None

__all__ = ["ORACLE_SQL", "STAGES", "run"]
