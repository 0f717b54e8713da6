"""A training corpus from raw documents: language, exact copies, near copies, source mix, packed sequences.

Each stage takes ``(spark, docs, sf_dir)`` and works on all that the one before it kept.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from unioncount.llm import grace_dedup, langid, mixing, packing, simhash
from unioncount.llm.common import table, written

STAGES = [
    ("language_id", langid.stage_language),
    ("exact_dedup", grace_dedup.stage_exact),
    ("near_dedup", simhash.stage_near),
    ("mix_sources", mixing.stage_mix),
    ("pack_sequences", packing.stage_pack),
]

#: SQL cannot express the stages' search, rounding and packing; tests/llm compares them with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; every result but the last is written as Parquet and read again."""
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = written(docs, name)
    return docs
