"""Corpus pipeline: five stages from raw documents to packed training sequences.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns
of documents. ``run`` writes each stage's result to the shared folder and reads it as the next one's
input, so a lost executor never costs more than a stage; what a stage left there besides is deleted then.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from hybridsort.llm import stages
from hybridsort.llm.common import delete_staged, staged, table
from hybridsort.ship import ship

STAGES = [
    ("quality_rules", stages.quality_rules),
    ("minhash_dedup", stages.minhash_dedup),
    ("substring_dedup", stages.substring_dedup),
    ("decontaminate", stages.decontaminate),
    ("pack", stages.pack),
]

#: Perplexity bands and packing have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = staged(stage(spark, docs, sf_dir), name)
        delete_staged(spark, keep=docs)
    return docs


def queries() -> dict:
    return {"pipeline": run}


def oracle_sql() -> dict:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
