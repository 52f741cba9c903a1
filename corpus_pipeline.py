"""The corpus pipeline: stages over `documents`, each written as Parquet and reread as the next one's input.

All stages but the last return the columns of `documents`; the last one packs what is left into sequences.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from hubsplit.llm import stages
from hubsplit.shared_dir import staged

STAGES = [
    ("quality rules", stages.quality_rules),
    ("SimHash near-dedup", stages.simhash_dedup),
    ("suffix-array dedup", stages.suffix_array_dedup),
    ("mixing to target weights", stages.mixing),
    ("best-fit packing", stages.packing),
]

#: The learned rules and the token ids of the last stage cannot be expressed in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), "stage-" + name.split()[0].lower())
    return STAGES[-1][1](spark, docs, sf_dir)
