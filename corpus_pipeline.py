"""The training-data pipeline: five stages over ``documents``, each written as Parquet and read again by the next.

Quality rules drop documents, near-dedup leaves one document of each group, decontamination drops documents that hold
a window of the benchmark, the secret scan masks secrets in the texts, packing cuts what is left into sequences.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from seqentropy.llm.common import scratch_path
from seqentropy.llm.decontamination import decontaminate
from seqentropy.llm.near_dedup import drop_near_copies
from seqentropy.llm.packing import pack
from seqentropy.llm.quality import keep_good
from seqentropy.llm.secrets import mask_secrets

STAGES = [
    ("quality_rules", keep_good),
    ("near_dedup", drop_near_copies),
    ("decontamination", decontaminate),
    ("secret_scan", mask_secrets),
    ("packing", pack),
]

#: No SQL: trained models, byte-pair ids and greedy packing; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages from ``documents`` on; returns the last one's rows."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        path = scratch_path(spark, name)
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
