"""The corpus pipeline: five stages over the documents, each written as Parquet and read again."""

from __future__ import annotations

from balcut.llm.decontaminate import decontamination_stage
from balcut.llm.pieces import pieces_stage
from balcut.llm.quality import quality_stage
from balcut.llm.secrets import secrets_stage
from balcut.llm.shared import settle, table
from balcut.llm.simhash import duplicates_stage
from pyspark.sql import DataFrame, SparkSession

STAGES = [
    ("quality rules", quality_stage),
    ("SimHash near-dedup", duplicates_stage),
    ("benchmark decontamination", decontamination_stage),
    ("secret scans", secrets_stage),
    ("SentencePiece encoding and decoding", pieces_stage),
]

#: Fingerprints, hashed ratios and segmentations have no SQL; the tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
