"""The corpus pipeline: quality rules, near copies, repeated passages, packing.

Each stage works on all that the one before kept, and all but the last return the
columns of their input.  Defined results: null and empty texts fail the quality rules;
rows with a null doc_id are judged, and stay beside near copies, as no smallest id is
known; repeated rows of a kept document stay together; very long texts are treated
whole; an empty table gives no rows; further columns pass through the first three stages.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hcube.llm.packing import op3_best_fit_packing
from hcube.llm.quality import keep_good
from hcube.llm.session import written
from hcube.llm.shingles import keep_one
from hcube.llm.suffix_dedup import without_repeats


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_good(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_one(docs)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = without_repeats(docs)
    return out.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else out


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return op3_best_fit_packing(docs)


STAGES = [
    ("quality_rules", quality_rules),
    ("near_copies", near_copies),
    ("repeated_passages", repeated_passages),
    ("packing", packing),
]

#: No SQL: hashing by XXH64, byte-pair ids and bin completion are out of its reach.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
