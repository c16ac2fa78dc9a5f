"""A corpus pipeline of five of the `llm` operators.

Quality rules, toxicity, near-duplicates, mixing to target weights, packing. Each
stage reads what the one before it kept. `run` writes each stage's rows to the
folder that driver and executors share and reads them again for the next; what a stage
leaves beside its rows is removed, and so are its rows once the next has read them.

Defined results: a null, empty or short text fails the quality rules, so it reaches no
later stage; very long texts go through whole. A null or repeated doc_id is kept as any
other, and rows alike in id and text are one class of the third stage. Ties are settled
by each stage as its own text says. An empty table gives no pieces. Columns beyond those
of `documents`, whatever their names, are carried to the last stage and end there.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from iterspark.llm import mixing, near_dup, packing, quality_rules, toxicity
from iterspark.llm.common import fresh_path, remove, scratch

STAGES = [
    ("quality_rules", quality_rules.stage),
    ("toxicity", toxicity.stage),
    ("near_duplicates", near_dup.stage),
    ("mixing", mixing.stage),
    ("packing", packing.stage),
]

#: Models and signatures: SQL cannot express these stages.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    return run_on(spark, spark.read.parquet(f"{sf_dir}/documents.parquet"), sf_dir)


def run_on(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of the documents that the stages leave."""
    former = None
    for name, stage in STAGES:
        path = fresh_path(spark, f"stage-{name}")
        with scratch(spark):
            stage(spark, docs, sf_dir).write.parquet(path)
        if former is not None:
            remove(spark, former)
        docs, former = spark.read.parquet(path), path
    return docs


def queries() -> dict:
    return {"pipeline": run}
