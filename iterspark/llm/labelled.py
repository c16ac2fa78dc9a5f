"""Labelled training rows for the classifiers.

A classifier is fitted on a bounded sample: of the labelled documents that are
not held out, those with the smallest hash of their id, `most` at the most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from iterspark.llm.common import fold

#: Rows that a classifier is fitted on, at the most.
MOST_LABELLED = 20_000


def training_rows(docs: DataFrame, labels: DataFrame, label: str, most: int = MOST_LABELLED) -> DataFrame:
    """(text, y double, part int 1 to 4) of the sample. A document labelled twice takes its larger label."""
    own = labels.filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max(label).cast("double").alias("y"))
    own = own.withColumn("part", fold(F.col("doc_id"))).filter("part <> 0")
    sample = own.join(docs.select("doc_id").distinct(), "doc_id", "left_semi").orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    return docs.select("doc_id", "text").join(F.broadcast(sample), "doc_id").select("text", "y", "part")
