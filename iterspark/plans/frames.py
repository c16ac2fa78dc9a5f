"""Planner results as DataFrames, over graphs whose costs follow from the tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from iterspark.plans.dag import Dag
from iterspark.plans.reuse import ReusePlan

NODES = "node int, compute_cost long, load_cost long, size long, forced boolean, required boolean"


def nodes_frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, NODES)


def edges_frame(spark: SparkSession, edges: list[tuple[int, int]]) -> DataFrame:
    return spark.createDataFrame(edges, "src int, dst int")


def plan_frame(spark: SparkSession, plan: ReusePlan) -> DataFrame:
    return spark.createDataFrame([(int(n), s, int(plan.cost)) for n, s in plan.states.items()], "node int, state string, total_cost long")


def transitive_ancestors(edges: DataFrame, most_rounds: int = 64) -> DataFrame:
    """(node, ancestor) pairs by doubling: paths of length 1, 2, 4, ... until nothing is new."""
    pairs = edges.select(F.col("dst").alias("node"), F.col("src").alias("ancestor")).distinct()
    n = pairs.count()
    for _ in range(most_rounds):
        step = pairs.alias("a").join(pairs.alias("b"), F.col("a.ancestor") == F.col("b.node")).select("a.node", "b.ancestor")
        pairs = pairs.union(step).distinct()
        rows = pairs.collect()  # a graph of a few thousand nodes
        pairs = edges.sparkSession.createDataFrame(rows, pairs.schema)
        if len(rows) == n:
            break
        n = len(rows)
    return pairs


def cumulative_frame(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(node, cumulative): own compute cost plus that of all distinct ancestors."""
    own = nodes.select("node", "compute_cost")
    of_ancestors = transitive_ancestors(edges).join(own.withColumnRenamed("node", "ancestor"), "ancestor").groupBy("node").agg(F.sum("compute_cost").alias("c"))
    return own.join(of_ancestors, "node", "left").select("node", (F.col("compute_cost") + F.coalesce("c", F.lit(0))).alias("cumulative"))


def slice_frame(edges: DataFrame, outputs: list[int]) -> DataFrame:
    spark = edges.sparkSession
    reach = transitive_ancestors(edges).filter(F.col("node").isin(outputs)).select(F.col("ancestor").alias("node"))
    return reach.union(spark.createDataFrame([(o,) for o in outputs], "node int")).distinct()


def dag_of(edges: list[tuple[int, int]], n: int) -> Dag:
    return Dag.from_edges(range(1, n + 1), edges)
