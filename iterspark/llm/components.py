"""Connected components of an edge table, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from iterspark.llm.common import cut, discard, joined_by_key


def _counts(edges: DataFrame) -> tuple[int, int, int, int]:
    """Rows, the most rows that share an `a` and that share a `b`, and nodes that are both; counted with a map-side combine."""
    ends = F.array(F.struct(F.col("a").alias("node"), F.lit(1).alias("as_a")), F.struct(F.col("b").alias("node"), F.lit(0).alias("as_a")))
    by_node = edges.select(F.explode(ends).alias("e")).groupBy("e.node").agg(F.sum("e.as_a").alias("x"), F.sum(1 - F.col("e.as_a")).alias("y"))
    return tuple(by_node.agg(*[F.coalesce(c, F.lit(0)) for c in (F.sum("x"), F.max("x"), F.max("y"), F.count_if((F.col("x") > 0) & (F.col("y") > 0)))]).first())


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, label) for every node of `edges` (a, b); the label is the least node of its component.

    Each round hangs larger neighbours on the least one around a node, then the
    node and its smaller neighbours on the least of these. Rounds grow with the
    logarithm of the longest path. Minima are pre-aggregated, and a node with a large
    part of all edges is joined by broadcast. No edges give no rows.
    """
    pairs = edges.select("a", "b").filter("a <> b")
    now = cut(pairs.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    for _ in range(most_rounds):
        rows, most_a, most_b, inner = _counts(now)
        if most_a <= 1 and not inner:  # every node hangs on one that hangs on none
            break
        turned = F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b"))))
        both = now.select(turned.alias("e")).select("e.a", "e.b")
        least = both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m"), F.count("*").alias("n"))
        hung = joined_by_key(now.select(F.col("b").alias("a"), F.col("a").alias("b")), least, "a", "n", 2 * rows, most_b)
        large = hung.select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n"))
        small = joined_by_key(large, low, "a", "n", rows, most_a)
        former, now = now, cut(small.select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").union(low.select("a", F.col("m").alias("b"))).distinct())
        discard(former)
    else:
        raise RuntimeError("components did not settle")
    # settled, every node but the labels has just one row
    return now.select(F.col("a").alias("node"), F.col("b").alias("label")).union(now.select(F.col("b").alias("node"), F.col("b").alias("label")).distinct())
