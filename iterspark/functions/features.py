"""Learned parts of features: in one pass over the rows (fused), or a job for each."""

from __future__ import annotations

from dataclasses import dataclass
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


#: A vocabulary becomes part of an expression; larger ones are an error, never cut.
MOST_WORDS = 100_000


@dataclass(frozen=True)
class FeatureState:
    """stat: range, mean, deviation, quantiles (n parts) or vocabulary."""

    column: str
    stat: str
    n: int = 4
    accuracy: int = 10_000
    train_only: bool = False


def _aggregate(s: FeatureState) -> Column:
    c = F.col(s.column)
    if s.train_only:
        c = F.when(F.col("split") == "train", c)
    if s.stat == "range":
        return F.array(F.min(c).cast("double"), F.max(c).cast("double"))
    if s.stat == "mean":
        return F.array(F.avg(c))
    if s.stat == "deviation":
        return F.array(F.avg(c), F.stddev_samp(c))
    return F.percentile_approx(c, [i / s.n for i in range(1, s.n)], s.accuracy).cast("array<double>")


def fit_features(df: DataFrame, specs: dict[str, FeatureState], fused: bool = True) -> dict[str, Any]:
    """Numbers as lists, vocabularies as sorted lists. Fused: one aggregation, and one count for all vocabularies."""
    numeric = {n: s for n, s in specs.items() if s.stat != "vocabulary"}
    vocab = {n: s for n, s in specs.items() if s.stat == "vocabulary"}
    out: dict[str, Any] = {}
    groups = [numeric] if fused else [{n: s} for n, s in numeric.items()]
    for g in groups:
        if g:
            row = df.agg(*[_aggregate(s).alias(n) for n, s in g.items()]).first()
            out |= {n: list(row[n]) if row[n] is not None else [] for n in g}
    groups = [vocab] if fused else [{n: s} for n, s in vocab.items()]
    for g in groups:
        if g:
            pairs = F.explode(F.array(*[F.struct(F.lit(n).alias("feature"), F.col(s.column).cast("string").alias("value")) for n, s in g.items()]))
            words = df.select(pairs.alias("p")).select("p.*").filter("value is not null").distinct()
            rows = words.limit(MOST_WORDS + 1).collect()
            if len(rows) > MOST_WORDS:
                raise ValueError(f"over {MOST_WORDS} values in the vocabularies of {sorted(g)}: hash the column, or join a table of indices")
            for n in g:
                out[n] = sorted(r["value"] for r in rows if r["feature"] == n)
    return out


# expressions for extractors, from learned states


def bucket_sql(column: str, low: float, high: float, n: int) -> str:
    """Number 0..n-1 of the equal-width bucket; the highest value is in the last."""
    width = (high - low) / n
    return f"cast(least({n - 1}, floor(({column} - {low!r}D) / {width!r}D)) as int)" if width else "0"


def scale_sql(column: str, mean: float, deviation: float) -> str:
    return f"(({column} - {mean!r}D) / {deviation or 1.0!r}D)"


def min_max_sql(column: str, low: float, high: float) -> str:
    """0 to 1 over the learned range; 0 where the range is a point."""
    return f"(({column} - {low!r}D) / {high - low!r}D)" if high > low else "0D"


def impute_sql(column: str, mean: float) -> str:
    return f"coalesce({column}, {mean!r}D)"


def index_sql(column: str, vocabulary: list[str]) -> str:
    words = ", ".join("'" + v.replace("\\", "\\\\").replace("'", "\\'") + "'" for v in vocabulary)
    return f"(array_position(array({words}), {column}) - 1)"


def interact_sql(*columns: str, sep: str = "|") -> str:
    return f"concat_ws('{sep}', {', '.join(columns)})"


def interact(*columns: str, sep: str = "|") -> Column:
    return F.concat_ws(sep, *columns)


def bucketize(df: DataFrame, column: str, n: int, name: str) -> DataFrame:
    low, high = fit_features(df, {"r": FeatureState(column, "range")})["r"]
    return df.withColumn(name, F.expr(bucket_sql(column, low, high, n)))


def long_form(df: DataFrame, key: list[str], columns: list[str]) -> DataFrame:
    """(key, feature, value): an example's portable form, a row for each feature."""
    return df.select(*key, F.explode(F.array(*[F.struct(F.lit(c).alias("feature"), F.col(c).cast("double").alias("value")) for c in columns])).alias("f")).select(*key, "f.feature", "f.value")


def assemble(df: DataFrame, columns: list[str], name: str = "features", kind: str = "auto") -> DataFrame:
    """A vector column with slot names; sparse or dense as asked, by default whichever is smaller."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.functions import array_to_vector, vector_to_array

    out = VectorAssembler(inputCols=columns, outputCol=name).transform(df)
    return out.withColumn(name, array_to_vector(vector_to_array(name))) if kind == "dense" else out


def lineage(layout: list[str], weights: list[float]) -> list[tuple[int, str, float]]:
    """(slot, extractor, weight)."""
    return [(i, n, w) for i, (n, w) in enumerate(zip(layout, weights, strict=True))]


def prune_by_weight(rows: list[tuple[int, str, float]], eps: float = 0.0) -> list[str]:
    """Extractors none of whose slots weighs more than `eps`; for inference with this fitted model only."""
    most: dict[str, float] = {}
    for _, name, w in rows:
        most[name] = max(most.get(name, 0.0), abs(w))
    return sorted(n for n, w in most.items() if w <= eps)


def prune_model(model: dict, eps: float = 0.0) -> dict:
    """A linear model (layout, weights, bias) without the extractors of which no slot weighs more than `eps`."""
    gone = set(prune_by_weight(lineage(model["layout"], model["weights"]), eps))
    left = [(n, w) for n, w in zip(model["layout"], model["weights"], strict=True) if n not in gone]
    return model | {"layout": [n for n, _ in left], "weights": [w for _, w in left]}


def compared_scores(a: DataFrame, b: DataFrame, key: str, score: str) -> DataFrame:
    """(n, same): rows of `a`, and those that `b` has with an equal key and score, repeats and nulls counted. 1 - same / n is what pruning changes."""
    side = lambda df, in_a: df.select(key, score, F.lit(in_a).alias("_a"), F.lit(1 - in_a).alias("_b"))
    counts = side(a, 1).unionByName(side(b, 0)).groupBy(key, score).agg(F.sum("_a").alias("_a"), F.sum("_b").alias("_b"))
    zero = F.lit(0).cast("long")
    return counts.agg(F.coalesce(F.sum("_a"), zero).alias("n"), F.coalesce(F.sum(F.least("_a", "_b")), zero).alias("same"))


def flat_image(column: str) -> Column:
    """An image, an array of rows, as one array in order of rows; null where the image or a row is null."""
    return F.flatten(column)


def random_cosine(df: DataFrame, column: str, dims: int, seed: int | None, name: str = "projected") -> DataFrame:
    """cos(w . x + b) for `dims` random (w, b); without a seed the result differs each time."""
    width = len(df.select(column).first()[0])
    rng = np.random.default_rng(seed)
    w, b = rng.normal(size=(width, dims)), rng.uniform(0, 2 * np.pi, dims)

    @F.pandas_udf("array<float>")
    def project(v: pd.Series) -> pd.Series:
        return pd.Series(list(np.cos(np.stack(v.to_numpy()) @ w + b).astype(np.float32)))

    return df.withColumn(name, project(column))


def tf_idf(tokens: DataFrame, key: str, token: str) -> DataFrame:
    """(key, token, n, weight): count times ln((documents + 1) / (documents with the token + 1))."""
    counts = tokens.groupBy(key, token).agg(F.count("*").alias("n"))
    documents = F.broadcast(tokens.agg(F.count_distinct(key).alias("_documents")))  # one row
    frequency = counts.groupBy(token).agg(F.count("*").alias("_df"))
    weight = F.col("n") * F.log((F.col("_documents") + 1) / (F.col("_df") + 1))
    return counts.join(frequency, token).join(documents).select(key, token, "n", weight.alias("weight"))


def principal_shares(df: DataFrame, column: str, k: int) -> list[float]:
    """Shares of the variance that the first `k` principal components of an array column explain."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector

    vectors = df.select(array_to_vector(F.col(column).cast("array<double>")).alias("v"))
    return [float(x) for x in PCA(k=k, inputCol="v", outputCol="p").fit(vectors).explainedVariance]
