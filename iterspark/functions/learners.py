"""Learners whose results SQL can reproduce, and thin uses of Spark's own."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def least_squares(df: DataFrame, x: str, y: str) -> list[float]:
    """(intercept, slope) from one aggregation."""
    r = df.agg(F.regr_intercept(y, x), F.regr_slope(y, x)).first()
    return [r[0], r[1]]


def centroids(df: DataFrame, vector: str, label: str, dims: int) -> DataFrame:
    """(label, centre): a mean for each place of the vector; map-side combined."""
    return df.groupBy(label).agg(F.array(*[F.avg(F.get(vector, F.lit(i)).cast("double")) for i in range(dims)]).alias("centre"))


def squared_distance(a: str, b: str):
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, v: s + v)


def nearest(df: DataFrame, vector: str, centres: DataFrame, label: str, most_centres: int = 10_000) -> DataFrame:
    """Adds `predicted`, the label of the nearest centre (the least label where several are). Centres are few and checked."""
    rows = centres.select(F.struct(F.col(label).alias("label"), "centre").alias("c")).limit(most_centres + 1).collect()
    if len(rows) > most_centres:
        raise ValueError(f"more than {most_centres} centres")
    one = df.sparkSession.createDataFrame([([r["c"] for r in rows],)], _centres_schema(centres, label))
    scored = df.join(F.broadcast(one))
    best = F.array_min(F.transform("_centres", lambda c: F.struct(F.aggregate(F.zip_with(F.col(vector).cast("array<double>"), c["centre"], lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, v: s + v).alias("d"), c["label"].alias("label"))))
    return scored.withColumn("predicted", best["label"]).drop("_centres")


def _centres_schema(centres: DataFrame, label: str):
    from pyspark.sql import types as T

    return T.StructType([T.StructField("_centres", T.ArrayType(T.StructType([T.StructField("label", centres.schema[label].dataType), T.StructField("centre", T.ArrayType(T.DoubleType()))])))])


def kmeans_fixed(df: DataFrame, key: str, vector: str, dims: int, k: int, rounds: int) -> DataFrame:
    """Lloyd's rounds from the first k keys as centres: (key, cluster) after `rounds` rounds."""
    first = df.orderBy(key).limit(k)
    rows = first.select(key, F.col(vector).cast("array<double>").alias("centre")).collect()
    centres = df.sparkSession.createDataFrame([(i, r["centre"]) for i, r in enumerate(rows)], "cluster int, centre array<double>")
    out = None
    for i in range(rounds):
        out = nearest(df, vector, centres, "cluster").withColumnRenamed("predicted", "cluster")
        if i < rounds - 1:
            centres = centroids(out, vector, "cluster", dims)
    return out.select(key, "cluster")


def logistic(df: DataFrame, columns: list[str], label: str, reg: float = 0.1, l1: float = 0.0, max_iter: int = 30, weight: str | None = None):
    """Spark's logistic regression over numeric columns, rows weighted by `weight`; returns the fitted pipeline."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    weighted = {"weightCol": weight} if weight else {}
    return Pipeline(stages=[VectorAssembler(inputCols=columns, outputCol="features"), LogisticRegression(labelCol=label, regParam=reg, elasticNetParam=l1, maxIter=max_iter, **weighted)]).fit(df)


def naive_bayes(tokens: DataFrame, token: str, label: str, smoothing: float = 1.0) -> DataFrame:
    """(token, log_odds) of a token in label 1 against label 0, from counts."""
    counts = tokens.groupBy(token).agg(F.sum(F.when(F.col(label) == 1, 1).otherwise(0)).alias("n1"), F.sum(F.when(F.col(label) == 0, 1).otherwise(0)).alias("n0"))
    whole = counts.agg(F.sum("n1").alias("t1"), F.sum("n0").alias("t0"), F.count("*").alias("v"))
    joined = counts.join(F.broadcast(whole))
    odds = F.log((F.col("n1") + smoothing) / (F.col("t1") + smoothing * F.col("v"))) - F.log((F.col("n0") + smoothing) / (F.col("t0") + smoothing * F.col("v")))
    return joined.select(token, "n0", "n1", odds.alias("log_odds"))


def grid_search(fit, score, grid: dict[str, list]) -> list[tuple[dict, float]]:
    """Every point of the grid with its score, best first."""
    from itertools import product

    points = [dict(zip(grid, v, strict=True)) for v in product(*grid.values())]
    return sorted(((p, score(fit(**p))) for p in points), key=lambda x: -x[1])


#: Bytes of input that one task of a learner takes.
TASK_BYTES = 128 << 20


def tasks_for(df: DataFrame, least: int = 1) -> int:
    """Tasks for a frame by Catalyst's estimate of its size, so that they grow with the input and not with the machine."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return max(least, min(-(-size // TASK_BYTES), 100_000))


def dealt(df: DataFrame, column: str, least: int = 8) -> DataFrame:
    """A deal of the rows that follows from their values, so that a reloaded input gives the same result."""
    return df.repartition(tasks_for(df, least), F.xxhash64(column)).sortWithinPartitions(column)


def word_vectors(docs: DataFrame, tokens: str, size: int = 32, window: int = 5, min_count: int = 5, iters: int = 1, seed: int = 7) -> DataFrame:
    """(word, vector) by a skip-gram with a hierarchical softmax. The vocabulary, without vectors, sits on the driver: raise `min_count` with the corpus.

    Each of its parts trains by itself and their vectors are averaged, so there are as few as the input's size allows.
    """
    from iterspark.functions import skip_gram

    return skip_gram.fit(docs, tokens, size, window, min_count, iters, seed, tasks_for(docs))


def kmeans(df: DataFrame, vector: str, k: int, seed: int = 7, max_iter: int = 20) -> DataFrame:
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    vec = dealt(df, vector).withColumn("_v", array_to_vector(F.col(vector).cast("array<double>")))
    return KMeans(k=k, seed=seed, maxIter=max_iter, featuresCol="_v", predictionCol="cluster").fit(vec).transform(vec).drop("_v")
