"""Digit vectors: a costly projection that differs each time, a learner of many classes, cheap reports."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from iterspark.functions import learners as L
from iterspark.functions.features import random_cosine
from iterspark.plans.session import Workflow

EDITS = [("start", {}), ("learn", {"reg": 0.01}), ("post", {"report": "confusion"}), ("prep", {"dims": 512}), ("post", {"report": "accuracy"}), ("learn", {"reg": 0.1}), ("post", {"report": "confusion"}), ("prep", {"dims": 256}), ("learn", {"reg": 0.05}), ("post", {"report": "accuracy"}), ("post", {"report": "confusion"})]
START = {"reg": 0.1, "dims": 256, "report": "accuracy", "seed": None}


def parameters(iteration: int) -> dict:
    out = dict(START)
    for _, change in EDITS[: iteration + 1]:
        out |= change
    return out


def digit_vectors(sf_dir: str, iteration: int = 0, **edits) -> Workflow:
    p = parameters(iteration) | edits
    reg, dims, report, seed = p["reg"], p["dims"], p["report"], p["seed"]
    wf = Workflow("digit_vectors")
    images = wf.source("images", f"{sf_dir}/embeddings.parquet")
    projected = wf.define("projection", "scanner", "prep", [images], lambda d: random_cosine(d, "embedding", dims, seed).select("vec_id", "label", "projected"), deterministic=seed is not None)
    examples = wf.define("examples", "examples_plain", "prep", [projected], lambda d: d.select("vec_id", F.when(F.col("vec_id") % 5 < 4, "train").otherwise("test").alias("split"), F.col("label").cast("double").alias("label"), "projected"))

    def fit(e):
        from pyspark.ml.classification import LogisticRegression
        from pyspark.ml.functions import array_to_vector

        x = e.filter("split = 'train'").select("label", array_to_vector(F.col("projected").cast("array<double>")).alias("features"))
        m = LogisticRegression(regParam=reg, maxIter=10, family="multinomial").fit(x)
        return {"weights": m.coefficientMatrix.toArray().tolist(), "bias": m.interceptVector.toArray().tolist()}

    def apply(e, m):
        w, b = np.array(m["weights"]), np.array(m["bias"])

        @F.pandas_udf("double")
        def best(v: pd.Series) -> pd.Series:
            return pd.Series((np.stack(v.to_numpy()) @ w.T + b).argmax(1).astype(float))

        return e.select("vec_id", "split", "label", best("projected").alias("prediction"))

    _, pred = wf.learner("model", examples, fit, apply)
    if report == "accuracy":
        fn = lambda t: [r.asDict() for r in t.filter("split = 'test'").agg(F.avg((F.col("label") == F.col("prediction")).cast("double")).alias("accuracy")).collect()]
    else:
        fn = lambda t: [r.asDict() for r in t.filter("split = 'test'").groupBy("label", "prediction").count().orderBy("label", "prediction").collect()]
    wf.output(wf.reduce([pred], fn, "checked"))
    return wf


def centroid_accuracy(df):
    """Nearest centre of the training part, on the rest: an exact learner."""
    parts = df.withColumn("split", F.when(F.col("vec_id") % 5 < 4, "train").otherwise("test"))
    centres = L.centroids(parts.filter("split = 'train'"), "embedding", "label", 64)
    return L.nearest(parts, "embedding", centres, "label").groupBy("split").agg(F.avg((F.col("label") == F.col("predicted")).cast("double")).alias("accuracy"), F.count("*").alias("n"))
