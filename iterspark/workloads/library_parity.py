"""Library parity: model selection over `documents` with the quality labels, every grid point a branch of its own.

A grid point is a model, its predictions and a score; one more point reuses the
others. The last reducer picks the best point by its score on the validation part
and reports its score on the test part.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from iterspark.functions import features as X
from iterspark.plans.session import Workflow

#: Edit of each iteration: (phase, parameters that differ from the iteration before).
EDITS = [
    ("start", {}),
    ("learn", {"regs": (0.1, 0.01, 0.001)}),
    ("post", {"metric": "f1"}),
    ("prep", {"letters": True}),
    ("learn", {"l1": 0.5}),
    ("post", {"metric": "accuracy"}),
]
START = {"regs": (0.1, 0.01), "l1": 0.0, "letters": False, "metric": "f1_and_accuracy"}
WORD = r"[^\x20\x09-\x0D]+"


def parameters(iteration: int) -> dict:
    out = dict(START)
    for _, change in EDITS[: iteration + 1]:
        out |= change
    return out


def described(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """split, distinct (share of distinct words; null without words), letters (share of letters), words, label."""
    own = labels.filter("quality is not null").groupBy("doc_id").agg(F.max("quality").cast("double").alias("label"))
    part = F.pmod("doc_id", F.lit(5))
    found = F.regexp_extract_all("text", F.lit(WORD), F.lit(0))
    slim = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).select("doc_id", found.alias("w"), F.length("text").alias("n"), F.length(F.regexp_replace("text", r"[^\p{L}]", "")).alias("l"))
    rows = slim.select("doc_id", F.size("w").alias("words"), F.when(F.size("w") > 0, F.size(F.array_distinct("w")) / F.size("w")).alias("distinct"), F.when(F.col("n") > 0, F.col("l") / F.col("n")).alias("letters"))
    split = F.when(part == 0, "test").when(part == 1, "validation").otherwise("train")
    return rows.join(own, "doc_id").select(split.alias("split"), "words", "distinct", "letters", "label")


def cut_scores(rows: DataFrame, cuts: list[float]) -> DataFrame:
    """(cut, n, hits): a rule for each cut, label 1 from that share of distinct words on; all cuts in one pass."""
    right = [F.sum(((F.coalesce("distinct", F.lit(0.0)) >= c) == (F.col("label") == 1)).cast("long")) for c in cuts]
    whole = rows.agg(F.count("*").alias("n"), F.array(*[F.struct(F.lit(c).alias("cut"), F.coalesce(r, F.lit(0)).alias("hits")) for c, r in zip(cuts, right, strict=True)]).alias("s"))
    return whole.select("n", F.explode("s").alias("s")).select("s.cut", "n", "s.hits")


def _scores(pred: DataFrame) -> dict:
    hit = (F.col("label") == F.col("prediction")).cast("double")
    both = F.sum(F.col("label") * F.col("prediction"))
    rows = pred.filter("split <> 'train'").groupBy("split").agg(F.avg(hit).alias("accuracy"), (2 * both / F.nullif(F.sum("label") + F.sum("prediction"), F.lit(0.0))).alias("f1"))
    return {r["split"]: {"accuracy": r["accuracy"], "f1": r["f1"]} for r in rows.collect()}


def library_parity(sf_dir: str, iteration: int = 0, **edits) -> Workflow:
    p = parameters(iteration) | edits
    wf = Workflow("library_parity")
    l1, metric, regs = p["l1"], p["metric"], list(p["regs"])
    docs, labels = wf.source("documents", f"{sf_dir}/documents.parquet"), wf.source("labels", f"{sf_dir}/labels.parquet")
    rows = wf.synthesize([docs, labels], described, "rows")
    columns = ["distinct", *(["letters"] if p["letters"] else [])]
    chosen = [wf.extractor("x_words", "log1p(words)")]
    for c in columns:
        mean, spread = wf.state(rows, c, "mean", f"{c}_mean"), wf.state(rows, c, "deviation", f"{c}_spread")
        chosen.append(wf.extractor(f"x_{c}", lambda m, s, c=c: X.scale_sql(f"({X.impute_sql(c, m[0])})", *s), [mean, spread]))
    wf.features(rows, include=chosen)
    examples = wf.examples(rows, "examples", wf.extractor("label", "label"), keep=["split"])

    def fitted(reg: float):
        def fit(ex):
            from iterspark.functions.learners import logistic

            layout = [c for c in ex.columns if c.startswith("x_")]
            model = logistic(ex.filter("split = 'train'").na.fill(0.0), layout, "label", reg, l1).stages[-1]
            return {"weights": [float(w) for w in model.coefficients.toArray()], "bias": float(model.intercept), "layout": layout}

        return fit

    def apply(ex, model):
        z = sum((F.coalesce(F.col(c), F.lit(0.0)) * w for c, w in zip(model["layout"], model["weights"], strict=True)), F.lit(model["bias"]))
        return ex.select("split", "label", (z > 0).cast("double").alias("prediction"))

    scores = []
    for reg in regs:
        _, pred = wf.learner(f"model_{reg}", examples, fitted(reg), apply, predictions=f"predictions_{reg}")
        scores.append(wf.reduce([pred], _scores, f"score_{reg}"))
    by = "accuracy" if metric == "accuracy" else "f1"

    def best(*found):
        ranked = sorted(zip(regs, found, strict=True), key=lambda x: (-(x[1].get("validation", {}).get(by) or 0.0), x[0]))
        reg, score = ranked[0]
        return {"reg": reg, "by": by, "test": score.get("test", {}) if metric == "f1_and_accuracy" else score.get("test", {}).get(by)}

    wf.output(wf.reduce(scores, best, "best"))
    return wf
