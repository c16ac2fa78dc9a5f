"""Price class: one source, fine-grained supervised features on `lineitem`. The label is the net charge above a cut."""

from __future__ import annotations

from pyspark.sql import functions as F

from iterspark.functions import features as X
from iterspark.plans.session import Workflow

#: Edit of each iteration: (phase, parameters that differ from the iteration before).
EDITS = [
    ("start", {}),
    ("prep", {"month": True, "tax": False}),
    ("prep", {"bins": 20}),
    ("prep", {"cross": True}),
    ("post", {"report": "precision"}),
    ("learn", {"reg": 0.01}),
    ("post", {"report": "f1"}),
    ("post", {"report": "by_status"}),
    ("post", {"report": "confusion"}),
    ("post", {"report": "calibration"}),
    ("post", {"report": "by_month"}),
]
START = {"month": False, "tax": True, "bins": 10, "cross": False, "report": "accuracy", "reg": 0.1, "copies": 1}


def parameters(iteration: int) -> dict:
    out = dict(START)
    for _, change in EDITS[: iteration + 1]:
        out |= change
    return out


def net_charge():
    return F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))


def parse(df, copies: int = 1):
    """Typed rows with split and label."""
    if copies > 1:
        df = df.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.lit(copies))))
    return df.select(
        F.when(F.col("l_orderkey") % 10 < 8, "train").otherwise("test").alias("split"),
        *[F.col(f"l_{a}").alias(b) for a, b in (("extendedprice", "price"), ("quantity", "qty"), ("discount", "disc"), ("tax", "tax"), ("returnflag", "flag"), ("linestatus", "status"))],
        F.month("l_shipdate").alias("month"),
        (net_charge() > 50000).cast("double").alias("label"),
    )


_REPORTS = {
    "accuracy": lambda t: t.agg(F.avg((F.col("label") == F.col("prediction")).cast("double")).alias("value")),
    "precision": lambda t: t.agg(F.avg(F.when(F.col("prediction") == 1, (F.col("label") == 1).cast("double"))).alias("value"), F.avg(F.when(F.col("label") == 1, (F.col("prediction") == 1).cast("double"))).alias("recall")),
    "f1": lambda t: t.agg((2 * F.sum(F.col("label") * F.col("prediction")) / (F.sum("label") + F.sum("prediction"))).alias("value")),
    "by_status": lambda t: t.groupBy("status").agg(F.avg((F.col("label") == F.col("prediction")).cast("double")).alias("value")),
    "confusion": lambda t: t.groupBy("label", "prediction").count(),
    "calibration": lambda t: t.groupBy(F.floor(F.col("probability") * 10).alias("decile")).agg(F.avg("label").alias("value")),
    "by_month": lambda t: t.groupBy("month").agg(F.avg((F.col("label") != F.col("prediction")).cast("double")).alias("value")),
}


def price_class(path: str, iteration: int = 0, **edits) -> Workflow:
    p = parameters(iteration) | edits
    wf = Workflow("price_class")
    copies, bins, reg, report = p["copies"], p["bins"], p["reg"], p["report"]
    data = wf.source("data", path)
    rows = wf.scan(data, lambda df: parse(df, copies), "rows")
    span = wf.state(rows, "price", "range", "price_span")
    flags = wf.state(rows, "flag", "vocabulary", "flag_words")
    stats = wf.state(rows, "status", "vocabulary", "status_words")
    scales = {c: wf.state(rows, c, "deviation", f"{c}_scale") for c in ("price", "qty", "disc", "tax")}

    def scaled(c: str):
        return wf.extractor(f"x_{c}", lambda s: X.scale_sql(c, *s), [scales[c]])

    chosen = [scaled(c) for c in ("price", "qty", "disc")]
    if p["tax"]:
        chosen.append(scaled("tax"))
    chosen.append(wf.extractor("x_bucket", lambda s: X.bucket_sql("price", s[0], s[1], bins), [span]))
    chosen.append(wf.extractor("x_flag", lambda w: X.index_sql("flag", w), [flags]))
    chosen.append(wf.extractor("x_status", lambda w: X.index_sql("status", w), [stats]))
    if p["month"]:
        chosen.append(wf.extractor("x_month", "month"))
    if p["cross"]:
        chosen.append(wf.extractor("x_cross", lambda s, w: f"({X.bucket_sql('price', s[0], s[1], bins)}) * {max(len(w), 1)} + {X.index_sql('flag', w)}", [span, flags]))
    wf.extractor("x_unused", "length(flag)")  # declared, never chosen: sliced away
    wf.features(rows, include=chosen)
    label = wf.extractor("label", "label")
    examples = wf.examples(rows, "examples", label, keep=["split", "status", "month"])

    def fit(ex):
        from iterspark.functions.learners import logistic

        model = logistic(ex.filter("split = 'train'").na.fill(0.0), [c for c in ex.columns if c.startswith("x_")], "label", reg).stages[-1]
        return {"weights": [float(w) for w in model.coefficients.toArray()], "bias": float(model.intercept), "layout": [c for c in ex.columns if c.startswith("x_")]}

    def apply(ex, model):
        z = sum((F.coalesce(F.col(c).cast("double"), F.lit(0.0)) * w for c, w in zip(model["layout"], model["weights"], strict=True)), F.lit(model["bias"]))
        return ex.select("split", "status", "month", "label", (1 / (1 + F.exp(-z))).alias("probability")).withColumn("prediction", (F.col("probability") > 0.5).cast("double"))

    _, pred = wf.learner("model", examples, fit, apply)
    fn = _REPORTS[report]
    checked = wf.reduce([pred], lambda t: [r.asDict() for r in fn(t.filter("split = 'test'")).collect()], "checked")
    wf.uses(checked, label)
    wf.output(checked)
    return wf
