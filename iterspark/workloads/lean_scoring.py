"""A model whose useless weights learning makes zero, and scoring that leaves those features out."""

from __future__ import annotations

from pyspark.sql import functions as F

from iterspark.plans.session import Workflow
from iterspark.workloads.price_class import net_charge

FEATURES = {"x_price": "l_extendedprice / 1000", "x_qty": "l_quantity", "x_disc": "l_discount", "x_tax": "l_tax", "x_line": "l_linenumber", "x_month": "month(l_shipdate)"}
#: Strength of the penalty on absolute weights, which makes small ones zero.
PENALTY = 0.05


def _rows(wf: Workflow, path: str):
    return wf.scan(wf.source("data", path), lambda d: d.withColumn("key", F.struct("l_orderkey", "l_linenumber")).withColumn("label", (net_charge() > 50000).cast("double")), "rows")


def _fit(e):
    from iterspark.functions.learners import logistic

    names = [c for c in e.columns if c.startswith("x_")]
    m = logistic(e.na.drop(), names, "label", PENALTY, 1.0).stages[-1]
    return {"weights": [float(w) for w in m.coefficients.toArray()], "bias": float(m.intercept), "layout": names}


def _apply(e, m):
    z = sum((F.coalesce(F.col(c).cast("double"), F.lit(0.0)) * w for c, w in zip(m["layout"], m["weights"], strict=True)), F.lit(m["bias"]))
    return e.select("key", (1 / (1 + F.exp(-z))).alias("probability"))


def training(path: str) -> Workflow:
    wf = Workflow("lean_training")
    rows = _rows(wf, path)
    wf.features(rows, include=[wf.extractor(n, sql) for n, sql in FEATURES.items()])
    model, _ = wf.learner("model", wf.examples(rows, "examples", wf.extractor("label", "label"), keep=["key"]), _fit, _apply)
    wf.output(model)
    return wf


def scoring(path: str, model: dict, eps: float | None = 0.0) -> Workflow:
    """Scores of all rows; features that weigh `eps` or less are not run (None: all are)."""
    wf = Workflow("lean_scoring")
    rows = _rows(wf, path)
    for n, sql in FEATURES.items():
        wf.extractor(n, sql)
    wf.output(wf.score(rows, model, _apply, "scores", keep=["key"], eps=eps))
    return wf
