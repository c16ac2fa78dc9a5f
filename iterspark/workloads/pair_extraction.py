"""Pair extraction: sentences of two sources, word pairs labelled by a knowledge base; edits of prep only."""

from __future__ import annotations

from pyspark.sql import functions as F

from iterspark.operators import relational as R
from iterspark.plans.session import Workflow

EDITS = [("start", {}), ("prep", {"distance": True}), ("prep", {"shapes": True}), ("prep", {"ends": True}), ("prep", {"shapes": False}), ("prep", {"titles": True})]
START = {"distance": False, "shapes": False, "ends": False, "titles": False}
LEAST = 8
#: What an unknown pair counts for in fitting, where a known one counts 1: positives are rare.
UNKNOWN_WEIGHT = 1 / 64


def parameters(iteration: int) -> dict:
    out = dict(START)
    for _, change in EDITS[: iteration + 1]:
        out |= change
    return out


def known_pairs(bench, pages=None):
    own = bench.select(F.concat(F.lit("b"), "item_id").alias("id"), "text")
    if pages is not None:
        own = own.union(pages.select(F.concat(F.lit("p"), "page_id").alias("id"), F.regexp_extract("html", r"<title>([^<]*)", 1).alias("text")))
    return R.candidate_pairs(R.mentions(R.sentences(own, ["id"]), ["id"], LEAST), ["id"]).select("word_a", "word_b")


def labelled(pairs, known):
    """All pairs, labelled 1 where they are known."""
    return pairs.join(known.withColumn("y", F.lit(1.0)), ["word_a", "word_b"], "left").withColumn("label", F.coalesce("y", F.lit(0.0))).drop("y")


def pair_extraction(sf_dir: str, iteration: int = 0, **edits) -> Workflow:
    p = parameters(iteration) | edits
    wf = Workflow("pair_extraction")
    docs, talk, bench = (wf.source(n, f"{sf_dir}/{t}.parquet") for n, t in (("articles", "documents"), ("talk", "conversations"), ("bench", "benchmark")))
    both = wf.synthesize([docs, talk], lambda d, c: d.select(F.concat(F.lit("d"), "doc_id").alias("id"), "text").union(c.select(F.concat_ws("-", F.lit("c"), "conv_id", "turn").alias("id"), "text")), "texts")
    sents = wf.scan(both, lambda t: R.sentences(t, ["id"]), "sentences")
    found = wf.scan(sents, lambda s: R.mentions(s, ["id"], LEAST), "mentions")
    pairs = wf.synthesize([found], lambda m: R.candidate_pairs(m, ["id"]), "pairs")
    if p["titles"]:
        kb = wf.synthesize([bench, wf.source("pages", f"{sf_dir}/pages.parquet")], known_pairs, "known")
    else:
        kb = wf.synthesize([bench], lambda b: known_pairs(b), "known")
    rows = wf.synthesize([pairs, kb], labelled, "labelled")
    chosen = [wf.extractor("x_often", "ln(1 + n_sentences)")]
    if p["distance"]:
        chosen.append(wf.extractor("x_gap", "least(least_gap, 20)"))
    if p["shapes"]:
        chosen.append(wf.extractor("x_lengths", "length(word_a) + length(word_b)"))
    if p["ends"]:
        chosen.append(wf.extractor("x_ends", "cast(right(word_a, 2) = right(word_b, 2) as double)"))
    wf.features(rows, include=chosen)
    ex = wf.examples(rows, "examples", wf.extractor("label", "label"), keep=["word_a", "word_b"])

    def fit(e):
        from iterspark.functions.learners import logistic

        names = [c for c in e.columns if c.startswith("x_")]
        e = e.withColumn("_weight", F.when(F.col("label") == 1, 1.0).otherwise(UNKNOWN_WEIGHT))
        m = logistic(e, names, "label", 0.01, weight="_weight").stages[-1]
        return {"weights": [float(w) for w in m.coefficients.toArray()], "bias": float(m.intercept), "layout": names}

    def apply(e, m):
        z = sum((F.col(c).cast("double") * w for c, w in zip(m["layout"], m["weights"], strict=True)), F.lit(m["bias"]))
        return e.select("word_a", "word_b", "label", (z > 0).cast("double").alias("prediction"))

    _, pred = wf.learner("model", ex, fit, apply, predictions="extracted")
    wf.output(wf.reduce([pred], lambda t: [r.asDict() for r in t.groupBy("label", "prediction").count().orderBy("label", "prediction").collect()], "precision"))
    return wf
