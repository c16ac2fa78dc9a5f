"""Entity clusters: articles and a knowledge base, two unsupervised learners, then a report."""

from __future__ import annotations

from pyspark.sql import functions as F

from iterspark.functions import learners as L
from iterspark.operators import relational as R
from iterspark.plans.session import Workflow

EDITS = [
    ("start", {}),
    ("prep", {"lang": "en"}),
    ("learn", {"k": 20}),
    ("post", {"report": "members"}),
    ("learn", {"k": 15}),
    ("prep", {"parts": True}),
    ("learn", {"embedding": "cooccurrence"}),
    ("post", {"report": "sizes"}),
    ("prep", {"least": 2}),
    ("learn", {"dims": 48}),
    ("post", {"report": "members"}),
]
START = {"lang": None, "k": 10, "report": "sizes", "parts": False, "embedding": "skip_gram", "least": 1, "dims": 32}


def parameters(iteration: int) -> dict:
    out = dict(START)
    for _, change in EDITS[: iteration + 1]:
        out |= change
    return out


def knowledge_base(bench, part=None):
    """Distinct lower-cased words of five letters or more."""
    words = R.tokens(bench, ["item_id"]).select("token")
    if part is not None:
        words = words.union(R.tokens(part, ["p_partkey"], "p_name").select("token"))
    return words.filter(F.length("token") >= 5).distinct()


def cooccurrence_vectors(toks, dims: int, window: int = 2):
    """(word, vector): counts of neighbours, neighbours hashed to `dims` places; exact and distributed."""
    pairs = R.cooccurrence(toks, "doc_id", window)
    place = F.pmod(F.xxhash64("other"), F.lit(dims)).cast("int")
    cells = pairs.groupBy("token", place.alias("d")).agg(F.sum("n").cast("double").alias("v"))
    entries = F.map_from_entries(F.collect_list(F.struct("d", "v")))
    return cells.groupBy(F.col("token").alias("word")).agg(entries.alias("m")).select("word", F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0.0))).alias("vector"))


def entity_clusters(sf_dir: str, iteration: int = 0, **edits) -> Workflow:
    p = parameters(iteration) | edits
    lang, k, report, least, dims, embedding = p["lang"], p["k"], p["report"], p["least"], p["dims"], p["embedding"]
    wf = Workflow("entity_clusters")
    docs, bench = wf.source("articles", f"{sf_dir}/documents.parquet"), wf.source("bench", f"{sf_dir}/benchmark.parquet")
    chosen = wf.scan(docs, lambda d: d.select("doc_id", "lang", "text") if lang is None else d.filter(F.col("lang") == lang).select("doc_id", "lang", "text"), "chosen")
    toks = wf.scan(chosen, lambda d: R.token_lists(d, ["doc_id"], least), "tokens")
    if p["parts"]:
        kb = wf.synthesize([bench, wf.source("part", f"{sf_dir}/part.parquet")], knowledge_base, "entities")
    else:
        kb = wf.synthesize([bench], lambda b: knowledge_base(b), "entities")
    if embedding == "skip_gram":
        fit = lambda t: L.word_vectors(t, "ws", size=dims)
    else:
        fit = lambda t: cooccurrence_vectors(t.select("doc_id", F.posexplode("ws").alias("pos", "token")), dims)
    vectors = wf.define("vectors", "model", "learn", [toks], fit)
    own = wf.define("entity_vectors", "synthesizer", "learn", [vectors, kb], lambda v, e: v.join(e, v["word"] == e["token"], "left_semi"))
    clusters = wf.define("clusters", "predictions", "learn", [own], lambda v: L.kmeans(v, "vector", k).select("word", "cluster"))
    if report == "sizes":
        fn = lambda c: [r.asDict() for r in c.groupBy("cluster").count().orderBy("cluster").collect()]
    else:
        fn = lambda c: [r.asDict() for r in c.groupBy("cluster").agg(F.slice(F.sort_array(F.collect_set("word")), 1, 5).alias("top")).orderBy("cluster").collect()]
    wf.output(wf.reduce([clusters], fn, "report"))
    return wf
