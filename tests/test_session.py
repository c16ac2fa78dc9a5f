import os
import time

import pytest
from pyspark.sql import functions as F

from iterspark.functions import features as X
from iterspark.operators import relational as R
from iterspark.plans.session import Policy, Session, Workflow
from iterspark.plans.store import MaterializationStore
from iterspark.workloads import lean_scoring
from iterspark.workloads.digit_vectors import digit_vectors
from iterspark.workloads.library_parity import library_parity
from iterspark.workloads.pair_extraction import known_pairs, pair_extraction
from iterspark.workloads.price_class import EDITS, price_class
from iterspark.workloads.simulator import WEIGHTS, simulate

D = "/root/testdata/sf0.001"


def rounded(x):
    return [{k: round(v, 4) if isinstance(v, float) else v for k, v in r.items()} for r in sorted(x, key=str)]


def steps(n, least=0, slow=False, path=f"{D}/orders.parquet"):
    wf = Workflow("plain")
    rows = wf.scan(wf.source("data", path), lambda d: d.filter(F.col("o_totalprice") > least), "rows")
    by = wf.scan(rows, lambda r: r.groupBy("o_orderstatus").count(), "by")
    wf.scan(rows, lambda r: r.limit(1), "unused")
    out = wf.reduce([by], lambda b: sorted([r["count"] for r in b.collect()])[:n], "out")
    wf.output(out)
    return wf


@pytest.mark.parametrize("policy", [Policy.optimal(), Policy.keep_all(), Policy.keep_none(), Policy.one_shot(), Policy.manual_keep(["rows"]), Policy.history(), Policy.baseline("local"), Policy.baseline("cumulative"), Policy.baseline("deepest")], ids=lambda p: p.name)
def test_every_policy_gives_what_scratch_gives(spark, tmp_path, policy):
    s = Session(spark, str(tmp_path / "a"), policy)
    for i, args in enumerate([(2,), (3,), (3, 1000.0), (2, 1000.0), (2,)]):
        got = s.run(steps(*args)).outputs["out"]
        assert got == Session(spark, str(tmp_path / f"scratch{i}"), Policy.one_shot()).run(steps(*args)).outputs["out"]


def test_post_edit_prunes_what_is_above(spark, tmp_path):
    s = Session(spark, str(tmp_path), Policy.keep_all())
    first = s.run(steps(2))
    assert "unused" not in first.states and first.record["n_compute"] == 4
    again = s.run(steps(3))
    assert again.states == {"data": "prune", "rows": "prune", "by": "load", "out": "compute"}
    assert again.status["out"] == "modified" and again.status["rows"] == "unchanged"
    same = s.run(steps(3))
    assert same.states["out"] == "load" and same.outputs == again.outputs


def test_reverting_with_short_and_long_history(spark, tmp_path):
    for history, expected in (("previous", "compute"), ("all", "load")):
        s = Session(spark, str(tmp_path / history), Policy.keep_all(), history=history)
        for least in (0, 500.0, 0):
            res = s.run(steps(2, least))
        assert res.states["out"] == expected


def test_state_outlives_the_session_and_damage_is_not_read(spark, tmp_path):
    Session(spark, str(tmp_path), Policy.keep_all()).run(steps(2))
    s = Session(spark, str(tmp_path), Policy.keep_all())
    assert s.run(steps(3)).states["by"] == "load"
    for stored in s.store.live.values():
        if stored.payload == "frame":
            os.remove(tmp_path / stored.path / "_SUCCESS")
    assert s.run(steps(1)).states["by"] == "compute"


def test_changed_source_is_read_again(spark, tmp_path):
    path = str(tmp_path / "orders")
    spark.read.parquet(f"{D}/orders.parquet").limit(50).coalesce(1).write.parquet(path)
    s = Session(spark, str(tmp_path / "s"), Policy.keep_all())
    a = s.run(steps(3, path=path)).outputs
    time.sleep(0.01)
    spark.read.parquet(f"{D}/orders.parquet").limit(90).coalesce(1).write.mode("append").parquet(path)
    res = s.run(steps(3, path=path))
    assert res.states["out"] == "compute" and res.outputs != a


def test_dump_rerun_takes_prep_edits_only(spark, tmp_path):
    s = Session(spark, str(tmp_path), Policy.dump_rerun())
    s.run(steps(2))
    assert s.run(steps(2, 9.0)).record["n_compute"] == 4
    with pytest.raises(ValueError):
        s.run(steps(3, 9.0))


def test_nondeterministic_results_are_frozen_under_post_edits_only(spark, tmp_path):
    s = Session(spark, str(tmp_path / "f"), Policy.keep_all())
    s.run(digit_vectors(D, 0, dims=16))
    post = s.run(digit_vectors(D, 0, dims=16, report="confusion"))
    assert post.states["predictions"] == "load"
    learn = s.run(digit_vectors(D, 0, dims=16, report="confusion", reg=0.5))
    assert learn.states["projection"] == "compute"
    never = Session(spark, str(tmp_path / "n"), Policy.keep_all(), nondeterministic="never")
    assert "projection" not in never.run(digit_vectors(D, 0, dims=16)).kept


def test_price_class_edits(spark, tmp_path):
    path = f"{D}/lineitem.parquet"
    s = Session(spark, str(tmp_path / "a"), Policy.keep_all())
    for i in (0, 1, 4, 5):
        res = s.run(price_class(path, i))
        scratch = Session(spark, str(tmp_path / f"b{i}"), Policy.one_shot()).run(price_class(path, i))
        assert rounded(res.outputs["checked"]) == rounded(scratch.outputs["checked"])
    assert "x_unused" not in res.states
    assert res.states["examples"] == "load" and res.states["rows"] == "prune"


def test_pair_extraction_reuses_sentences(spark, tmp_path):
    s = Session(spark, str(tmp_path), Policy.keep_all())
    s.run(pair_extraction(D, 0))
    assert s.run(pair_extraction(D, 1)).states["sentences"] == "prune"


def test_pair_extraction_predicts_every_candidate_pair(spark, tmp_path):
    docs, talk = (spark.read.parquet(f"{D}/{t}.parquet") for t in ("documents", "conversations"))
    texts = docs.selectExpr("concat('d', doc_id) id", "text").union(talk.selectExpr("concat_ws('-', 'c', conv_id, turn) id", "text"))
    pairs = R.candidate_pairs(R.mentions(R.sentences(texts, ["id"]), ["id"], 8), ["id"]).select("word_a", "word_b")
    known = known_pairs(spark.read.parquet(f"{D}/benchmark.parquet"))
    got = Session(spark, str(tmp_path), Policy.keep_none()).run(pair_extraction(D, 0)).outputs["precision"]
    hits = pairs.join(known, ["word_a", "word_b"], "left_semi").count()
    assert sum(r["count"] for r in got) == pairs.count() and sum(r["count"] for r in got if r["label"] == 1) == hits > 0


def test_waves_give_the_same(spark, tmp_path):
    a = Session(spark, str(tmp_path / "a"), Policy.keep_none(), parallel_nodes=3).run(steps(3)).outputs
    assert a == Session(spark, str(tmp_path / "b"), Policy.keep_none()).run(steps(3)).outputs


def test_store_budget_sweep_and_evict(spark, tmp_path):
    store = MaterializationStore(spark, str(tmp_path), budget_bytes=5000)
    assert store.put("s1", "n", "scalar", list(range(100)), 1)
    assert store.put("s2", "n", "scalar", list(range(5000)), 1) is None
    assert store.used <= 5000
    (tmp_path / "store" / "s9" / "orphan").mkdir(parents=True)
    again = MaterializationStore(spark, str(tmp_path), 5000)
    assert again.read(again.lookup("s1")) == list(range(100)) and not (tmp_path / "store" / "s9" / "orphan").exists()
    again.evict(4999, {"s1": 1.0})
    assert again.lookup("s1") is None


def test_uncaching_leaves_children(spark):
    a = spark.range(100).persist()
    b = a.selectExpr("id + 1 as x").persist()
    b.count()
    a.unpersist()
    assert b.storageLevel.useMemory


def test_simulator_follows_weights():
    got = simulate(EDITS, WEIGHTS["price_class"], 200, 3)
    assert got == simulate(EDITS, WEIGHTS["price_class"], 200, 3)
    assert sum(p == "post" for p, _ in got) > sum(p == "learn" for p, _ in got)


def test_one_more_grid_point_reuses_the_others(spark, tmp_path):
    s = Session(spark, str(tmp_path), Policy.keep_all())
    first = s.run(library_parity(D, 0)).outputs["best"]
    assert first["test"]["accuracy"] > 0.6
    more = s.run(library_parity(D, 1))
    assert more.states["model_0.001"] == "compute"
    assert {more.states[f"model_{r}"] for r in (0.1, 0.01)} == {"prune"} and more.states["rows"] != "compute"
    assert s.run(library_parity(D, 2)).states["model_0.001"] == "prune"


def test_a_new_session_knows_the_last_graph(spark, tmp_path):
    Session(spark, str(tmp_path), Policy.keep_all()).run(steps(2))
    s = Session(spark, str(tmp_path), Policy.keep_all())
    res = s.run(steps(2, 500.0))
    assert res.status["rows"] == "modified" and res.status["by"] == "inherited" and res.status["data"] == "unchanged"
    assert sorted(x.node for x in s.store.live.values()) == ["by", "out", "rows"]  # the old ones are purged
    dump = str(tmp_path / "d")
    Session(spark, dump, Policy.dump_rerun()).run(steps(2))
    assert Session(spark, dump, Policy.dump_rerun()).run(steps(2, 9.0)).record["n_compute"] == 4


def test_dump_rerun_writes_each_time_and_outputs_are_outside_the_budget(spark, tmp_path):
    s = Session(spark, str(tmp_path / "a"), Policy.dump_rerun())
    first = s.run(steps(2))
    again = s.run(steps(2))
    assert sorted(first.kept) == sorted(again.kept) == ["by", "out", "rows"]
    tight = Session(spark, str(tmp_path / "b"), Policy.optimal(budget_bytes=1))
    assert tight.run(steps(2)).kept == ["out"] and tight.store.used == 0 < tight.store.output_bytes
    assert tight.run(steps(2)).states["out"] == "load"


def test_extractors_belong_to_their_record_sets():
    wf = Workflow("two")
    data = wf.source("data", "p")
    a, b = (wf.scan(data, lambda d: d, n) for n in ("a", "b"))
    wf.extractor("x", "1", rows=a)
    wf.extractor("y", "2", rows=b)
    wf.examples(a, "ea")
    wf.examples(b, "eb")
    dag = wf.compile()
    assert dag.nodes["ea"].parents == ("a", "x") and dag.nodes["eb"].parents == ("b", "y")
    wf.extractor("z", "3")
    with pytest.raises(ValueError):
        wf.examples(b, "ec")


def test_scoring_leaves_out_what_weighs_nothing(spark, tmp_path):
    path = f"{D}/lineitem.parquet"
    session = Session(spark, str(tmp_path), Policy.keep_none())
    model = {"layout": ["x_disc", "x_price", "x_qty"], "weights": [0.0, 0.1, -0.01], "bias": -5.0}
    full, lean, rough = (session.run(lean_scoring.scoring(path, model, eps)) for eps in (None, 0.0, 0.05))
    assert "x_disc" in full.states and "x_disc" not in lean.states and "x_qty" in lean.states and "x_qty" not in rough.states
    n, same = X.compared_scores(full.outputs["scores"], lean.outputs["scores"], "key", "probability").first()
    assert n == same == spark.read.parquet(path).count()
    n, same = X.compared_scores(full.outputs["scores"], rough.outputs["scores"], "key", "probability").first()
    assert same < n


def test_training_data_is_cached_only_where_asked(spark, tmp_path):
    got = [Session(spark, str(tmp_path / str(c)), Policy.one_shot(c)).run(lean_scoring.training(f"{D}/lineitem.parquet")) for c in (True, False)]
    assert [r.record["policy"] for r in got] == ["one_shot", "one_shot_uncached"]
    a, b = (r.outputs["model"] for r in got)
    assert a["layout"] == b["layout"] and a["weights"] == pytest.approx(b["weights"], abs=1e-6)
