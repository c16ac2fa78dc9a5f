import heapq
import os
import random
from collections import Counter
from datetime import timedelta

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.errors import PySparkException

from iterspark import operator_queries, planner_queries, table_queries
from iterspark.functions import features as X
from iterspark.functions import learners as L
from iterspark.functions import metrics as M
from iterspark.functions import skip_gram
from iterspark.operators import relational as R
from iterspark.sources import io
from iterspark.streaming import minibatch
from iterspark.workloads.stream_features import stream_features

D = "/root/testdata/sf0.001"
Q = planner_queries.queries() | table_queries.queries() | operator_queries.queries()
SQL = planner_queries.oracle_sql() | table_queries.oracle_sql() | operator_queries.oracle_sql()
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from read_parquet('{D}/{t}.parquet')")
    return con


def plain(df: pd.DataFrame) -> list[str]:
    def one(v):
        if v is None or v is pd.NaT or (isinstance(v, float) and v != v):
            return None
        if hasattr(v, "item"):
            v = v.item()
        return round(float(v), 5) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)

    return sorted(repr([one(v) for v in r]) for r in df[sorted(df.columns)].astype(object).values.tolist())


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_equals_sql(spark, duck, name):
    got, want = Q[name](spark, D).toPandas(), duck.execute(SQL[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert plain(got) == plain(want)


@pytest.mark.parametrize("name", sorted(set(Q) - set(SQL)))
def test_query_without_sql_gives_rows(spark, name):
    assert Q[name](spark, D).count() > 0


def test_spans_of_all_orders_by_brute_force(spark):
    rows = [(i, 1000.0) for i in range(1, 40)] + [(50, 1499.99), (51, 1500.0), (52, 500.0), (53, 501.0), (54, -3.5), (55, None), (56, 0.0)]
    got = table_queries.orders_in_spans(spark.createDataFrame(rows, "o_orderkey long, o_totalprice double")).collect()
    want = {k: sum(1 for _, x in rows if x is not None and p <= x < p + 500) for k, p in rows if p is not None}
    assert {r["span"]: r["n"] for r in got} == want and len(got) == len(want)


def test_interval_counts_equal_those_of_pairs(spark):
    at = [0.0, 0.0, -0.0, 1.5, 9.99, 10.0, 10.0, 25.0, 31.0, 1e6, -7.5, None, float("nan"), float("inf"), float("-inf")]
    spans = [(0.0, 10.0), (0.0, 10.0), (-8.0, 32.0), (10.0, 10.0), (9.0, 2.0), (10.0, 10.5), (2.0, 3.0), (25.0, 45.0), (None, 3.0), (float("nan"), float("nan")), (-30.0, 0.0)]
    points, held = spark.createDataFrame([(x,) for x in at], "x double"), spark.createDataFrame(spans, "low double, high double")
    want = Counter((a, b) for a, b in set(spans) for x in at if None not in (a, b, x) and a <= x < b)
    for width in (10.0, 0.7, 1e9):
        got = R.interval_counts(points, held, "x", "low", "high", width).collect()
        assert {(r["low"], r["high"]): r["n"] for r in got} == want and len(got) == len(want)
    pairs = R.interval_join(points.filter("abs(x) < 1e7"), held.distinct().filter("low <= high"), "x", "low", "high", 10.0)
    assert Counter((r["low"], r["high"]) for r in pairs.collect()) == want


def test_spans_of_orders_at_one_price_make_no_pairs(spark, tmp_path):
    spark.range(100_000).selectExpr("id o_orderkey", "double(if(id % 10 = 0, 1499.99, 1000)) o_totalprice").write.parquet(f"{tmp_path}/orders.parquet")
    got = Q["interval_join"](spark, str(tmp_path)).groupBy("n").count().collect()  # ten thousand million pairs
    assert sorted(map(tuple, got)) == [(10_000, 10_000), (100_000, 90_000)]


def test_spans_of_many_prices_make_no_pairs(spark):
    orders = spark.range(100_000).selectExpr("id o_orderkey", "1000 + id / 1000D o_totalprice")  # 100 from end to end
    got = table_queries.orders_in_spans(orders).filter("n <> 100000 - span").count()  # five thousand million pairs
    assert got == 0


def test_token_lists_keep_one_row_a_text(spark):
    rows = spark.createDataFrame([(1, "B a, cc"), (1, "dd"), (2, "1 2"), (3, None)], "doc_id long, text string")
    got = sorted(tuple(r["ws"]) for r in R.token_lists(rows, ["doc_id"]).collect())
    assert got == [("b", "a", "cc"), ("dd",)]
    assert sorted(tuple(r["ws"]) for r in R.token_lists(rows, ["doc_id"], 2).collect()) == [("cc",), ("dd",)]


def test_every_order_has_a_span(spark, duck):
    spans = {name for name in SQL if name.startswith("interval_join") and duck.execute(f"SELECT count(*) FROM ({SQL[name]})").fetchone()[0] == duck.execute("SELECT count(DISTINCT o_orderkey) FROM orders").fetchone()[0]}
    assert spans == {"interval_join", "interval_join_all_spans"}


def _cents_of_groups(spark, folder, name):
    """A price so large that a double beside it keeps no cents, then a thousand orders of a cent."""
    rows = [("F", "1-URGENT", 9e13)] + [("F", "5-LOW", 0.01)] * 1000 + [("O", "5-LOW", None)]
    spark.createDataFrame(rows, "o_orderstatus string, o_orderpriority string, o_totalprice double").coalesce(1).write.parquet(f"{folder}/orders.parquet")
    return {tuple(r)[:2]: tuple(r)[2:] for r in Q[name](spark, str(folder)).collect()}


def test_a_cube_loses_no_cents(spark, tmp_path):
    got = _cents_of_groups(spark, tmp_path, "cube_orders")
    assert got == {("F", "1-URGENT"): (1, 9 * 10**15), ("F", "5-LOW"): (1000, 1000), ("O", "5-LOW"): (1, None), ("F", None): (1001, 9 * 10**15 + 1000), ("O", None): (1, None), (None, "1-URGENT"): (1, 9 * 10**15), (None, "5-LOW"): (1001, 1000), (None, None): (1002, 9 * 10**15 + 1000)}


def test_a_rollup_loses_no_cents(spark, tmp_path):
    got = _cents_of_groups(spark, tmp_path, "rollup_orders")
    assert got == {("F", "1-URGENT"): (1, 9 * 10**15), ("F", "5-LOW"): (1000, 1000), ("O", "5-LOW"): (1, None), ("F", None): (1001, 9 * 10**15 + 1000), ("O", None): (1, None), (None, None): (1002, 9 * 10**15 + 1000)}


TABLE_QUERIES = ["equivalence_chain", "feature_exclusion", "iteration_cumulative_time", "keep_knapsack_star", "originals_closure", "out_of_scope_order", "phase_breakdown", "planner_gap_by_shape", "slice_reachable"]


@pytest.mark.parametrize("name", TABLE_QUERIES)
def test_a_query_reads_a_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        Q[name](spark, str(tmp_path)).collect()


@pytest.mark.parametrize("price", [float("nan"), float("inf"), float("-inf")])
def test_a_rollup_leaves_no_price_out(spark, tmp_path, price):
    rows = [("F", "5-LOW", 1.0), ("F", "5-LOW", price)]
    spark.createDataFrame(rows, "o_orderstatus string, o_orderpriority string, o_totalprice double").write.parquet(f"{tmp_path}/orders.parquet")
    with pytest.raises(PySparkException, match="o_totalprice"):  # as its SQL, which can cast no such sum
        Q["rollup_orders"](spark, str(tmp_path)).collect()


def test_cooccurrence_of_all_documents_by_brute_force(spark, duck):
    tokens = duck.execute("SELECT regexp_extract_all(lower(text), '\\p{L}+') FROM documents").fetchall()
    want = Counter()
    for (row,) in tokens:
        for i, a in enumerate(row or []):
            for b in row[i + 1 : i + 3]:
                want[a, b] += 1
                want[b, a] += 1
    got = {(r["token"], r["other"]): r["n"] for r in Q["cooccurrence_documents"](spark, D).collect()}
    assert got == want
    vectors = Q["cooccurrence_embedding_documents"](spark, D)
    assert {r[0] for r in vectors.select("word").collect()} == {a for a, _ in want}


def test_entry_module():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())


def test_fused_states_take_fewer_jobs(spark):
    rows = spark.read.parquet(f"{D}/lineitem.parquet")
    specs = {c: X.FeatureState(c, "range") for c in ("l_tax", "l_discount", "l_quantity")}
    jobs = []
    for fused in (True, False):
        spark.sparkContext.setJobGroup(f"g{fused}", "count")
        X.fit_features(rows, specs, fused)
        jobs.append(M.job_counts(spark, f"g{fused}")["jobs"])
    spark.sparkContext.setJobGroup("", "")
    assert jobs[0] < jobs[1]


def test_logistic_beats_chance_and_grid_search(spark):
    df = spark.range(400).selectExpr("cast(id % 20 as double) x", "cast((id % 20) > 9 as double) y")

    def acc(m):
        return M.accuracy(m.transform(df), "y", "prediction").first()[0]

    best = L.grid_search(lambda reg: L.logistic(df, ["x"], "y", reg), acc, {"reg": [0.01, 0.1]})
    assert best[0][1] > 0.9 and len(best) == 2


def test_visible_text_and_shape(spark):
    df = spark.createDataFrame([("<p>Hi <b>you</b></p><script>x<1</script>",), (None,)], "h string")
    assert [r[0] for r in df.select(R.visible_text(df.h)).collect()] == ["Hi you", None]
    assert df.limit(1).select(R.word_shape(R.F.lit("Ab12c"))).first()[0] == "Xxdx"


def test_sources_and_sinks_round_trip(spark, tmp_path):
    df = spark.read.parquet(f"{D}/nation.parquet")
    for kind in ("parquet", "csv", "json", "orc"):
        io.write(df, str(tmp_path / kind), kind, **({"header": True} if kind == "csv" else {}))
        back = io.read(spark, str(tmp_path / kind), kind, df.schema, **({"header": True} if kind == "csv" else {}))
        assert M.content_hash(back.select(df.columns)) == M.content_hash(df)
    io.write(df, "", "noop")
    io.write_bucketed(df, "nation_b", "n_nationkey", 2)
    assert io.read(spark, "nation_b", "table").count() == 25
    assert io.read_split(spark, f"{D}/nation.parquet", f"{D}/nation.parquet").filter("split = 'test'").count() == 25


def test_stream_decision_survives_a_restart(spark, tmp_path):
    a = stream_features(spark, f"{D}/events.parquet", str(tmp_path))
    first, rows = a.decision, a.read("features").count()
    b = stream_features(spark, f"{D}/events.parquet", str(tmp_path))
    assert b.decision == first and b.read("features").count() == rows
    a.on_batch(spark.read.parquet(f"{D}/events.parquet").limit(10), 0)
    assert a.read("features").filter("batch = 0").count() <= 10


def test_memory_sampler():
    with M.MemorySampler(0.01) as m:
        pass
    assert m.peak >= m.average > 0


def test_random_cosine_with_and_without_seed(spark):
    e = spark.read.parquet(f"{D}/embeddings.parquet").limit(5)
    one = lambda seed: [list(r[0]) for r in X.random_cosine(e, "embedding", 4, seed).select("projected").collect()]
    assert one(1) == one(1) and one(None) != one(None)


def test_a_watermark_drops_late_rows(spark, tmp_path):
    rows = spark.read.parquet(f"{D}/events.parquet")
    first, last = rows.agg({"ts": "min"}).first()[0], rows.agg({"ts": "max"}).first()[0]
    folder = tmp_path / "files"
    folder.mkdir()
    for i, when in enumerate((last, last, first)):  # the newest row twice: by then a delay of a day shuts out the oldest
        rows.filter(rows["ts"] == when).coalesce(1).write.parquet(str(tmp_path / f"part{i}"))
        part = next((tmp_path / f"part{i}").glob("*.parquet")).rename(folder / f"{i}.parquet")
        os.utime(part, (1_700_000_000 + i, 1_700_000_000 + i))  # a file stream goes by the files' times

    def run(late, out):
        stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(str(folder))
        got = minibatch.drained(minibatch.tumbling_counts(stream, late=late), str(tmp_path / out), "update")
        return got.filter(got["window_start"] < last - timedelta(days=1)).count()

    assert run("1 day", "strict") == 0
    assert run("3650 days", "lenient") == 1


def test_an_experiment_prints_a_line(spark, capsys):
    import json

    from iterspark import experiments

    experiments.main([D, "--workload", "digit_vectors", "--policy", "keep_none", "--iterations", "2"])
    line = json.loads(capsys.readouterr().out.strip().splitlines()[-1])
    assert line["finished"] and len(line["versions"]) == 2


def test_vocabularies_beyond_the_bound_are_an_error(spark, monkeypatch):
    rows = spark.createDataFrame([(w,) for w in "abcb"] + [(None,)], "w string")
    state = {"v": X.FeatureState("w", "vocabulary")}
    assert X.fit_features(rows, state)["v"] == ["a", "b", "c"]
    monkeypatch.setattr(X, "MOST_WORDS", 2)
    with pytest.raises(ValueError, match="over 2 values"):
        X.fit_features(rows, state)


def test_scores_compared_and_images_flattened(spark):
    a = spark.createDataFrame([(1, 0.5), (2, None), (3, 0.1), (4, 0.2)], "k int, s double")
    b = spark.createDataFrame([(1, 0.5), (2, None), (3, 0.4)], "k int, s double")
    assert tuple(X.compared_scores(a, b, "k", "s").first()) == (4, 2)
    images = spark.createDataFrame([([[1, 2], [3, 4]],), ([],), (None,), ([[1], None],)], "image array<array<int>>")
    assert [r[0] for r in images.select(X.flat_image("image")).collect()] == [[1, 2, 3, 4], [], None, None]
    model = {"layout": ["a", "b", "c"], "weights": [0.0, -0.2, 0.01], "bias": 1.0}
    assert X.prune_model(model) == {"layout": ["b", "c"], "weights": [-0.2, 0.01], "bias": 1.0}
    assert X.prune_model(model, 0.05)["layout"] == ["b"]


def _texts(n):
    rng = random.Random(3)
    topics = [[f"{t}{i}" for i in range(12)] for t in "ab"]
    return [(i, rng.choices(topics[i % 2], k=rng.randint(0, 40))) for i in range(n)] + [(n, None), (n + 1, ["rare"] * 4 + [None])]


def test_word_vectors_of_several_parts_follow_from_the_texts(spark, monkeypatch):
    monkeypatch.setattr(L, "tasks_for", lambda df, least=1: 4)
    texts = _texts(600)
    runs = []
    for order in (texts, texts[::-1]):
        got = L.word_vectors(spark.createDataFrame(order, "doc_id long, ws array<string>").repartition(3), "ws", size=8)
        runs.append({r["word"]: r["vector"] for r in got.collect()})
    assert runs[0] == runs[1]
    assert len(runs[0]) == 24  # "rare" comes four times


def test_words_with_the_same_neighbours_are_near(spark, monkeypatch):
    monkeypatch.setattr(L, "tasks_for", lambda df, least=1: 1)
    df = spark.createDataFrame(_texts(1500), "doc_id long, ws array<string>")
    got = {r["word"]: np.array(r["vector"]) for r in L.word_vectors(df, "ws", size=8).collect()}
    near = {True: [], False: []}
    for a in got:
        for b in got:
            if a < b:
                near[a[0] == b[0]].append(got[a] @ got[b] / np.linalg.norm(got[a]) / np.linalg.norm(got[b]))
    assert np.mean(near[True]) > np.mean(near[False]) + 0.5


def test_huffman_paths_are_as_short_as_can_be():
    rng = random.Random(5)
    for n in (1, 2, 3, 200):
        counts = np.array([rng.randint(5, 400) for _ in range(n)])
        heap, least = sorted(counts.tolist()), 0
        while len(heap) > 1:
            a, b = heapq.heappop(heap), heapq.heappop(heap)
            least += a + b
            heapq.heappush(heap, a + b)
        ways = skip_gram.paths(np.arange(n), *skip_gram.huffman(counts))
        lengths = (ways.top != 0).sum(1) + (ways.deep >= 0).sum(1)
        assert (lengths * counts).sum() == least
        turns = {(tuple(t), *zip(d[d >= 0], s[d >= 0], strict=True)) for t, d, s in zip(ways.top, ways.deep, ways.signs, strict=True)}
        assert len(turns) == n


def _plain_step(ids, texts, inner, tree, window, reach, rate):
    """The steps of one block of places, pair by pair."""
    size = inner.shape[1]
    nodes = np.zeros((tree.n_nodes, size))
    to_inner, to_nodes = np.zeros(inner.shape), np.zeros(nodes.shape)
    for c in range(len(ids)):
        path = [(k, s) for k, s in enumerate(tree.top[ids[c]]) if s] + [(k, s) for k, s in zip(tree.deep[ids[c]], tree.signs[ids[c]], strict=True) if k >= 0]
        for o in range(max(0, c - reach[c]), min(len(ids), c + reach[c] + 1)):
            if o != c and texts[o] == texts[c]:
                for k, s in path:
                    g = rate * s / (1 + np.exp(s * (inner[ids[o]] @ nodes[k])))
                    to_inner[ids[o]] += g * nodes[k]
                    to_nodes[k] += g * inner[ids[o]]
    return to_inner, to_nodes


def test_a_step_is_the_sum_over_all_pairs(monkeypatch):
    rng, window = np.random.default_rng(2), 3
    counts = rng.integers(5, 50, 150)
    tree = skip_gram.paths(np.arange(150), *skip_gram.huffman(counts))
    n = 200
    ids, texts = rng.integers(0, 150, n).astype(np.int32), (np.arange(n) // 30).astype(np.uint8)
    reach = np.random.default_rng(4).integers(1, window + 1, -(-n // (skip_gram.BLOCK * skip_gram.BLOCKS)) * skip_gram.BLOCK * skip_gram.BLOCKS, dtype=np.uint8).tolist()
    seen = []
    move = skip_gram._move
    monkeypatch.setattr(skip_gram, "_move", lambda rows, at, steps, cells, rates: (seen.append((at, steps[cells] * rates[cells][:, None])), move(rows, at, steps, cells, rates)))
    inner = skip_gram.starts(np.arange(150), 8, 7)
    before = inner.astype(float)
    tail = window + skip_gram.BLOCK * skip_gram.BLOCKS
    skip_gram.train(np.concatenate([np.zeros(window, np.int32), ids, np.zeros(tail, np.int32)]), np.concatenate([np.full(window, 255, np.uint8), texts, np.full(tail, 255, np.uint8)]), inner, tree, window, 1, np.random.default_rng(4))
    _, to_nodes = _plain_step(ids, texts, before, tree, window, reach, skip_gram.RATE)
    got = np.zeros((tree.n_nodes + 1, 8))
    np.add.at(got, seen[0][0], seen[0][1])
    assert np.abs(to_nodes[skip_gram.TOP :]).sum() > 0
    assert np.allclose(got[skip_gram.TOP : -1], to_nodes[skip_gram.TOP :], atol=1e-6)
