"""Registered queries of the operators around the methods: exact keep, equivalence, transformations, relational and stream operators."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from iterspark.functions import features as X
from iterspark.functions import metrics as M
from iterspark.operators import relational as R
from iterspark.plans import frames, keep, synthetic
from iterspark.plans.versions import signatures
from iterspark.planner_queries import assignments_sql, table_version_sql, table_versions, version_dag
from iterspark.registry import Registry, t, work_folder
from iterspark.streaming import minibatch
from iterspark.workloads import library_parity as parity

_registry = Registry()
query = _registry.query

# planners

_DIAMOND = ([(1, 2), (1, 3), (2, 4), (3, 4)], {1: 9, 2: 2, 3: 3, 4: 4}, {1: 3, 2: 1, 3: 2, 4: 2}, [4], [4])
_KEEP_BUDGET = 4
_KEPT = " + ".join(f"CASE WHEN (m >> {i - 1}) & 1 = 1 THEN {_DIAMOND[2][i]} ELSE 0 END" for i in _DIAMOND[2])
_UNKEPT_LOADED = " OR ".join(f"(s{i} = 1 AND (m >> {i - 1}) & 1 = 0)" for i in _DIAMOND[2])


@query(f"""WITH a AS ({assignments_sql(_DIAMOND)}), o AS (SELECT m, min(cost) + ({_KEPT}) * (SELECT count(*) FROM orders) AS objective FROM a, range(16) r(m) WHERE ({_KEPT}) <= {_KEEP_BUDGET} AND NOT ({_UNKEPT_LOADED}) GROUP BY m)
SELECT concat_ws(',', {", ".join(f"CASE WHEN (m >> {i - 1}) & 1 = 1 THEN '{i}' END" for i in _DIAMOND[2])}) AS kept, CAST(objective AS BIGINT) AS objective FROM o ORDER BY objective, m LIMIT 1""")
def keep_exact_small(spark, d):
    k = t(spark, d, "orders").count()
    edges, c, l, forced, required = _DIAMOND
    cost, load = ({str(n): v * k for n, v in x.items()} for x in (c, l))
    names = [{str(n) for n in x} for x in (forced, required)]
    best, kept = keep.keep_exact(frames.dag_of(edges, len(c)), cost, load, load, _KEEP_BUDGET * k, forced=names[0], required=names[1])
    return spark.createDataFrame([(",".join(sorted(kept)), int(best))], "kept string, objective long")


@query(f"SELECT node, status = 'unchanged' AS first_second, status = 'unchanged' AS second_third, true AS first_third FROM ({table_version_sql()}) WHERE status NOT IN ('added', 'removed')")
def equivalence_chain(spark, d):
    """A version, an edited one and the first again: which nodes are equivalent in each pair."""
    first, second = table_versions(spark, d)
    a, b, c = (signatures(version_dag(v)) for v in (first, second, first))
    rows = [(n, a[n] == b[n], b[n] == c[n], a[n] == c[n]) for n in a if n in b]
    return spark.createDataFrame(rows, "node string, first_second boolean, second_third boolean, first_third boolean")


# transformations


@query("WITH r AS (SELECT min(l_extendedprice) AS lo, max(l_extendedprice) AS hi FROM lineitem) SELECT l_returnflag, round(avg((l_extendedprice - lo) / (hi - lo)), 5) AS mean, round(min((l_extendedprice - lo) / (hi - lo)), 5) AS least, round(max((l_extendedprice - lo) / (hi - lo)), 5) AS most FROM lineitem, r GROUP BY 1")
def min_max_scale(spark, d):
    li = t(spark, d, "lineitem").select("l_returnflag", "l_extendedprice")
    low, high = X.fit_features(li, {"r": X.FeatureState("l_extendedprice", "range")})["r"]
    scaled = li.withColumn("x", F.expr(X.min_max_sql("l_extendedprice", low, high)))
    return scaled.groupBy("l_returnflag").agg(*[F.round(f("x"), 5).alias(n) for n, f in (("mean", F.avg), ("least", F.min), ("most", F.max))])


_TOKENS = "SELECT item_id, unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS token FROM benchmark"


@query(f"WITH k AS ({_TOKENS}), c AS (SELECT item_id, token, count(*) AS n FROM k GROUP BY 1, 2), f AS (SELECT token, count(*) AS df FROM c GROUP BY 1) SELECT item_id, token, n, round(n * ln(((SELECT count(DISTINCT item_id) FROM k) + 1.0) / (df + 1)), 5) AS weight FROM c JOIN f USING (token)")
def tf_idf_weights(spark, d):
    return X.tf_idf(R.tokens(t(spark, d, "benchmark"), ["item_id"]), "item_id", "token").withColumn("weight", F.round("weight", 5))


@query()
def tf_idf_weights_documents(spark, d):
    return X.tf_idf(R.tokens(t(spark, d, "documents"), ["doc_id"]), "doc_id", "token").withColumn("weight", F.round("weight", 5))


@query()
def principal_components(spark, d):
    return spark.createDataFrame(list(enumerate(X.principal_shares(t(spark, d, "embeddings"), "embedding", 4))), "component int, share double")


# relational operators


@query("SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS finished, count(*) FILTER (o_orderstatus = 'O') AS open, count(*) FILTER (o_orderstatus = 'P') AS partial FROM orders GROUP BY 1")
def pivot_status(spark, d):
    p = t(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count()
    return p.select("o_orderpriority", *[F.coalesce(c, F.lit(0)).cast("long").alias(n) for c, n in (("F", "finished"), ("O", "open"), ("P", "partial"))])


@query("""SELECT o_orderkey, rank() OVER p AS place, dense_rank() OVER p AS dense_place, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 5) AS share_before, round(cume_dist() OVER w, 5) AS share_upto,
coalesce(lag(o_orderkey) OVER w, -1) AS former, coalesce(lead(o_orderkey) OVER w, -1) AS later, coalesce(nth_value(o_orderkey, 2) OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING), -1) AS second
FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey), p AS (PARTITION BY o_custkey ORDER BY o_orderpriority)""")
def rank_windows(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    p = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return t(spark, d, "orders").select(
        "o_orderkey",
        F.rank().over(p).cast("long").alias("place"),
        F.dense_rank().over(p).cast("long").alias("dense_place"),
        F.ntile(4).over(w).cast("long").alias("quarter"),
        F.round(F.percent_rank().over(w), 5).alias("share_before"),
        F.round(F.cume_dist().over(w), 5).alias("share_upto"),
        F.coalesce(F.lag("o_orderkey").over(w), F.lit(-1)).alias("former"),
        F.coalesce(F.lead("o_orderkey").over(w), F.lit(-1)).alias("later"),
        F.coalesce(F.nth_value("o_orderkey", 2).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)), F.lit(-1)).alias("second"),
    )


@query("""SELECT l_linestatus, count(DISTINCT l_suppkey) AS suppliers, round(stddev_samp(l_quantity), 4) AS deviation, round(var_pop(l_quantity), 4) AS variance, round(corr(l_quantity, l_extendedprice), 4) AS correlation,
round(covar_samp(l_quantity, l_discount), 4) AS covariance, round(quantile_cont(l_extendedprice, 0.5), 2) AS middle, count(*) FILTER (l_tax > 0.04) AS taxed, max(struct_pack(p := l_extendedprice, k := l_orderkey)).k AS dearest FROM lineitem GROUP BY 1""")
def statistics(spark, d):
    return t(spark, d, "lineitem").groupBy("l_linestatus").agg(
        F.count_distinct("l_suppkey").alias("suppliers"),
        F.round(F.stddev_samp("l_quantity"), 4).alias("deviation"),
        F.round(F.var_pop("l_quantity"), 4).alias("variance"),
        F.round(F.corr("l_quantity", "l_extendedprice"), 4).alias("correlation"),
        F.round(F.covar_samp("l_quantity", "l_discount"), 4).alias("covariance"),
        F.round(F.percentile("l_extendedprice", 0.5), 2).alias("middle"),
        F.count_if(F.col("l_tax") > 0.04).alias("taxed"),
        F.max(F.struct("l_extendedprice", "l_orderkey"))["l_orderkey"].alias("dearest"),
    )


@query("""SELECT p_partkey, lower(p_name) AS lowered, substr(p_type, 1, 5) AS head, translate(p_brand, 'aeiou', 'AEIOU') AS vowels, length(trim(p_name)) AS size, split_part(p_type, ' ', 1) AS first_word,
regexp_extract(p_brand, '[0-9]+') AS number, p_brand || '/' || p_type AS joined, levenshtein(p_brand, p_type) AS edits, p_name LIKE '%a%' AS has_a FROM part""")
def string_functions(spark, d):
    return t(spark, d, "part").select(
        "p_partkey",
        F.lower("p_name").alias("lowered"),
        F.substring("p_type", 1, 5).alias("head"),
        F.translate("p_brand", "aeiou", "AEIOU").alias("vowels"),
        F.length(F.trim("p_name")).cast("long").alias("size"),
        F.split_part("p_type", F.lit(" "), F.lit(1)).alias("first_word"),
        F.regexp_extract("p_brand", "[0-9]+", 0).alias("number"),
        F.concat_ws("/", "p_brand", "p_type").alias("joined"),
        F.levenshtein("p_brand", "p_type").cast("long").alias("edits"),
        F.col("p_name").like("%a%").alias("has_a"),
    )


@query("""SELECT year(o_orderdate) AS year, quarter(o_orderdate) AS quarter, dayofweek(o_orderdate) + 1 AS day_of_week, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month_start,
count(*) AS n, CAST(max(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE))) AS BIGINT) AS last_day, strftime(max(CAST(o_orderdate AS DATE) + 30), '%Y-%m-%d') AS due FROM orders GROUP BY 1, 2, 3, 4""")
def date_functions(spark, d):
    o = t(spark, d, "orders").withColumn("day", F.to_date("o_orderdate"))
    keys = [F.year("day").cast("long").alias("year"), F.quarter("day").cast("long").alias("quarter"), F.dayofweek("day").cast("long").alias("day_of_week"), F.date_format(F.trunc("day", "month"), "yyyy-MM-dd").alias("month_start")]
    return o.groupBy(*keys).agg(F.count("*").alias("n"), F.max(F.datediff("day", F.lit("1992-01-01").cast("date"))).cast("long").alias("last_day"), F.date_format(F.max(F.date_add("day", 30)), "yyyy-MM-dd").alias("due"))


@query("""SELECT s_suppkey, round(ln(abs(s_acctbal) + 1), 6) AS logged, round(sqrt(abs(s_acctbal)), 6) AS root, round(pow(s_acctbal / 1000, 2), 6) AS squared, greatest(s_acctbal, 0.0) AS above, least(s_acctbal, 100.0) AS below,
CAST(sign(s_acctbal) AS BIGINT) AS side, ((s_suppkey - 7) % 5 + 5) % 5 AS ring, CAST(floor(s_acctbal / 1000) AS BIGINT) AS bin FROM supplier""")
def math_functions(spark, d):
    x = F.col("s_acctbal")
    return t(spark, d, "supplier").select(
        "s_suppkey",
        F.round(F.log(F.abs(x) + 1), 6).alias("logged"),
        F.round(F.sqrt(F.abs(x)), 6).alias("root"),
        F.round(F.pow(x / 1000, F.lit(2.0)), 6).alias("squared"),
        F.greatest(x, F.lit(0.0)).alias("above"),
        F.least(x, F.lit(100.0)).alias("below"),
        F.signum(x).cast("long").alias("side"),
        F.pmod(F.col("s_suppkey") - 7, F.lit(5)).cast("long").alias("ring"),
        F.floor(x / 1000).alias("bin"),
    )


@query("""WITH e AS (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings)
SELECT vec_id, round(sqrt(list_dot_product(v, v)), 4) AS norm, round(list_max(v), 5) AS most, CAST(list_position(v, list_max(v)) AS BIGINT) AS most_at, round(list_sum(v[1:8]), 4) AS head, len(list_filter(v, lambda x: x > 0)) AS positive FROM e""")
def array_functions(spark, d):
    e = t(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    return e.select(
        "vec_id",
        F.round(F.sqrt(total(F.transform("v", lambda x: x * x))), 4).alias("norm"),
        F.round(F.array_max("v"), 5).alias("most"),
        F.array_position("v", F.array_max("v")).alias("most_at"),
        F.round(total(F.slice("v", 1, 8)), 4).alias("head"),
        F.size(F.filter("v", lambda x: x > 0)).cast("long").alias("positive"),
    )


@query("WITH f AS (SELECT 'price' AS feature, l_extendedprice AS value FROM lineitem UNION ALL SELECT 'tax', l_tax FROM lineitem UNION ALL SELECT 'discount', l_discount FROM lineitem) SELECT feature, count(*) AS n, round(sum(value), 2) AS total FROM f WHERE value > 0.02 GROUP BY 1")
def map_features(spark, d):
    """Features as a key-value map: filtered, exploded, counted."""
    m = F.create_map(F.lit("price"), "l_extendedprice", F.lit("tax"), "l_tax", F.lit("discount"), "l_discount")
    return t(spark, d, "lineitem").select(F.explode(F.map_filter(m, lambda _, v: v > 0.02)).alias("feature", "value")).groupBy("feature").agg(F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("total"))


@query("SELECT part, count(*) AS n FROM (SELECT CASE WHEN x > 100 THEN 'above' WHEN NOT (x > 100) THEN 'not above' ELSE 'unknown' END AS part FROM (SELECT nullif(value, 0.0) * CASE WHEN event_id % 9 = 0 THEN NULL ELSE 1 END AS x FROM events)) GROUP BY 1")
def three_valued_filter(spark, d):
    x = F.when(F.col("event_id") % 9 != 0, F.nullif(F.col("value"), F.lit(0.0)))
    e = t(spark, d, "events").select(x.alias("x"))
    parts = {"above": F.col("x") > 100, "not above": ~(F.col("x") > 100), "unknown": (F.col("x") > 100).isNull()}
    kinds = F.coalesce(*[F.when(c, F.lit(n)) for n, c in parts.items()])
    return e.groupBy(kinds.alias("part")).agg(F.count("*").alias("n"))


@query("SELECT item_id, len(w) AS words, max_len FROM (SELECT item_id, string_split(text, ' ') AS w, (SELECT max(length(x)) FROM unnest(string_split(text, ' ')) u(x)) AS max_len FROM benchmark)")
def lateral_words(spark, d):
    b = t(spark, d, "benchmark")
    each = b.lateralJoin(spark.tvf.explode(F.split(F.col("text").outer(), " ")).toDF("word"))
    return each.groupBy("item_id").agg(F.count("*").alias("words"), F.max(F.length("word")).cast("long").alias("max_len"))


@query("SELECT c.c_custkey, count(o_orderkey) AS n, round(coalesce(sum(o_totalprice), 0), 2) AS total FROM customer c LEFT JOIN orders ON c_custkey = o_custkey AND o_orderstatus <> 'P' GROUP BY 1")
def outer_join(spark, d):
    """Pre-aggregated before the join, so that a customer with very many orders costs one row."""
    o = t(spark, d, "orders").filter("o_orderstatus <> 'P'").groupBy("o_custkey").agg(F.count("*").alias("n"), F.sum("o_totalprice").alias("total"))
    c = t(spark, d, "customer").select("c_custkey")
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).cast("long").alias("n"), F.round(F.coalesce("total", F.lit(0.0)), 2).alias("total"))


# functions in Python, all ways; each gives the built-in's answer

_WAYS = ["built in", "python", "pandas", "arrow batches"]


@query(" UNION ALL ".join(f"SELECT '{w}' AS way, role, CAST(sum(len(regexp_extract_all(text, '[^ ]+'))) AS BIGINT) AS words FROM conversations GROUP BY role" for w in _WAYS))
def udf_family(spark, d):
    rows = t(spark, d, "conversations").select("role", F.coalesce("text", F.lit("")).alias("text"))

    @F.udf("long")
    def by_row(text):
        return len([w for w in text.split(" ") if w])

    @F.pandas_udf("long")
    def by_series(text: pd.Series) -> pd.Series:
        return text.str.split(" ").map(lambda ws: sum(1 for w in ws if w)).astype("int64")

    def by_batch(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len([w for w in x.split(" ") if w]) for x in b.column(1).to_pylist()], pa.int64())], names=["role", "w"])

    def summed(df: DataFrame, way: str) -> DataFrame:
        return df.groupBy("role").agg(F.sum("w").cast("long").alias("words")).select(F.lit(way).alias("way"), "role", "words")

    out = summed(rows.select("role", F.regexp_count("text", F.lit("[^ ]+")).alias("w")), _WAYS[0])
    out = out.union(summed(rows.select("role", by_row("text").alias("w")), _WAYS[1])).union(summed(rows.select("role", by_series("text").alias("w")), _WAYS[2]))
    return out.union(summed(rows.mapInArrow(by_batch, "role string, w long"), _WAYS[3]))


# streams: what a replay in files gives is what the table gives


def _replay(spark, d, root) -> DataFrame:
    return minibatch.replayed(spark, f"{d}/events.parquet", f"{root}/replay", 3)


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(opens) OVER (PARTITION BY user_id ORDER BY ts) AS no FROM g) SELECT n, count(*) AS sessions FROM (SELECT user_id, no, count(*) AS n FROM s GROUP BY 1, 2) GROUP BY 1""")
def stream_sessions(spark, d):
    root = work_folder(spark)
    got = minibatch.drained(minibatch.session_counts(_replay(spark, d, root)), f"{root}/sessions", "complete")
    return got.groupBy("n").agg(F.count("*").alias("sessions"))


@query("SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY 1")
def stream_deduplicated(spark, d):
    """Every event arrives twice; the state keeps ids for longer than the replay's span."""
    root = work_folder(spark)
    events = _replay(spark, d, root)
    got = minibatch.drained(minibatch.deduplicated(events.union(events), "event_id", "3650 days"), f"{root}/dedup")
    return got.groupBy("event_type").agg(F.count("*").alias("n"))


@query("SELECT c_mktsegment, count(*) AS n, round(sum(value), 3) AS total FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def stream_static_join(spark, d):
    root = work_folder(spark)
    customers = t(spark, d, "customer").withColumnRenamed("c_custkey", "user_id")
    got = minibatch.drained(minibatch.enriched(_replay(spark, d, root), customers, "user_id", ["c_mktsegment"]), f"{root}/joined")
    return got.groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("value"), 3).alias("total"))


@query("SELECT user_id, count(*) AS n, round(sum(value), 3) AS total FROM events GROUP BY 1")
def stream_running_totals(spark, d):
    """Each user's state after its last batch."""
    root = work_folder(spark)
    got = minibatch.drained(minibatch.running_totals(_replay(spark, d, root), "user_id", "value"), f"{root}/totals", "update")
    return got.groupBy("user_id").agg(F.max_by(F.struct("n", F.round("total", 3).alias("total")), "batch").alias("s")).select("user_id", "s.n", "s.total")


# measures and model selection

_CUTS = [0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8]
_PARITY_SQL = f"""WITH l AS (SELECT doc_id, max(quality) AS label FROM labels WHERE quality IS NOT NULL GROUP BY 1),
w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
r AS (SELECT CASE WHEN len(w) > 0 THEN len(list_distinct(w)) / len(w) ELSE 0 END AS share, label FROM w JOIN l USING (doc_id) WHERE doc_id % 5 = 1)
SELECT CAST(cut AS DOUBLE) AS cut, count(*) AS n, sum(CASE WHEN (share >= CAST(cut AS DOUBLE)) = (label = 1) THEN 1 ELSE 0 END)::BIGINT AS hits FROM r, (VALUES {", ".join(f"({c})" for c in _CUTS)}) c(cut) GROUP BY 1"""


@query(_PARITY_SQL)
def grid_cut_scores(spark, d):
    """Model selection with an exact learner: hits of each cut on the validation part."""
    rows = parity.described(t(spark, d, "documents"), t(spark, d, "labels")).filter("split = 'validation'")
    return parity.cut_scores(rows, _CUTS)


@query("""WITH x AS (SELECT vec_id % 7 AS cluster, vec_id, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) AS i FROM embeddings),
m AS (SELECT cluster, i, avg(v) AS c FROM x GROUP BY 1, 2)
SELECT cluster, count(DISTINCT vec_id) AS n, round(sum((v - c) * (v - c)), 4) AS cost FROM x JOIN m USING (cluster, i) GROUP BY 1""")
def within_cluster_cost(spark, d):
    e = t(spark, d, "embeddings").select((F.col("vec_id") % 7).alias("c"), "embedding")
    return M.within_cluster_cost(e, "embedding", "c", 64).withColumn("cost", F.round("cost", 4))


_SHAPE_EDGES = {"chain": 6, "star": 6, "diamonds": 8}


@query(f"""WITH g AS (SELECT l_partkey % 35 // 7 AS seed, 1 + CAST(sum(l_suppkey) AS BIGINT) % 100 AS cost FROM lineitem GROUP BY l_partkey % 35)
SELECT shape, CAST(edges AS BIGINT) AS edges, CAST(seed AS BIGINT) AS seed, CAST(sum(cost) AS BIGINT) AS compute_all, CAST(0 AS BIGINT) AS gap FROM (VALUES {", ".join(f"('{k}', {v})" for k, v in _SHAPE_EDGES.items())}) s(shape, edges), g GROUP BY 1, 2, 3""")
def planner_gap_by_shape(spark, d):
    """Planned less least cost on small graphs of each shape, with costs from line items of 35 groups of parts; the search over all assignments finds nothing cheaper."""
    groups = t(spark, d, "lineitem").groupBy((F.col("l_partkey") % 35).alias("g")).agg(F.count("*").alias("n"), F.sum("l_suppkey").alias("k"), F.sum("l_linenumber").alias("m")).collect()
    own = {seed: ({}, {}) for seed in range(5)}
    for r in groups:
        compute, load = own[r["g"] // 7]
        node = f"n{r['g'] % 7:06d}"
        compute[node], load[node] = 1 + r["k"] % 100, None if r["n"] % 5 == 0 else 1 + r["m"] % 150
    rows = [(s, len(synthetic.SHAPES[s](7, seed)), seed, sum(own[seed][0].values()), synthetic.gap(s, 7, seed, own[seed])) for s in _SHAPE_EDGES for seed in own]
    return spark.createDataFrame(rows, "shape string, edges long, seed long, compute_all long, gap long")


def queries() -> dict:
    return dict(_registry.queries)


def oracle_sql() -> dict[str, str]:
    return dict(_registry.sql)
