"""Each operator against a brute-force version, and on nulls, empty and long texts, ties, repeats, empty tables, clashing names."""

import collections
import hashlib
import os
import re
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from iterspark.llm import common, components, fingerprints, fixity, labelled, mixing, near_dup, packing, quality_classifier, quality_rules, sharding, textvec, toxicity, url_filter
from iterspark.llm import queries as Q

D = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0d]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long"
ODD_TEXTS = [None, "", " \t\n", "one", "one two three four five", "a b c d e f a b c d e f", "é\u00a0ß \u2003x", "x " * 30_000, "w" * 50_000, "same text here for all of us", "same text here for all of us"]


def words(s):
    return WORD.findall(s or "")


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls everywhere, repeated rows, and columns whose names clash with the operators' own."""
    rows = [(i, x, ["en", None, "xx"][i % 3], ["a", None][i % 2], 0) for i, x in enumerate(ODD_TEXTS)]
    rows += [(None, None, None, None, None), (3, "one", "en", "a", 0), (3, "one", "en", "a", 0)]
    df = spark.createDataFrame(rows, DOCS)
    for name in ("size", "taken", "copies", "rate", "kept", "text_id", "score", "hash", "_key", "file", "label", "n_words"):
        df = df.withColumn(name, F.lit("clash"))
    return df


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{D}/documents.parquet")


@pytest.fixture(scope="module")
def labels(spark):
    return spark.read.parquet(f"{D}/labels.parquet")


# words and shingles


@pytest.mark.parametrize("size", [8, 1 << 18])
def test_words_and_shingles_by_hand(size):
    texts = [*ODD_TEXTS[:7], "a b", "", "b a", "a b c d e f g"]
    by_word, n = {}, 0
    for block in textvec.blocks(pa.array(texts), size):
        w = textvec.words(block)
        for i in range(len(block.bounds) - 1):
            own = words(texts[block.first + i])
            got = w.hash[w.first[i] : w.first[i + 1]]
            assert len(got) == len(own)
            for a, b in zip(own, got, strict=True):
                assert by_word.setdefault(a, b) == b
            h, d = textvec.shingles(w)
            assert (d == i).sum() == (len(own) - 4 if len(own) >= 5 else bool(own))
            n += 1
    assert n == len(texts) and len(set(by_word.values())) == len(by_word)


# 1 mixing


def test_targets_reshare_the_excess():
    sizes = {"b": 100, None: 100, "a": 100}
    got = mixing.targets(sizes, (3, 1, 2), 1.5, 2)
    assert got == {"a": 200.0, "b": pytest.approx(250 / 3), None: pytest.approx(500 / 3)}
    assert sum(mixing.targets({"a": 10, "b": 1000, "c": 5}, (3, 1, 2), 1.5, 2).values()) == pytest.approx(1522.5)


def test_mix_meets_targets_and_reruns_agree(docs):
    got = mixing.mix(docs).toPandas().merge(docs.toPandas()[["doc_id", "source", "text"]], on="doc_id")
    assert (got["size"] == got.text.map(lambda s: len(words(s)))).all()
    assert (got.taken <= 2 * got["size"]).all()
    for _, g in got.groupby("source"):
        assert abs(g.taken.sum() - g.target.iloc[0]) <= g["size"].max()
        assert g["size"].sum() == g.source_size.iloc[0]
    again = mixing.mix(docs.repartition(7)).toPandas().set_index("doc_id").taken
    assert (again.sort_index() == got.set_index("doc_id").taken.sort_index()).all()


def test_rates_are_an_exponential_tilt(docs):
    got = mixing.mix(docs, keep=("source",)).toPandas()
    for _, g in got[got.rate.between(1e-6, 2 - 1e-6) & (got["size"] > 0)].groupby("source"):
        slope = np.log(g.rate) / g["size"]
        assert np.allclose(slope, slope.iloc[0], rtol=1e-4, atol=1e-9)


def test_mix_odd(odd, none):
    got = mixing.mix(odd).toPandas()
    assert len(got) == odd.count() and (got.taken <= 2 * got["size"]).all()
    assert mixing.mix(none).count() == 0
    assert mixing.stage(None, odd, D).columns == odd.columns


# 2 fixity


def test_replicas_laid_out_by_themselves(spark):
    pages = spark.read.parquet(f"{D}/pages.parquet").select("page_id", "url", "html")
    bad = F.when(F.col("page_id") % 7 == 3, F.concat(F.col("html"), F.lit("xyz"))).otherwise(F.col("html"))
    other = pages.filter("page_id % 11 <> 4").withColumn("html", bad).union(pages.filter("page_id % 13 = 5").withColumn("page_id", F.col("page_id") + 10**6))
    got = fixity.compare(pages, other.repartition(3), per_file=8, fanout=5).toPandas()
    ids = [r[0] for r in pages.select("page_id").collect()]
    want = {i: "lost" if i % 11 == 4 else "damaged" if i % 7 == 3 else "sound" for i in ids} | {i + 10**6: "extra" for i in ids if i % 13 == 5}
    assert dict(zip(got.record_id, got.state, strict=True)) == want and len(got) == len(want)
    assert (got.replica_sha256.isna() == (got.state == "lost")).all() and (got.sha256.isna() == (got.state == "extra")).all()
    # the replica's own offsets cut its records out of its own files
    columns = [F.col(c) for c in ("page_id", "url", "html")]
    texts = {hashlib.sha256(r[0].encode()).hexdigest(): r[0].encode() for r in other.select(fixity.record_text(*columns)).collect()}
    laid = fixity.layout(fixity.records(other), -(-len(ids) // 8)).toPandas().sort_values(["file", "seq"])
    files = {f: b"".join(texts[x] for x in g.digest) for f, g in laid.groupby("file")}
    at = dict(zip(laid.digest, zip(laid.file, laid.offset, laid.length, strict=True), strict=True))
    for r in got[got.state != "lost"].itertuples():
        f, offset, length = at[r.replica_sha256]
        assert offset == r.replica_offset and files[f][offset : offset + length] == texts[r.replica_sha256]
    assert set(fixity.compare(pages, pages).toPandas().state) == {"sound"}


def test_only_differing_branches_are_looked_at(spark):
    pages = spark.range(4000).selectExpr("id as page_id", "'u' as url", "repeat('h', 20) as html")
    other = pages.withColumn("html", F.when(F.col("page_id") == 77, "z").otherwise(F.col("html")))
    a, b = (fixity.tree(fixity.layout(fixity.records(x), 4)) for x in (pages, other))
    assert [x.groupBy("file").count().agg(F.max("count")).first()[0] for x in a][-1] == 1
    (slot,) = fixity.audit(a, b).collect()
    assert slot["first_byte"] < slot["end_byte"] and slot["replica_end_byte"] < slot["end_byte"]


def test_offsets_cut_the_records_out_of_the_files(spark):
    pages = spark.read.parquet(f"{D}/pages.parquet")
    rec = pages.select(fixity.record_text(F.col("page_id"), F.col("url"), F.col("html")).alias("record")).withColumn("digest", F.sha2("record", 256)).withColumn("length", F.octet_length("record").cast("long"))
    laid = fixity.layout(rec.withColumn("key", F.col("digest")), 5)
    files = {r["file"]: bytes(r["content"]) for r in fixity.archive_files(laid).collect()}
    for r in laid.collect():
        cut = files[r["file"]][r["offset"] : r["offset"] + r["length"]]
        assert hashlib.sha256(cut).hexdigest() == r["digest"]
    assert sum(map(len, files.values())) == sum(r["length"] for r in laid.collect())


def test_audit_odd(spark):
    rows = [(1, None, None), (1, None, None), (None, "u", ""), (2, "u", "h" * 100_000), (3, "u", "one"), (3, "u", "two")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", F.lit(1)).withColumn("key", F.lit(1)).withColumn("state", F.lit(1))
    got = fixity.compare(pages, pages).toPandas()
    assert sorted(got.copies) == [1, 1, 1, 1, 2] and set(got.state) == {"sound"}
    # copies differ; of records that share id and url one is changed; an id of its own is changed
    other = spark.createDataFrame([(1, None, None), (None, "u", "x"), (2, "u", "h" * 100_000), (3, "u", "one"), (3, "u", "three")], "page_id long, url string, html string")
    got = fixity.compare(pages, other).toPandas()
    states = collections.Counter((None if pd.isna(r.record_id) else int(r.record_id), r.state) for r in got.itertuples())
    assert states == {(1, "recount"): 1, (None, "damaged"): 1, (2, "sound"): 1, (3, "sound"): 1, (3, "damaged"): 1}
    empty = pages.limit(0)
    assert fixity.compare(empty, empty).count() == 0
    assert set(fixity.compare(empty, pages).toPandas().state) == {"extra"} and set(fixity.compare(pages, empty).toPandas().state) == {"lost"}
    # one record becomes two of its id and url: the first is placed anew, but found
    got = fixity.compare(pages.filter("page_id = 2"), pages.filter("page_id = 2").union(spark.createDataFrame([(2, "u", "k", 1, 1, 1)], pages.schema.simpleString()[7:-1])))
    assert collections.Counter(got.toPandas().state) == {"sound": 1, "extra": 1}


# 3 and 5 classifiers


def auc(score, y):
    r = pd.Series(score).rank().to_numpy()
    p = np.asarray(y) == 1
    return (r[p].sum() - p.sum() * (p.sum() + 1) / 2) / (p.sum() * (~p).sum())


@pytest.mark.parametrize("which", ["quality", "toxic"])
def test_held_out_accuracy(spark, which):
    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    if which == "quality":
        got = quality_classifier.classify_quality(spark, docs, labels)
    else:
        got = toxicity.score_toxicity(docs, toxicity.fit_toxicity(docs, labels))
    got = got.toPandas()
    assert len(got) == 1000 and got.score.between(0, 1).all()
    assert (got.held_out == got.doc_id.map(lambda i: zlib.crc32(str(i).encode()) % 5 == 0)).all()
    assert (got.predicted == (got.score >= (0.3 if which == "quality" else 0.5))).all()
    held = got[got.held_out].merge(labels.toPandas(), on="doc_id")
    assert auc(held.score, held[which]) > (0.9 if which == "quality" else 0.8)


def test_context_vectors_do_not_hang_on_the_deal(docs):
    shape = quality_classifier.Shape(buckets=2048, dims=16)
    a = quality_classifier.context_vectors(docs.coalesce(1), shape)
    b = quality_classifier.context_vectors(docs.repartition(70), shape)
    assert np.array_equal(a, b) and np.any(a)


def test_context_vectors_by_hand(spark):
    shape = quality_classifier.Shape(buckets=1024, dims=8, window=1)
    got = quality_classifier.context_vectors(spark.createDataFrame([("a b c",)], "text string"), shape)
    (block,) = textvec.blocks(pa.array(["a b c"]))
    buckets = quality_classifier.bucket_of(textvec.words(block), shape)
    index = np.zeros((1024, 8))
    for place, sign in quality_classifier._places(np.arange(1024), shape):
        index[np.arange(1024), place] += sign
    want = index[buckets[0]] + index[buckets[2]]
    assert np.allclose(got[buckets[1]], want / max(1, np.linalg.norm(want)), atol=1e-6)


def test_classifiers_odd(spark, odd, none, labels):
    for frame in (odd, none):
        q = quality_classifier.classify_quality(spark, frame, labels).toPandas()
        t = toxicity.score_toxicity(frame, toxicity.fit_toxicity(frame, labels)).toPandas()
        assert len(q) == len(t) == frame.count()
        assert q.score.between(0, 1).all() and t.score.between(0, 1).all()
    assert toxicity.stage(spark, odd, D).columns == odd.columns
    no_labels = labels.limit(0)
    assert set(quality_classifier.classify_quality(spark, odd, no_labels).toPandas().score) == {0.5}
    assert set(toxicity.score_toxicity(odd, toxicity.fit_toxicity(odd, no_labels)).toPandas().score) == {0.0}


def test_training_rows_are_bounded_and_leave_the_held_out_fold(docs, labels):
    got = labelled.training_rows(docs, labels, "quality", 20)
    assert got.count() == 20 and got.filter("part = 0").count() == 0


def test_obfuscated_insults_count():
    texts = ["you 1d10t", "you i.d.i.o.t", "you IDIOOOOT", "you idiot", "fine words", "", "idiot! you!", "you id!ot!!", "idiiott", "i-d-i-i-o-t"]
    x = toxicity.features(pa.array(texts), toxicity.Lexicon.of(["idiot"]))
    f = {n: x[:, i] for i, n in enumerate(toxicity.FEATURES)}
    assert list(f["obfuscated_count"]) == [1, 1, 1, 1, 0, 0, 1, 1, 1, 1]
    assert list(f["lexicon_count"]) == [0, 0, 0, 1, 0, 0, 1, 0, 0, 0]
    assert list(f["near_you"] > 0) == [1, 1, 1, 1, 0, 0, 1, 1, 0, 0]


def test_features_by_brute_force(docs):
    """Lexicon words, second-person proximity, capitals, punctuation and obfuscation rates of whole texts, word by word."""
    bad, you = ["the", "stupid", "hate"], set(toxicity.SECOND_PERSON)
    texts = [r["text"] for r in docs.limit(60).collect()] + ["YOU are 5tup1d!! hate-you, h.a.t.e", "u $tupid u", "a  hate\tb c d e you", "Stuuupid @@ ##x", *ODD_TEXTS[:7]]
    x = toxicity.features(pa.array(texts), toxicity.Lexicon.of(bad))
    f = {n: x[:, i] for i, n in enumerate(toxicity.FEATURES)}
    looks = dict(zip("0134578@$!", "oieastbasi", strict=True))
    drop = set(".,;:?\"'()[]{}-_*|~/\\`^+=#%&<>")
    alnum = re.compile(r"[A-Za-z0-9\u0080-\U0010ffff]")
    low = lambda s: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in s)

    def forms(w):
        inner = [0 < i < len(w) - 1 and alnum.match(w[i - 1]) and alnum.match(w[i + 1]) for i in range(len(w))]
        plain = [c for c, ok in zip(w, inner, strict=True) if ok or (c not in drop and c != "!")]
        leet = [looks.get(c, low(c)) for c, ok in zip(w, inner, strict=True) if c not in drop and (ok or c != "!")]
        return low("".join(plain)), "".join(c for i, c in enumerate(leet) if not (i and c == leet[i - 1] and "a" <= c <= "z"))

    squeezed = {forms(w)[1] for w in bad}
    people = {forms(w)[1] for w in you}
    for i, t in enumerate(texts):
        w, size = words(t), max(len((t or "").encode()), 1)
        plain, leet = [p for p, _ in map(forms, w) if p], [q for _, q in map(forms, w) if q]
        lex, hits = sum(p in bad for p in plain), [j for j, q in enumerate(leet) if q in squeezed]
        near = [j for j in hits if any(leet[k] in people for k in range(max(0, j - 4), min(len(leet), j + 5)))]
        n = max(len(w), 1)
        want = {"lexicon": lex / n, "obfuscated": max(len(hits) - lex, 0) / n, "near_you": len(near) / n, "second_person": sum(q in people for q in leet) / n}
        want |= {"upper": sum("A" <= c <= "Z" for c in t or "") / size, "exclaim": (t or "").count("!") / size, "sign": sum(c in "@#$%&*^~+=<>|_/\\" for c in t or "") / size, "log_words": np.log1p(len(w))}
        for name, v in want.items():
            assert f[name][i] == pytest.approx(v, abs=1e-12), (name, t and t[:60])


def test_gradients_and_temperature_by_brute_force():
    """One step of training from the same start: the network's gradient by differences; the temperature by search."""
    rng = np.random.default_rng(4)
    x, y = rng.normal(size=(40, 5)), (rng.random(40) < 0.4).astype(float)
    net = quality_classifier.Network(hidden=3, epochs=1, rate=1e-3, decay=0.0).fit(x, y, np.zeros(40, dtype=bool))
    start = quality_classifier.Network(hidden=3, epochs=0, decay=0.0).fit(x, y, np.zeros(40, dtype=bool))
    z = (x - start.mean) / start.std

    def loss(w):
        logit = np.tanh(z @ w[0] + w[1]) @ w[2] + w[3]
        return np.mean(np.logaddexp(0, np.where(y > 0.5, -logit, logit)))

    for k, a in enumerate(start.w):
        for at in np.ndindex(a.shape):
            up, down = [b.copy() for b in start.w], [b.copy() for b in start.w]
            up[k][at] += 1e-6
            down[k][at] -= 1e-6
            slope = (loss(up) - loss(down)) / 2e-6
            if abs(slope) > 1e-4:  # the first step of the optimiser goes `rate` against the gradient's sign
                assert net.w[k][at] - a[at] == pytest.approx(-1e-3 * np.sign(slope), rel=1e-2)
    held = np.arange(40) % 2 == 0
    net = quality_classifier.Network(hidden=8, epochs=200).fit(x, y, held)
    logit = net._logit(((x - net.mean) / net.std)[held])
    grid = np.linspace(0.25, 8, 4000)
    best = min(np.mean(np.logaddexp(0, np.where(y[held] > 0.5, -logit, logit) / t)) for t in grid)
    assert net.temperature > 1 and np.mean(np.logaddexp(0, np.where(y[held] > 0.5, -logit, logit) / net.temperature)) <= best + 1e-4


def test_a_tree_splits_where_all_splits_tried_are_worse():
    rng = np.random.default_rng(1)
    x, y = rng.integers(0, 6, (400, 3)).astype(float), (rng.random(400) < 0.5).astype(float)
    y[x[:, 1] > 3] = 1
    (splits, value), *_ = toxicity.Trees(rounds=1, depth=1, rate=1.0, least=5, shrink=5.0).fit(x, y).trees
    p = np.clip(y.mean(), 1e-4, 1 - 1e-4)
    g, h = y - p, np.full(400, p * (1 - p))
    score = lambda m: g[m].sum() ** 2 / (h[m].sum() + 5)
    tried = {(k, t): score(x[:, k] <= t) + score(x[:, k] > t) for k in range(3) for t in range(5)}
    (feature, edge), _ = max(tried.items(), key=lambda kv: kv[1])
    assert splits[0][0] == feature and edge <= splits[0][1] < edge + 1
    left = x[:, feature] <= edge
    assert value == pytest.approx([g[left].sum() / (h[left].sum() + 5), g[~left].sum() / (h[~left].sum() + 5)])


def test_isotonic_and_trees():
    x, y = toxicity.isotonic(np.array([1.0, 2, 3, 4]), np.array([0.0, 1, 0, 1]))
    assert list(y) == [0, 0.5, 0.5, 1] and list(x) == [1, 2, 3, 4]
    rng = np.random.default_rng(0)
    a = rng.normal(size=(2000, 3))
    b = ((a[:, 0] > 0) ^ (a[:, 1] > 0)).astype(float)
    assert auc(toxicity.Trees().fit(a, b).margin(a), b) > 0.97


# 4 urls


def brute_url(url, rules):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    host = "".join(c.lower() if "A" <= c <= "Z" else c for c in re.match(r"[^/?#]*", rest)[0])
    path = re.match(r"[^?#]*", rest[len(host) :])[0]
    fits = [r for r in rules if (host == r[0] or host.endswith("." + r[0])) and path.startswith(r[1])]
    best = max(fits, key=lambda r: (len(r[0] + r[1]), len(r[0])), default=None)
    return host, path, best and best[0] + best[1], best[2] if best else "allow"


URLS = ["http://A.Example.org/en/1?x", "https://example.org/en/12/3", "x://org", "x://org/", "http://notexample.org/es/", "http://www.fr.com/fr/a#b", "http://x.com/de/", "http://x.com?/de/", "no scheme", "", None, "http:///p", "a://b.c/://d", "http://com.org.com/fr/" + "y" * 50_000]


def test_urls_by_both_ways(spark):
    rules = [*url_filter.RULES, ("a.example.org", "/", "allow"), ("c", "/://", "block"), ("www.fr.com", "/fr/a", "block")]
    df = spark.createDataFrame([(i, u) for i, u in enumerate(URLS)], "page_id long, url string").withColumn("rule", F.lit(1)).withColumn("host", F.lit(1))
    want = {i: brute_url(u, rules) for i, u in enumerate(URLS)}
    for bound in (200_000, 0):
        got = url_filter.judge_urls(df, rules, broadcast_rules=bound, ranges=4).collect()
        assert {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in got} == want
    assert url_filter.judge_urls(df.limit(0), rules).count() == 0


def test_many_rules_are_swept_in_even_ranges(spark):
    rng = np.random.default_rng(2)
    labels = ["com", "org", "net", "a", "b", "shop", "x1", "news"]
    hosts = sorted({".".join(rng.choice(labels, rng.integers(1, 5))) for _ in range(700)})
    paths = ["", "/", "/a", "/a/b", "/a/b/c", "/z\u00e9", "/ab"]
    rules = [(h, str(p), ["allow", "block", "review-later"][int(rng.integers(3))]) for h in hosts for p in rng.choice(paths, 3, replace=False)]
    rules += [("hot.com", f"/p/{i}", "block") for i in range(1500)] + [("hot.com", "/p/7", "allow"), (None, "/", "block"), ("x1", None, "allow")]
    urls = [f"http://{'.'.join(rng.choice(labels, rng.integers(1, 6)))}{rng.choice(paths)}{rng.choice(paths)}?q" for _ in range(600)]
    urls += [f"s://www.Hot.com/p/{i}/x" for i in range(0, 3000, 7)] + ["s://hot.com/p/77"] * 900 + URLS
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").repartition(5)
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filter.judge_urls(df, rules, broadcast_rules=10, ranges=16).collect()}
    assert got == {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filter.judge_urls(df, rules).collect()}
    whole = [r for r in rules if None not in r and r != ("hot.com", "/p/7", "allow")]
    some = [*range(0, 600, 6), *range(600, 1030, 40), *range(len(urls) - len(URLS), len(urls))]
    assert all(got[i] == brute_url(urls[i], whole) for i in some)
    keys = spark.createDataFrame([(url_filter.key_of(f"n{i:06}.example.com"),) for i in range(20_000)], "key string")
    sizes = [r["count"] for r in url_filter.dealt(keys, url_filter._bounds(keys, 64)).groupBy("range").count().collect()]
    assert len(sizes) > 60 and max(sizes) < 3 * 20_000 / 64


def test_a_batch_enters_the_rules_where_its_urls_are():
    rules = [(f"h{i:05}.com", "/", "block") for i in range(5000)] + [("com", "/", "allow"), ("a.h04000.com", "/x", "allow")]
    sweep = url_filter.Sweep(rules)
    hosts = ["z.h00001.com", "a.h04000.com", "b.a.h04000.com", "q.com", "h04999.com", "net"]
    got = sweep.run(hosts, ["/x"] * 6, "none")
    assert got == (["h00001.com/", "a.h04000.com/x", "a.h04000.com/x", "com/", "h04999.com/", None], ["block", "allow", "allow", "allow", "block", "none"])


# 6 fingerprints


def brute_next(rows):
    order = sorted(rows, key=lambda r: -r[0])
    return {r[0]: order[(i + 1) % len(order)] for i, r in enumerate(order)}


@pytest.mark.parametrize("per_range", [7, 2000])
def test_edits_and_fingerprints(spark, docs, per_range):
    rows = [(r["doc_id"], r["text"] or "") for r in docs.collect()] + [(10**9 + i, x or "") for i, x in enumerate(ODD_TEXTS)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    after, texts = brute_next(rows), dict(rows)
    led = fingerprints.with_next(df, rows_per_range=per_range).collect()
    assert len(led) == len(rows)
    for r in led:
        s, nxt = texts[r["doc_id"]], after[r["doc_id"]][1]
        h = len(s) // 2
        assert r["following"] == nxt and r["edited"] == s[: len(s) - h] + nxt[:h] and r["n_chars"] == len(s)


@pytest.mark.parametrize("hot", [None, 5])
def test_successors_of_a_hot_id(spark, hot):
    rows = [(i, f"text {i}") for i in range(100)] + [(hot, f"hot {i % 150}") for i in range(300)] + [(2**63 - 1, "z")] * 40
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(7)
    got = [(r["doc_id"], r["text"], r["following"]) for r in fingerprints.with_next(df, rows_per_range=20).collect()]
    tie = {r["text"]: r["h"] for r in df.select("text", F.xxhash64("text").alias("h")).collect()}
    order = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0), tie[r[1]]))
    assert sorted(got, key=repr) == sorted(((*r, order[(i + 1) % len(order)][1]) for i, r in enumerate(order)), key=repr)


def test_likeness_is_near_the_true_one(docs):
    got = fingerprints.fingerprint_documents(docs).toPandas().set_index("doc_id")
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    after = brute_next(rows)
    errors = []
    for i, s in rows:
        h = len(s) // 2
        e = s[: len(s) - h] + after[i][1][:h]
        assert got.edited_sha256[i] == hashlib.sha256(e.encode()).hexdigest()
        sets = [{tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} if w else set() for w in (words(s), words(e))]
        errors.append(got.near_edited[i] - len(sets[0] & sets[1]) / max(1, len(sets[0] | sets[1])))
    assert abs(np.mean(errors)) < 0.03 and np.abs(errors).mean() < 0.1


def test_sketches_merge_and_equal_texts_agree():
    texts = [" ".join(f"w{i}" for i in range(a, b)) for a, b in ((0, 2000), (1500, 6000), (0, 30), (20, 60))]
    s = fingerprints.sketches(pa.array([*texts, texts[0].replace(" ", "\n"), "", None]))
    assert np.array_equal(s[0], s[4]) and len(s[5]) == len(s[6]) == 0
    assert all(np.array_equal(fingerprints.decode(fingerprints.encode(x)), x) for x in s)
    whole = fingerprints.merged(s[0], s[1])
    assert abs(fingerprints.compare(s[0], whole)[1] - 1) < 1e-9
    assert fingerprints.compare(s[0], s[0])[0] == 1.0 and fingerprints.compare(s[5], s[6])[0] == 1.0 and fingerprints.compare(s[5], s[0])[0] == 0.0
    big = fingerprints.sketches(pa.array([" ".join(f"w{i}" for i in range(1000, 1400))]))[0]
    assert fingerprints.compare(big, s[0])[1] > 0.9 > fingerprints.compare(big, s[0])[0]


def test_repeated_passages_keep_the_least_hashes():
    passages = [" ".join(f"{c}{i}" for i in range(n)) for c, n in (("a", 12), ("b", 20), ("c", 50), ("d", 90))]
    texts = [p + f"\n{p}" * 60 for p in passages] + ["x " * 5000, *passages, " ".join(f"w{i}" for i in range(3000))]
    h, d = textvec.shingles(textvec.words(next(textvec.blocks(pa.array(texts)))), 5)
    limit = np.uint64(0.125 * 2**48)
    got = fingerprints.sketches(pa.array(texts))
    for i, sketch in enumerate(got):
        every = np.unique(h[d == i] >> np.uint64(16))
        under = every[every < limit]
        assert np.array_equal(sketch, under if len(under) >= 16 else every[:16])
    part, whole = fingerprints.sketches(pa.array([texts[2], texts[2] + " end"]))
    assert fingerprints.compare(part, whole)[0] > 0.8


def test_fingerprints_odd(odd, none):
    assert fingerprints.fingerprint_documents(odd).count() == odd.count()
    assert fingerprints.fingerprint_documents(none).count() == 0
    assert fingerprints.fingerprint_documents(odd.limit(1)).count() == 1


# 7 quality rules


def brute_rules(s):
    w = words(s)
    n = collections.Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    covered = {j for i in range(len(w) - 4) if n[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
    seen, dup = set(), 0
    for line in (s or "").split("\n"):
        if words(line):
            dup += line in seen
            seen.add(line)
    return len(w), sum(map(len, w)), sum((s or "").count(c) for c in "#*$%&|<>"), dup, len(covered)


def test_base_counts(spark, docs):
    extra = [(10**6 + i, x, "en", "s", 0) for i, x in enumerate([*ODD_TEXTS, "a a a a a a", "#*$%&|<>", "x\nx\n \n\nx\n", "\u0085 \u2028 b"])]
    df = docs.union(spark.createDataFrame(extra, DOCS))
    got = {r["doc_id"]: r for r in quality_rules.divergence_rules(df).collect()}
    for r in df.collect():
        g, b = got[r["doc_id"]], brute_rules(r["text"])
        assert (g["n_words"], g["word_chars"], g["n_symbols"], g["n_dup_lines"], g["n_repeat_words"]) == b
        assert g["base_failed"] == (b[0] < 10 or 100 * b[4] > 20 * b[0]) and not (g["base_failed"] and g["kept"])


def test_divergence_by_hand(spark):
    df = spark.createDataFrame([([0.5, 0.5, 0.0], [0.25, 0.25, 0.5])], "p array<double>, q array<double>")
    p, q = np.array([0.5, 0.5, 0]), np.array([0.25, 0.25, 0.5])
    m = (p + q) / 2
    kl = lambda a: sum(x * np.log2(x / y) for x, y in zip(a, m, strict=True) if x)
    assert df.select(quality_rules.js_distance(F.col("p"), F.col("q"))).first()[0] == pytest.approx(np.sqrt((kl(p) + kl(q)) / 2))


def test_verdicts_by_brute_force(docs):
    """`kept` of whole texts: histograms, mean references, distances and guards in plain Python."""
    got = {r["doc_id"]: r for r in quality_rules.divergence_rules(docs).collect()}
    kinds = [lambda c: "a" <= c <= "z", lambda c: c in "\x20\t\n\x0b\x0c\r", lambda c: "A" <= c <= "Z", lambda c: "0" <= c <= "9", lambda c: c in "#*$%&|<>", lambda c: c in ".,;:!?'\"()-", lambda c: c > "\x7f"]
    shares, own = {}, {}
    for r in docs.collect():
        t, w = r["text"] or "", words(r["text"])
        counts = [0] * 8
        for c in t:
            counts[next((i for i, k in enumerate(kinds) if k(c)), 7)] += 1
        listed = quality_rules.COMMON_WORDS.get(r["lang"])
        hits = [w.count(x) for x in listed] if listed else None
        c = np.array(counts) / len(t) if len(t) >= 200 else None
        v = np.array([*hits, len(w) - sum(hits)]) / len(w) if hits and len(w) >= 100 else None
        own[r["doc_id"]] = (r["lang"], c, v)
        if not got[r["doc_id"]]["base_failed"]:
            for k, x in (("c", c), ("v", v)):
                if x is not None:
                    shares.setdefault((r["lang"], k), []).append(x)

    def distance(p, q):
        m = (p + q) / 2
        part = lambda a: sum(x * np.log2(x / y) for x, y in zip(a, m, strict=True) if x)
        return np.sqrt(max((part(p) + part(q)) / 2, 0))

    for i, (lang, c, v) in own.items():
        d = [distance(x, np.mean(shares[lang, k], axis=0)) if x is not None and (lang, k) in shares else None for k, x in (("c", c), ("v", v))]
        for name, want in zip(("char_distance", "word_distance"), d, strict=True):
            assert (got[i][name] is None) == (want is None) and (want is None or got[i][name] == pytest.approx(want, abs=1e-6))
        a, b = (x or 0 for x in d)
        if min(abs(a - 0.32), abs(b - 0.33), abs(a + b - 0.4)) > 1e-6:
            assert got[i]["kept"] == (not got[i]["base_failed"] and a <= 0.32 and b <= 0.33 and a + b <= 0.4)


def test_given_references_are_the_norm(spark, docs):
    norm = quality_rules.language_references(docs.filter("doc_id % 2 = 0"))
    junk = docs.filter("doc_id % 2 = 1").limit(5).withColumn("text", F.expr("repeat('# 1 $ 2 % 3 ', 60) || cast(doc_id as string) || reverse(repeat(cast(doc_id as string), 30))"))
    judged = quality_rules.divergence_rules(junk, references=norm).collect()
    by_itself = quality_rules.divergence_rules(junk).collect()
    assert len(judged) == 5 and all(r["char_distance"] > 0.32 for r in judged) and all(r["char_distance"] < 0.32 for r in by_itself if r["char_distance"] is not None)


def test_rules_part_clean_from_junk(spark):
    d = "/root/testdata/sf0.01"
    m = quality_rules.divergence_rules(spark.read.parquet(f"{d}/documents.parquet")).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id").filter("not base_failed").toPandas()
    assert m[m.quality == 1].kept.mean() > 0.99 and m[m.quality == 0].kept.mean() < 0.3


def test_rules_odd(odd, none):
    got = quality_rules.stage(None, odd, D)
    assert got.columns == odd.columns and got.count() <= odd.count()
    assert quality_rules.divergence_rules(odd).count() == odd.count()
    assert quality_rules.divergence_rules(none).count() == 0


# 8 packing


def hf_ids(texts):
    import public_tokenizers
    from tokenizers import Tokenizer

    tk = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    return [np.array([*e.ids, 0], dtype="<u4") for e in tk.encode_batch([x or "" for x in texts], add_special_tokens=False)]


def check_pieces(got, ids):
    """`ids`: of each doc_id, its ids."""
    for doc, g in got.groupby("doc_id"):
        at = 0
        for r in g.sort_values("start").itertuples():
            assert r.start == at and r.ids_crc32 == zlib.crc32(ids[doc][at : at + r.length].tobytes()) and r.doc_tokens == len(ids[doc])
            at += r.length
        assert at == len(ids[doc])
    padding = 0
    for _, g in got.groupby("sequence_id"):
        at = 0
        for r in g.sort_values("offset").itertuples():
            assert r.offset == at
            at += r.length
        assert at <= 1024
        padding += 0 if at & (at - 1) == 0 else 1024 - at
    return padding


def test_packing_round_trip(docs):
    rows = docs.collect()
    ids = dict(zip([r["doc_id"] for r in rows], hf_ids([r["text"] for r in rows]), strict=True))
    got = packing.pack(docs, packing.default_ranks(), block_rests=50).toPandas()
    assert set(got.doc_id) == set(ids)
    assert check_pieces(got, ids) <= 0.01 * got.length.sum()
    assert got.equals(packing.pack(docs, packing.default_ranks(), block_rests=50).toPandas())


def test_special_strings_have_the_ids_of_the_tokenizer_by_default(spark):
    texts = ["one<|endoftext|>two", "<|endoftext|>", "a <|endoftext|>\n<|endoftext|> b", "<|endoftext", " <|endoftext|><|endoftext|> ", "<|ENDOFTEXT|> <|pad|> plain", "hello <|endoftext|> world", *ODD_TEXTS]
    ids = dict(enumerate(hf_ids(texts)))
    got = packing.pack(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), packing.default_ranks()).toPandas()
    assert set(got.doc_id) == set(ids) and list(ids[1]) == [50256, 0]
    check_pieces(got, ids)


def test_costs_are_balanced():
    rng = np.random.default_rng(0)
    lengths = rng.integers(1, 900, 400)
    lengths = np.append(lengths, 1024 - lengths.sum() % 1024)
    placed = packing.assign(lengths, 1024, 1.0, 1 / 1024)
    cost, fill = collections.Counter(), collections.Counter()
    for i, start, n, s, offset in placed:
        assert offset == fill[s]
        fill[s] += n
        cost[s] += n + n * n / 1024
    assert set(fill.values()) == {1024}
    in_order = collections.Counter()
    at = 0
    for n in lengths:
        while n:
            part = min(int(n), 1024 - at % 1024)
            in_order[at // 1024] += part + part * part / 1024
            at, n = at + part, n - part
    assert np.std(list(cost.values())) < np.std(list(in_order.values()))


def test_packing_odd(odd, none):
    got = packing.pack(odd.dropna(subset=["doc_id"]).dropDuplicates(["doc_id"]), packing.default_ranks()).toPandas()
    rows = {r["doc_id"]: r["text"] for r in odd.collect() if r["doc_id"] is not None}
    check_pieces(got, dict(zip(rows, hf_ids(rows.values()), strict=True)))
    assert packing.pack(odd, packing.default_ranks()).select("doc_id").count() >= odd.count()
    assert packing.pack(none, packing.default_ranks()).count() == 0
    assert packing.sequence_costs(packing.pack(odd, packing.default_ranks())).agg(F.sum("padding")).first()[0] == 0


# 9 sharding


def test_store_keeps_every_row_through_merges(spark, docs, tmp_path):
    store = sharding.ShardStore(spark, str(tmp_path), fan_in=3, base_bytes=1 << 14, file_bytes=1 << 16)
    for i in range(7):
        store.append(docs.filter(F.col("doc_id") % 7 == i))
    before, shards = store.manifest()
    assert before == 7 and len(shards) == 7
    version = store.compact()
    _, after = store.manifest()
    assert version > 7 and len(after) < 7 and not store.plan(after)
    want = sorted((r["doc_id"], r["text"]) for r in docs.collect())
    assert sorted((r["doc_id"], r["text"]) for r in store.read().collect()) == want
    held = {(r["number"], r["merges"]) for r in store.read(shard_column="shard").select("shard.*").distinct().collect()}
    assert held == {(x.number, x.merges) for x in after} and all(x.merges <= 2 for x in after)
    # every version stays whole until it is expired
    reader = store.read(before)
    assert reader.count() == len(want) and store.read(4).filter("doc_id % 7 > 3").count() == 0
    assert store.expire(2) == list(range(1, version - 1))
    assert sorted((r["doc_id"], r["text"]) for r in store.read().collect()) == want and store.read(version - 1).count() == len(want)
    live = {s.path for v in store.versions() for s in store.manifest(v)[1]}
    assert {str(tmp_path / "shards" / p.name) for p in (tmp_path / "shards").iterdir()} == live


def test_commits_do_not_overwrite_each_other(spark, docs, tmp_path):
    a, b = (sharding.ShardStore(spark, str(tmp_path)) for _ in range(2))
    a.append(docs.limit(3))
    key = a.manifest()[1][0].schema

    def slow(shards):
        if len(shards) == 1:
            b.append(docs.limit(2))  # another writer is first
        return shards + [sharding.Shard("later", 1, 9, 0, key)]

    a.commit(slow)
    version, shards = a.manifest()
    assert version == 3 and len(shards) == 3
    for name in ("orphan", "written"):  # left by a dead writer, and not yet committed by one at work
        (tmp_path / "shards" / name).mkdir()
    (tmp_path / "shards" / "written" / "part").write_text("x")
    for path in (tmp_path / "shards" / "orphan", tmp_path / "shards" / "written"):
        os.utime(path, (1, 1))
    a.sweep()
    assert not (tmp_path / "shards" / "orphan").exists() and (tmp_path / "shards" / "written").exists() and len(a.manifest(1)[1]) == 1


def test_later_columns_are_kept_and_other_types_refused(spark, tmp_path):
    store = sharding.ShardStore(spark, str(tmp_path), fan_in=2)
    store.append(spark.createDataFrame([(1, "a")], "doc_id long, text string"))
    store.append(spark.createDataFrame([(2, "b", 0.5)], "doc_id long, text string, score double"))
    store.compact()
    assert sorted(map(tuple, store.read().collect())) == [(1, "a", None), (2, "b", 0.5)]
    with pytest.raises(ValueError):
        store.append(spark.createDataFrame([("3", "c")], "doc_id string, text string"))
    assert store.read().count() == 2 and store.read(1).columns == ["doc_id", "text"]


def test_sharding_odd(odd, none, tmp_path):
    clash = odd.withColumn("arrival", F.lit("keepme")).withColumn("_arrival", F.lit("too")).withColumn("shard", F.lit(0))
    store = sharding.compacted(clash, str(tmp_path / "a"))
    got = store.read()
    assert got.columns == clash.columns and sorted(map(repr, got.collect())) == sorted(map(repr, clash.collect()))
    assert store.read(shard_column="_shard").filter("_shard.merges = 2").count() > 0
    with pytest.raises(ValueError):
        store.read(shard_column="Shard")
    store = sharding.ShardStore(none.sparkSession, str(tmp_path / "b"))
    store.append(none)
    assert store.read().count() == 0


# 10 near-duplicates


def bags(texts):
    out = []
    for s in texts:
        w = words(s)
        out.append(collections.Counter(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else collections.Counter())
    return out


def likeness(a, b):
    both = sum((a & b).values())
    return both / max(1, sum((a | b).values()))


def test_signatures_estimate_weighted_jaccard():
    rng = np.random.default_rng(3)
    h = textvec.mix(np.arange(60, dtype=np.uint64))
    wa, wb = rng.integers(1, 9, 60), rng.integers(1, 9, 60)
    got = []
    for k in range(30):
        key = textvec.mix(h + np.uint64(1000 * k))
        s = near_dup.bag_signatures(np.concatenate((key, key)), np.repeat([0, 1], 60), np.concatenate((wa, wb)), 2, 128)
        got.append((s[0] == s[1]).mean())
    assert abs(np.mean(got) - np.minimum(wa, wb).sum() / np.maximum(wa, wb).sum()) < 0.02
    assert (near_dup.bag_signatures(h[:1], np.array([1]), np.array([1]), 2, 16)[0] == 0).all()


def family(spark, n):
    """A base text, copies with few and with many words changed, exact copies, and texts of their own."""
    rng = np.random.default_rng(5)
    base = [f"w{i}" for i in rng.integers(0, 5000, 120)]
    texts = []
    for i in range(n):
        t = list(base)
        for j in rng.integers(0, 120, i % 9):
            t[j] = f"z{rng.integers(0, 9999)}"
        texts.append(" ".join(t))
    texts += texts[:5] + [" ".join(f"q{x}" for x in rng.integers(0, 10**6, 60)) for _ in range(20)]
    return texts, spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(6)


@pytest.mark.parametrize("block", [8, 256])
def test_classes_are_those_of_all_pairs(spark, block):
    texts, df = family(spark, 90)
    got = near_dup.near_duplicates(df, block=block).toPandas().set_index("doc_id").class_id
    b = bags(texts)
    top = list(range(len(texts)))

    def find(i):
        while top[i] != i:
            i = top[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            if likeness(b[i], b[j]) >= 0.8:
                assert got[i] == got[j]
                x, y = find(i), find(j)
                top[max(x, y)] = min(x, y)
    assert [got[i] for i in range(len(texts))] == [find(i) for i in range(len(texts))]


def test_components_of_a_path_and_of_nothing(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (101, 100), (7, 7)], "a long, b long")
    got = {r["node"]: r["label"] for r in components.components(edges).collect()}
    assert got == {i: 0 for i in range(41)} | {100: 100, 101: 100}
    assert components.components(edges.limit(0)).count() == 0


def test_near_duplicates_odd(odd, none):
    got = near_dup.near_duplicates(odd).toPandas()
    assert len(got) == odd.count()
    classes = {i: g.class_id.iloc[0] for i, g in got.dropna(subset=["doc_id"]).groupby("doc_id")}
    assert classes[0] == classes[1] == 0 and classes[9] == classes[10] == 9 and classes[2] == 2
    kept = near_dup.stage(None, odd, D)
    assert kept.columns == odd.columns and kept.count() == got.text_id.nunique()
    assert near_dup.near_duplicates(none).count() == 0 and near_dup.stage(None, none, D).count() == 0


def test_each_class_keeps_one_row_where_ids_are_null_or_repeated(spark, tmp_path):
    own = [" ".join(f"{c}{i}" for i in range(60)) for c in "abcdef"]
    near = own[1] + " end"
    rows = [(None, own[0]), (None, own[2]), (None, own[3]), (None, own[3]), (5, own[0] + " end"), (5, own[1]), (7, near), (5, own[4]), (5, own[4]), (9, own[5]), (None, own[5])]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    letter = lambda s: s[0]
    got = near_dup.near_duplicates(docs).toPandas()
    text_of = {hashlib.md5(s.encode()).digest(): s for _, s in rows}
    got["letter"] = [letter(text_of[bytes(x)]) for x in got.text_id]
    got["label"] = got.label.map(bytes)
    assert len(got) == len(rows) and got.label.nunique() == 6 and (got.groupby("letter").label.nunique() == 1).all()
    assert (got.class_size == got.groupby("letter").letter.transform("size")).all() and (got.groupby("letter").kept.sum() == 1).all()
    kept = sorted((r["text"], r["doc_id"]) for r in near_dup.stage(None, docs, D).collect())
    assert kept == [(own[0] + " end", 5), (own[1], 5), (own[2], None), (own[3], None), (own[4], 5), (own[5], 9)]
    out = Q.op10_near_duplicates(spark, str(tmp_path)).toPandas()
    assert out.class_key.nunique() == 6 and (out.groupby("class_key").kept.sum() == 1).all()
    assert sorted(zip(out.class_id.fillna(0), out.class_size, strict=True)) == sorted([(5, 2)] * 6 + [(0, 1)] + [(0, 2)] * 2 + [(9, 2)] * 2)


# registered queries and the pipeline


def test_pipeline_and_queries(spark):
    import corpus_pipeline

    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "toxicity", "near_duplicates", "mixing", "packing"]
    got = corpus_pipeline.run(spark, D).toPandas()
    assert len(got) and got.groupby("sequence_id").length.sum().max() <= 1024
    docs = spark.read.parquet(f"{D}/documents.parquet").toPandas().set_index("doc_id")
    assert set(got.doc_id) < set(docs.index)
    assert (got.groupby("doc_id").length.sum() <= 2 * got.groupby("doc_id").doc_tokens.first()).all()


def test_pipeline_stage_by_stage_by_brute_force(spark, tmp_path):
    """Each stage on the last one's rows: what it keeps, from plain Python; then the pieces of the whole run."""
    import corpus_pipeline

    stages = dict(corpus_pipeline.STAGES)
    docs = spark.read.parquet(f"{D}/documents.parquet")
    rows = lambda df: sorted(((r["doc_id"], r["text"], r["lang"], r["source"]) for r in df.collect()), key=lambda r: (r[0], repr(r)))
    fine = stages["quality_rules"](spark, docs, D).cache()
    kept = {r["doc_id"] for r in quality_rules.divergence_rules(docs).filter("kept").collect()}
    assert rows(fine) == [r for r in rows(docs) if r[0] in kept]
    assert all(len(words(t)) >= 10 for _, t, _, _ in rows(fine))
    clean = stages["toxicity"](spark, fine, D).cache()
    model = toxicity.fit_toxicity(fine, spark.read.parquet(f"{D}/labels.parquet"))
    score = dict(zip([r[0] for r in rows(fine)], model.score(pa.array([r[1] for r in rows(fine)])), strict=True))
    assert rows(clean) == [r for r in rows(fine) if score[r[0]] < 0.5]
    unlike = stages["near_duplicates"](spark, clean, D).cache()
    own = rows(clean)
    b = bags([r[1] for r in own])
    top = list(range(len(own)))
    for i in range(len(own)):
        for j in range(i):
            if likeness(b[i], b[j]) >= 0.8:
                x, y = top[i], top[j]
                top = [min(x, y) if t in (x, y) else t for t in top]
    assert rows(unlike) == [own[i] for i in sorted(set(top))]
    mixed = stages["mixing"](spark, unlike, D).cache()
    times = collections.Counter(r[0] for r in rows(mixed))
    size = {r[0]: len(words(r[1])) for r in rows(unlike)}
    of = {r[0]: r[3] for r in rows(unlike)}
    goal = mixing.targets({s: sum(size[i] for i in size if of[i] == s) for s in set(of.values())}, (3, 1, 2), 1.5, 2)
    for s, want in goal.items():
        assert abs(sum(times[i] * size[i] for i in size if of[i] == s) - want) <= max(size[i] for i in size if of[i] == s)
    assert max(times.values()) <= 2 and set(times) <= set(size)
    got = stages["packing"](spark, mixed, D).toPandas()
    ids = {r[0]: i for r, i in zip(rows(unlike), hf_ids([r[1] for r in rows(unlike)]), strict=True)}
    for doc, g in got.groupby("doc_id"):
        assert g.length.sum() == times[doc] * len(ids[doc]) and (g.doc_tokens == len(ids[doc])).all()
    whole = corpus_pipeline.run(spark, D).toPandas()
    assert whole.groupby("doc_id").length.sum().to_dict() == got.groupby("doc_id").length.sum().to_dict()


def test_pipeline_odd(spark, odd, docs, none, tmp_path):
    import corpus_pipeline

    shared = spark.conf.get("spark.checkpoint.dir")
    before = {x for x in os.listdir(shared) if x.startswith("stage-")}
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 5000)
    both = docs.unionByName(odd, allowMissingColumns=True).unionByName(docs.limit(40).withColumn("doc_id", F.lit(None).cast("long")), allowMissingColumns=True)
    got = corpus_pipeline.run_on(spark, both, D).toPandas()
    assert len(got) and (got.groupby("sequence_id").length.sum() <= 1024).all()
    assert len({x for x in os.listdir(shared) if x.startswith("stage-")} - before) == 1  # the rows returned
    assert spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == "5000"
    spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert corpus_pipeline.run_on(spark, none, D).count() == 0


def test_a_cluster_without_a_shared_folder_is_an_error(spark, monkeypatch):
    class Cluster:
        master = "spark://host:7077"
        _jsc = type("J", (), {"sc": lambda self: type("S", (), {"getCheckpointDir": lambda self: type("N", (), {"isDefined": lambda self: False})()})()})()

    fake = type("Session", (), {"sparkContext": Cluster(), "conf": type("C", (), {"get": lambda self, k, d=None: d})()})()
    with pytest.raises(ValueError, match="checkpoint"):
        common.shared_folder(fake)


def test_recall_of_near_duplicates_on_documents(spark):
    """Classes against all pairs of whole documents, by one product of text-item matrices."""
    d = "/root/testdata/sf0.01"
    rows = spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "text").collect()
    b = bags([r["text"] for r in rows])
    of = {}
    for i, bag in enumerate(b):
        for item, n in bag.items():
            for k in range(n):
                of.setdefault((item, k), []).append(i)
    common_items = [x for x in of.values() if len(x) > 1]
    both = np.zeros((len(rows), len(rows)), dtype=np.float32)
    for at in range(0, len(common_items), 4000):
        m = np.zeros((len(rows), len(common_items[at : at + 4000])), dtype=np.float32)
        for j, x in enumerate(common_items[at : at + 4000]):
            m[x, j] = 1
        both += m @ m.T
    size = np.array([sum(x.values()) for x in b], dtype=np.float32)
    like = both / np.maximum(size[:, None] + size[None, :] - both, 1)
    got = near_dup.near_duplicates(spark.read.parquet(f"{d}/documents.parquet")).toPandas().set_index("doc_id").class_id
    ids = np.array([r["doc_id"] for r in rows])
    left, right = np.nonzero(np.triu(like >= 0.8 - 1e-6, 1))
    found = (got[ids[left]].to_numpy() == got[ids[right]].to_numpy()).mean()
    assert len(left) > 50 and found >= 0.99
    # and no class holds texts that no chain of links joins
    top = list(range(len(rows)))
    for i, j in zip(left, right, strict=True):
        x, y = top[i], top[j]
        if x != y:
            top = [min(x, y) if t in (x, y) else t for t in top]
    texts = {}
    for i, r in enumerate(rows):
        texts.setdefault(r["text"] or "", i)
    chains = [min(top[i], top[texts[r["text"] or ""]]) for i, r in enumerate(rows)]
    assert pd.Series(chains).groupby(got[ids].to_numpy()).nunique().max() == 1


def test_sql_oracles(spark):
    import duckdb

    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.execute(f"create view {t} as select * from read_parquet('{D}/{t}.parquet')")
    for name, sql in Q.oracle_sql().items():
        got, want = Q.queries()[name](spark, D).toPandas(), con.execute(sql).df()
        cols = sorted(want.columns)
        assert sorted(got.columns) == cols
        rows = lambda f: sorted(map(repr, f[cols].astype(object).where(f[cols].notna(), None).values.tolist()))
        assert rows(got) == rows(want), name
