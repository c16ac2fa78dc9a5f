"""Near-duplicates by BagMinHash signatures, bands and exact verification.

A text is the multiset of its shingles of five words. Each shingle owns Poisson
processes over the dyadic levels of a weight axis, [0,1), [1,2), [2,4), ...; a
point has a time, a register and a weight, and counts for a text whose (whole)
weight of that shingle lies above the point's. A register holds the earliest
point that counts, so two texts agree in a register with a probability equal to
their weighted Jaccard similarity. Points are made in order of time and only up to a
horizon by which the registers are filled; texts with a register left empty go on
to a later horizon, so the signature is exact.

Texts that agree in all registers of a band share a bucket. Every candidate link
is verified on the whole multisets. First each text of a bucket is compared with
the bucket's least text. Where a bucket then still holds more than one class, the
texts outside its largest class are compared in blocks of `block` by `block` with
those of its texts that their distances to the least text do not rule out; only links
that join classes come back. So no link between texts that share a bucket is lost, no
list of pairs is made, and a task's memory is bounded. Classes are the connected
components. Exact copies are collapsed before all this and joined again at the end.

No task holds all rows of a hot text, bucket or class: few keys can hold a large part
of the rows, and these are joined by broadcast; bags that many rows meet are copied
and the rows dealt over the copies.

Defined results: a null text counts as empty. Texts without words have no
shingles; they are alike only if they are the same text. Repeated rows are all
returned, in one class. A class is known by its least text_id (`label`), which no
other class has. Its class_id is its least doc_id (null if all its ids are null), which
other classes have too where ids are null or repeated. Just one row of each class is
`kept`: of the least id, then the least text_id. An empty table gives an empty table. Very long texts are used whole. Columns other
than the id and the text are not read; `stage` carries them.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from iterspark.llm.common import cut, joined_by_key, parked, release, short_batches
from iterspark.llm.components import components
from iterspark.llm.textvec import blocks, counted, mix, shingles, tidy, unit, words

#: Cells of distance to a bucket's leader.
_CELLS = 16
_STEP, _LEVEL = np.uint64(0xD1342543DE82EF95), np.uint64(0x2545F4914F6CDD1D)


def bag_signatures(hashes: np.ndarray, docs: np.ndarray, weights: np.ndarray, n_docs: int, registers: int) -> np.ndarray:
    """n_docs x registers, 64-bit; zeros for texts without shingles. Weights are whole numbers above 0."""
    best = np.full((n_docs, registers), np.inf)
    if len(hashes):
        total = np.bincount(docs, weights=weights, minlength=n_docs)
        levels = 1 + np.ceil(np.log2(weights)).astype(np.int64)  # 1: one level, 2: two, 3 and 4: three, ...
        at = np.repeat(np.arange(len(hashes)), levels)
        level = np.arange(len(at)) - np.repeat(np.cumsum(levels) - levels, levels)
        low = np.where(level == 0, 0.0, 2.0 ** (level - 1))
        width = np.maximum(low, 1.0)
        key, doc, weight = mix(hashes[at] + level.astype(np.uint64) * _LEVEL), docs[at], weights[at]
        horizon = np.where(total > 0, registers * (np.log(registers) + 3) / np.maximum(total, 1), 0.0)
        todo = total > 0
        while todo.any():
            use = np.flatnonzero(todo[doc])
            time, point = np.zeros(len(use)), 0
            while len(use):
                seed = mix(key[use] + np.uint64(point * int(_STEP) % 2**64))
                time = time - np.log(unit(seed)) / width[use]
                live = time <= horizon[doc[use]]
                use, time, seed = use[live], time[live], seed[live]
                place = mix(seed ^ _LEVEL)
                counts = (level[use] == 0) | (low[use] + width[use] * unit(mix(seed ^ _STEP)) < weight[use])
                cell = doc[use] * registers + (place % np.uint64(registers)).astype(np.int64)
                np.minimum.at(best.reshape(-1), cell[counts], time[counts])
                point += 1
            todo &= np.isinf(best).any(axis=1)
            best[todo] = np.inf
            horizon = np.where(todo, horizon * 2, horizon)
    return np.where(np.isinf(best), np.uint64(0), mix(best.view(np.uint64)))


def multisets(column: pa.Array, size: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray, int]]:
    """Of each block: number of its first text, hashes, text numbers, multiplicities, texts."""
    for block in blocks(column):
        h, d, n = counted(*shingles(words(block), size))
        yield block.first, h, d, n, len(block.bounds) - 1


def signature_table(docs: DataFrame, *, bands: int, rows: int, size: int) -> DataFrame:
    """(doc_id, text_id, keys): a key for each band, none for texts without words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys, has = [], []
            for _, h, d, n, texts in multisets(b.column("text"), size):
                sig = bag_signatures(h, d, n, texts, bands * rows).reshape(texts, bands, rows)
                key = np.broadcast_to(np.arange(bands, dtype=np.uint64), (texts, bands)).copy()
                for r in range(rows):
                    key = mix(key * np.uint64(3) + sig[:, :, r])
                keys.append(key.view(np.int64))
                has.append(np.bincount(d, minlength=texts) > 0)
            keys, has = (np.concatenate(keys), np.concatenate(has)) if keys else (np.zeros((0, bands), dtype=np.int64), np.zeros(0, dtype=bool))
            ends = np.concatenate(([0], np.cumsum(np.where(has, bands, 0)))).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(keys[has].reshape(-1)))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("text_id"), lists], names=["doc_id", "text_id", "keys"])

    return docs.mapInArrow(run, "doc_id long, text_id binary, keys array<long>")


def shingle_table(texts: DataFrame, size: int) -> DataFrame:
    """(text_id, bag): the k-th copy of a shingle is an item of its own; items are sorted 32-bit hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for _, h, d, n, count in multisets(b.column("text"), size):
                at = np.repeat(np.arange(len(h)), n)
                copy = np.arange(len(at)) - np.repeat(np.cumsum(n) - n, n)
                item = (mix(h[at] + copy.astype(np.uint64) * _STEP) >> np.uint64(32)).astype(np.uint32)
                ends = np.searchsorted(d[at], np.arange(count + 1))
                out += [np.sort(item[ends[i] : ends[i + 1]]).tobytes() for i in range(count)]
            yield pa.RecordBatch.from_arrays([b.column("text_id"), pa.array(out, pa.binary())], names=["text_id", "bag"])

    return texts.select("text_id", "text").mapInArrow(run, "text_id binary, bag binary")


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Weighted Jaccard similarity of two bags."""
    both = np.concatenate((a, b))
    both.sort(kind="stable")
    common = int(np.count_nonzero(both[1:] == both[:-1]))
    return common / max(len(both) - common, 1)


def _salted(bags: DataFrame, wanted: DataFrame) -> DataFrame:
    """Bags with `salt`, copied as often as `wanted` (text_id, salts) says; rows that meet a bag are dealt over its salts."""
    most = wanted.groupBy("text_id").agg(F.max("salts").alias("salts"))
    return bags.join(most, "text_id").withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).drop("salts")


def _salts(n: Column, spark) -> Column:
    """How many parts `n` rows are dealt to: of 64 rows each, four for a task at the most."""
    return F.greatest(F.least(F.ceil(n / 64), F.lit(4 * int(spark.conf.get("spark.sql.shuffle.partitions")))), F.lit(1)).cast("int")


def _star_likeness(members: DataFrame, bags: DataFrame) -> DataFrame:
    """(a, b, like): of each text of a bucket, b, its likeness to the bucket's leader, a."""
    pairs = members.filter("text_id <> leader").groupBy(F.col("leader").alias("a"), F.col("text_id").alias("b")).agg(F.max("n").alias("n"))
    pairs = pairs.withColumn("salts", _salts(F.col("n"), members.sparkSession)).withColumn("salt", F.pmod(F.xxhash64("b"), F.col("salts")).cast("int"))
    member = bags.select(F.col("text_id").alias("b"), F.col("bag").alias("bag_b"))
    leader = _salted(bags, pairs.select(F.col("a").alias("text_id"), "salts")).select(F.col("text_id").alias("a"), "salt", F.col("bag").alias("bag_a"))
    joined = pairs.join(member, "b").join(leader, ["a", "salt"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in batches:
            x, y = t.column("bag_a"), t.column("bag_b")
            like = [likeness(np.frombuffer(p.as_py(), np.uint32), np.frombuffer(q.as_py(), np.uint32)) for p, q in zip(x, y, strict=True)]
            yield pa.RecordBatch.from_arrays([t.column("a"), t.column("b"), pa.array(like, pa.float64())], names=["a", "b", "like"])

    return joined.select("a", "b", "bag_a", "bag_b").mapInArrow(run, "a binary, b binary, like double")


def _common(left: list[np.ndarray], right: list[np.ndarray], chunk: int = 4096) -> np.ndarray:
    """Numbers of common items of all pairs."""
    out = np.zeros((len(left), len(right)), dtype=np.float32)
    items = np.intersect1d(np.concatenate(left), np.concatenate(right))
    for i in range(0, len(items), chunk):
        part = items[i : i + chunk]
        sides = []
        for bags in (left, right):
            m = np.zeros((len(bags), len(part)), dtype=np.float32)
            for k, bag in enumerate(bags):
                lo, hi = np.searchsorted(bag, (part[0], part[-1]), side="left")
                own = bag[lo : hi + 1]
                at = np.searchsorted(part, own)
                hit = at < len(part)
                hit[hit] = part[at[hit]] == own[hit]
                m[k, at[hit]] = 1
            sides.append(m)
        out += sides[0] @ sides[1].T
    return out


def _verify_blocks(members: DataFrame, stars: DataFrame, bags: DataFrame, least: float, block: int) -> DataFrame:
    """Links (a, b) between labels of classes inside buckets. `members`: (bucket, n, leader, text_id, label).

    Distance (1 - likeness) is a metric, so two texts whose distances to the leader
    differ by more than 1 - `least` are no link. Texts are counted by cells of that
    distance; those that no other text is near enough to are left out. The others are
    dealt to blocks by hash, and blocks of texts outside the largest class meet all blocks.
    """
    spark, reach = members.sparkSession, math.floor((1 - least) * _CELLS + 1e-9) + 1
    by_label = members.groupBy("bucket", "label").agg(F.count("*").alias("n"))
    main = by_label.groupBy("bucket").agg(F.max(F.struct("n", "label")).alias("m"), F.sum("n").alias("size"), F.count("*").alias("labels")).filter("labels > 1 and size > 2")
    main = cut(main.select("bucket", F.col("m.label").alias("main"), "size"))
    total, largest = main.agg(F.sum("size"), F.max("size")).first()
    if not total:
        return spark.createDataFrame([], "a binary, b binary")
    near = stars.select(F.col("a").alias("leader"), F.col("b").alias("text_id"), "like")
    cell = F.floor((1 - F.coalesce("like", F.lit(1.0))) * _CELLS).cast("int")
    rows = joined_by_key(members, main, "bucket", "size", total, largest).join(near, ["leader", "text_id"], "left")
    rows = parked(rows.select("bucket", "size", "text_id", "label", (F.col("label") != F.col("main")).alias("outside"), cell.alias("cell")), "inside")
    counts = rows.groupBy("bucket", "cell").agg(F.count("*").alias("n"), F.count_if("outside").alias("o"), F.first("size").alias("size"))
    cells = counts.groupBy("bucket").agg(F.first("size").alias("size"), F.collect_list(F.struct("cell", "n", "o")).alias("cells"))

    def others(c: Column, count: str, within: str = "cells") -> Column:
        """Whether a cell within reach of `c` holds a text other than one in `c` itself."""
        return F.exists(within, lambda x: (F.abs(x["cell"] - c) <= reach) & (x[count] > F.when(x["cell"] == c, 1).otherwise(0)))

    # texts outside the largest class that some text is near, then texts that some of these are near
    live = F.filter("cells", lambda x: (x["o"] > 0) & others(x["cell"], "n"))
    met = F.filter("cells", lambda x: F.exists("live", lambda y: F.abs(y["cell"] - x["cell"]) <= reach))
    count = lambda column, field: F.ceil(F.aggregate(column, F.lit(0).cast("long"), lambda s, x: s + x[field]) / block).cast("int")
    cells = cells.withColumn("live", live).filter(F.size("live") > 0).withColumn("met", met).withColumn("ob", count("live", "o")).withColumn("nb", count("met", "n"))
    rows = joined_by_key(rows.drop("size"), parked(cells, "cells"), "bucket", "size", total, largest)
    holds = lambda column: F.exists(column, lambda x: x["cell"] == F.col("cell"))

    def side(kept: DataFrame, mine: str, other: str, outside: bool) -> DataFrame:
        spread = kept.select("bucket", "text_id", "label", F.pmod(F.xxhash64("text_id"), F.col(mine)).cast("int").alias("own"), F.col(other).alias("blocks"), _salts(F.col(other), spark).alias("salts"))
        each = spread.select("bucket", "text_id", "label", "salts", "own", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
        pair = (F.col("own").alias("o"), F.col("other").alias("m")) if outside else (F.col("other").alias("o"), F.col("own").alias("m"))
        return each.select("bucket", *pair, F.lit(outside).alias("outside"), "text_id", "label", "salts", F.pmod(F.xxhash64("bucket", "other"), F.col("salts")).cast("int").alias("salt"))

    dealt = side(rows.filter(F.col("outside") & holds("live")), "ob", "nb", True).union(side(rows.filter(holds("met")), "nb", "ob", False))
    dealt = dealt.join(_salted(bags, dealt.select("text_id", "salts")), ["text_id", "salt"]).select("bucket", "o", "m", "outside", "label", "bag")

    def run(table: pa.Table) -> pa.Table:
        side = np.array(table.column("outside").to_pylist(), dtype=bool)
        labels = table.column("label").to_pylist()
        bags_ = [np.frombuffer(x, np.uint32) for x in table.column("bag").to_pylist()]
        left, right = np.flatnonzero(side), np.flatnonzero(~side)
        a: list[bytes] = []
        b: list[bytes] = []
        if len(left) and len(right):
            size = np.array([len(x) for x in bags_], dtype=float)
            common = _common([bags_[i] for i in left], [bags_[i] for i in right])
            alike = common >= least * (size[left][:, None] + size[right][None, :] - common) - 1e-6
            joined = {x: x for x in labels}

            def top(x: bytes) -> bytes:
                while joined[x] != x:
                    joined[x] = x = joined[joined[x]]
                return x

            for i, j in zip(*np.nonzero(alike), strict=True):
                p, q = top(labels[left[i]]), top(labels[right[j]])
                if p != q:
                    joined[p] = q
                    a.append(labels[left[i]])
                    b.append(labels[right[j]])
        tidy()
        return pa.table({"a": pa.array(a, pa.binary()), "b": pa.array(b, pa.binary())})

    return dealt.groupBy("bucket", "o", "m").applyInArrow(run, "a binary, b binary")


def _identified(docs: DataFrame, doc_id: str, text: str) -> DataFrame:
    whole = F.coalesce(F.col(text), F.lit(""))
    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.unhex(F.md5(whole)).alias("text_id"), whole.alias("text"))


def _row_key(text_id: Column, doc_id: Column) -> Column:
    return F.struct(text_id.alias("t"), F.coalesce(doc_id, F.lit(0)).alias("i"), doc_id.isNull().alias("n"))


def near_duplicates(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", least: float = 0.8, size: int = 5, bands: int = 20, rows: int = 6, block: int = 256) -> DataFrame:
    """doc_id, class_id, class_size (rows), text_id, label, kept: a row for each row of `docs`."""
    found = _identified(docs, doc_id, text)
    signed = parked(signature_table(found, bands=bands, rows=rows, size=size).withColumn("row", F.monotonically_increasing_id()), "signatures")
    # null ids come last
    least_row = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row")).alias("first")
    texts = signed.groupBy("text_id").agg(least_row, F.count("*").alias("copies"), F.any_value("keys").alias("keys"))
    texts = parked(texts.select("text_id", F.col("first.doc_id").alias("first_id"), F.col("first.row").alias("first_row"), "copies", "keys"), "texts")
    n_texts, n_rows, most_copies = texts.agg(F.count("*"), F.coalesce(F.sum("copies"), F.lit(0)), F.coalesce(F.max("copies"), F.lit(0))).first()
    # a key holds its band's number, so keys of two bands are not alike
    keyed = texts.select("text_id", F.explode("keys").alias("bucket"))
    member_of = F.xxhash64(F.lit(5), "text_id").cast("decimal(20,0)")
    buckets = keyed.groupBy("bucket").agg(F.count("*").alias("n"), F.min("text_id").alias("leader"), F.sum(member_of).alias("who")).filter("n > 1")
    # bands often make the same bucket again; one of them is enough
    buckets = cut(buckets.groupBy("n", "leader", "who").agg(F.min("bucket").alias("bucket")).select("bucket", "leader", "n"))
    n_members, largest = buckets.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.max("n"), F.lit(0))).first()
    members = parked(joined_by_key(keyed, buckets, "bucket", "n", n_members, largest).select("bucket", "n", "leader", "text_id"), "members")
    wanted = members.select("text_id").distinct().join(texts.select("text_id", "first_id", "copies"), "text_id")
    of_first = joined_by_key(found.withColumn("_k", _row_key(F.col("text_id"), F.col("doc_id"))), wanted.select(_row_key(F.col("text_id"), F.col("first_id")).alias("_k"), "copies"), "_k", "copies", n_rows, most_copies)
    bags = parked(shingle_table(of_first, size).dropDuplicates(["text_id"]), "bags")
    release(docs.sparkSession)
    stars = parked(_star_likeness(members, bags), "stars")
    links = stars.filter(F.col("like") >= least).select("a", "b")
    labels = cut(components(links))
    inside = members.filter("n > 2").join(labels, members["text_id"] == labels["node"], "left").select("bucket", "n", "leader", "text_id", F.coalesce("label", "text_id").alias("label"))
    more = cut(_verify_blocks(inside, stars, bags, least, block))
    release(docs.sparkSession)
    classes = texts.join(labels, texts["text_id"] == labels["node"], "left").select("text_id", "first_id", "first_row", "copies", F.coalesce("label", "text_id").alias("label"))
    if not more.isEmpty():  # links between labels; the least label of a component is its least text, too
        tops = components(more).select(F.col("node").alias("label"), F.col("label").alias("top"))
        sizes = parked(classes.groupBy("label").agg(F.count("*").alias("texts")).join(tops, "label", "left"), "tops")
        classes = joined_by_key(parked(classes, "classes"), sizes, "label", "texts", n_texts).select("text_id", "first_id", "first_row", "copies", F.coalesce("top", "label").alias("label"))
    classes = parked(classes, "classes")
    least_text = F.min(F.struct(F.col("first_id").isNull().alias("none"), "first_id", "text_id", "first_row")).alias("first")
    whole = classes.groupBy("label").agg(least_text, F.sum("copies").alias("class_size"), F.count("*").alias("texts"))
    whole = whole.select("label", F.col("first.first_id").alias("class_id"), F.col("first.first_row").alias("kept_row"), "class_size", "texts")
    of_text = parked(joined_by_key(classes.select("text_id", "copies", "label"), whole, "label", "texts", n_texts).drop("texts"), "of_text")
    out = joined_by_key(signed.select("doc_id", "text_id", "row"), of_text, "text_id", "copies", n_rows, most_copies)
    return out.select("doc_id", "class_id", "class_size", "text_id", "label", (F.col("row") == F.col("kept_row")).alias("kept"))


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class, the one with the least id (of several, the least text_id); all columns."""
    short_batches(spark or docs.sparkSession)
    found = near_duplicates(docs).filter("kept")
    keep = parked(found.select(_row_key(F.col("text_id"), F.col("doc_id")).alias("_k"), "class_size"), "kept")
    rows, largest = keep.agg(F.coalesce(F.sum("class_size"), F.lit(0)), F.coalesce(F.max("class_size"), F.lit(0))).first()
    own = docs.select(F.struct("*").alias("_row"), _row_key(F.unhex(F.md5(F.coalesce("text", F.lit("")))), F.col("doc_id").cast("long")).alias("_k"))
    return joined_by_key(own, keep, "_k", "class_size", rows, largest).dropDuplicates(["_k"]).select("_row.*")
