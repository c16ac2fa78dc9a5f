"""Joins and windows beyond Spark's plain ones, and text parsing, as compositions of DataFrame functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TOKEN = r"\p{L}+"


def micros(ts: str) -> Column:
    """Microseconds since 1970 of a timestamp with or without a zone."""
    return F.unix_micros(F.col(ts).cast("timestamp"))


def as_of_join(left: DataFrame, right: DataFrame, by: str, ts: str, value: str, name: str) -> DataFrame:
    """Each left row with the last right `value` at or before its time, by union and one window; no row pairs are made."""
    a = left.select("*", F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias(name))
    b = right.select(F.col(by), F.col(ts), F.lit(0).alias("_side"), F.col(value).alias(name))
    w = Window.partitionBy(by).orderBy(ts, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b, allowMissingColumns=True).withColumn(name, F.last(name, ignorenulls=True).over(w)).filter("_side = 1").drop("_side")


def interval_join(points: DataFrame, spans: DataFrame, at: str, start: str, end: str, width: float, by: str | None = None) -> DataFrame:
    """Points with the spans that hold them (start <= at < end), by buckets of `width` and a residual test."""
    bucket = F.floor(F.col(at).cast("double") / width)
    cover = F.explode(F.sequence(F.floor(F.col(start).cast("double") / width), F.floor(F.col(end).cast("double") / width)))
    keys = ["_bucket"] + ([by] if by else [])
    joined = points.withColumn("_bucket", bucket).join(spans.withColumn("_bucket", cover), keys)
    return joined.filter((F.col(at) >= F.col(start)) & (F.col(at) < F.col(end))).drop("_bucket")


def interval_counts(points: DataFrame, spans: DataFrame, at: str, start: str, end: str, width: float) -> DataFrame:
    """(start, end, n): of each distinct span that holds points (start <= at < end), how many; no pair is made.

    Equal points and equal spans are counted once. Both go into buckets of `width`, whose points are counted in
    order: a span holds the points of its first bucket but those before its start, those of the buckets between,
    and those of its last bucket before its end. A span without an end is an error.
    """
    bucket = lambda c: F.floor(F.nanvl(F.col(c).cast("double") / width, F.lit(float("inf"))))
    mark = lambda b, place, sign, whole: F.struct(b.alias("b"), place.alias("place"), F.lit(sign).alias("sign"), whole.alias("whole"))
    first, last = bucket("_start"), bucket("_end")
    ends = F.array(mark(first, F.col("_start"), -1, last > first), mark(last, F.col("_end"), 1, F.lit(False)))
    between = F.transform(F.sequence(first + 1, last - 1), lambda b: mark(b, F.col("_end"), 0, F.lit(True)))
    held = spans.select(F.col(start).alias("_start"), F.col(end).alias("_end")).filter("_start < _end").distinct()
    marks = held.select("_start", "_end", F.explode(F.when(last > first + 1, F.concat(ends, between)).otherwise(ends)).alias("m"))
    known = points.filter(F.col(at).isNotNull()).groupBy(F.col(at).alias("place")).agg(F.count("*").alias("n")).withColumn("b", bucket("place"))
    w = Window.partitionBy("b").orderBy("place", "n")  # a mark, whose n is 0, comes before the points at its place
    before = F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0))
    inside = F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    rows = marks.select("_start", "_end", "m.*", F.lit(0).cast("long").alias("n")).unionByName(known, allowMissingColumns=True)
    part = F.col("sign") * before + F.when(F.col("whole"), inside).otherwise(0)
    parts = rows.select("_start", "_end", "sign", part.alias("n")).filter("sign is not null")
    return parts.groupBy(F.col("_start").alias(start), F.col("_end").alias(end)).agg(F.sum("n").alias("n")).filter("n > 0")


def sessionise(events: DataFrame, by: str, ts: str, gap_s: int, tie: str) -> DataFrame:
    """Adds session_no: a new session after a pause longer than `gap_s`."""
    w = Window.partitionBy(by).orderBy(ts, tie)
    pause = micros(ts) - F.lag(micros(ts)).over(w)
    return events.withColumn("_new", F.when(pause <= gap_s * 1_000_000, 0).otherwise(1)).withColumn("session_no", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0))).drop("_new")


def sliding(events: DataFrame, value: Column, by: str, order: Column, low: int, high: int, name: str) -> DataFrame:
    """An aggregate over a range frame of `order`."""
    return events.withColumn(name, value.over(Window.partitionBy(by).orderBy(order).rangeBetween(low, high)))


def top_k(df: DataFrame, by: str, order: list[Column], k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(by).orderBy(*order))).filter(F.col("rank") <= k)


def tokens(df: DataFrame, key: list[str], text: str = "text") -> DataFrame:
    """(key, pos, token): lower-cased runs of letters."""
    return df.select(*key, F.posexplode(F.regexp_extract_all(F.lower(text), F.lit(f"({TOKEN})"), 1)).alias("pos", "token"))


def token_lists(df: DataFrame, key: list[str], least: int = 1, text: str = "text") -> DataFrame:
    """(key, ws): each text's tokens of `least` letters or more in order, as one row; texts without any have none."""
    words = F.regexp_extract_all(F.lower(text), F.lit(f"({TOKEN})"), 1)
    return df.select(*key, F.filter(words, lambda w: F.length(w) >= least).alias("ws")).filter(F.size("ws") > 0)


def sentences(df: DataFrame, key: list[str], text: str = "text") -> DataFrame:
    """(key, sent_no, sentence): parts between full stops and line ends, trimmed, not empty."""
    parts = F.posexplode(F.split(text, r"[.\n]"))
    return df.select(*key, parts.alias("sent_no", "sentence")).withColumn("sentence", F.trim("sentence")).filter("sentence <> ''")


def mentions(sents: DataFrame, key: list[str], least: int = 8) -> DataFrame:
    """Words of `least` letters or more, with their place in the sentence."""
    return tokens(sents, [*key, "sent_no"], "sentence").filter(F.length("token") >= least).withColumnRenamed("token", "word")


def candidate_pairs(m: DataFrame, key: list[str]) -> DataFrame:
    """Distinct word pairs that share a sentence, with the sentences they share and their least distance.

    Pairs are made inside each sentence's list of words, not by a self-join: the list's
    words are rows of their own first, so that no cell holds all pairs of a long sentence.
    """
    lists = m.groupBy(*key, "sent_no").agg(F.array_sort(F.collect_list(F.struct("word", "pos"))).alias("ws"))
    left = lists.select(*key, "sent_no", "ws", F.explode("ws").alias("a"))
    later = F.transform(F.filter("ws", lambda b: b["word"] > F.col("a.word")), lambda b: F.struct(F.col("a.word").alias("word_a"), b["word"].alias("word_b"), F.abs(F.col("a.pos") - b["pos"]).alias("gap")))
    one = left.select(*key, "sent_no", F.explode(later).alias("p")).groupBy(*key, "sent_no", "p.word_a", "p.word_b").agg(F.min("p.gap").alias("gap"))
    return one.groupBy("word_a", "word_b").agg(F.count("*").alias("n_sentences"), F.min("gap").alias("least_gap"))


def cooccurrence(toks: DataFrame, key: str, window: int) -> DataFrame:
    """(token, other, n): ordered pairs at most `window` places apart in a text, by leads over one window."""
    w = Window.partitionBy(key).orderBy("pos")
    near = F.array(*[F.lead("token", i).over(w) for i in range(1, window + 1)])
    pairs = toks.select("token", near.alias("near")).select("token", F.explode("near").alias("other")).filter("other is not null")
    half = pairs.groupBy("token", "other").count()
    return half.unionByName(half.select(F.col("other").alias("token"), F.col("token").alias("other"), "count")).groupBy("token", "other").agg(F.sum("count").alias("n"))


def word_shape(c: Column) -> Column:
    """Stand-in for part-of-speech tags: letters to X or x, digits to d, runs cut to one."""
    s = F.regexp_replace(F.regexp_replace(F.regexp_replace(c, r"\p{Lu}+", "X"), r"\p{Ll}+", "x"), r"\p{Nd}+", "d")
    return s


def visible_text(html: Column) -> Column:
    """A page without scripts, styles and tags, with single spaces."""
    bare = F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1>", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(bare, r"(?s)<[^>]*>", " "), r"\s+", " "))
