"""URL rules by a sort-merge range join over reversed-host keys.

The canonical key of a host is its labels in reverse, each ended by a dot
(`www.example.org` gives `org.example.www.`), so a rule's host with all its
subdomains is an interval of keys. Urls and rules are sorted by key and swept
together; a stack holds the rule hosts whose intervals are open, each nested in
the one below. Paths of one host are intervals too, each linked to the one it
is nested in. The longest rule (host and path) wins; at equal length the
longer host.

Rules are sent to all tasks while they are at most `broadcast_rules`, and each batch
of urls enters the sorted rules where its first key belongs. More rules are swept in
two distributed merges, the first of the distinct hosts with the rules' hosts, the
second of the distinct (rule host, path) with the rules of that host. In either, keys
of both sides are dealt to ranges between quantiles, sorted in each range and read
once; a range starts with the intervals that its lower bound lies in. Keys are
distinct, so a hot host or url makes no range larger than others. Both ways give the
same result.

Defined results: a null url, or one without `://`, has an empty host and path and
fits no rule. Repeated rows are judged each. Null rules are left out; of rules
alike in host and path, block beats allow. No rule: verdict `default`. Urls may
be of any length. Columns other than the id and the url are not read.
"""

from __future__ import annotations

import math
from bisect import bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StringType, StructField, StructType

from iterspark.llm.common import joined_by_key, parked

Rule = tuple[str, str, str]  # host, path, verdict

#: The rules of the contract query.
RULES: list[Rule] = [("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block")]


def host_of(url: Column) -> Column:
    """After the first `://` up to `/`, `?`, `#` or the end; A-Z lower-cased."""
    rest = F.substring_index(_after(url), "/", 1)
    return F.translate(F.substring_index(F.substring_index(rest, "?", 1), "#", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def _after(url: Column) -> Column:
    return F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url))).otherwise(F.lit(""))


def with_host_and_path(df: DataFrame, url: str = "url") -> DataFrame:
    df = df.withColumn("host", F.coalesce(host_of(F.col(url)), F.lit("")))
    df = df.withColumn("_rest", F.coalesce(F.substring_index(F.substring_index(_after(F.col(url)), "?", 1), "#", 1), F.lit("")))
    slash = F.instr("_rest", "/")
    return df.withColumn("path", F.when(slash > 0, F.substring(F.col("_rest"), slash, F.length("_rest"))).otherwise(F.lit(""))).drop("_rest")


def key_of(host: str) -> str:
    return ".".join(reversed(host.split("."))) + "."


#: Rules passed over at once rather than one by one.
_FAR = 64


def outer_intervals(keys: list[str]) -> list[int]:
    """Of each of the sorted keys, the place of the longest other that it starts with, or -1."""
    out: list[int] = []
    open_: list[int] = []
    for i, k in enumerate(keys):
        while open_ and not k.startswith(keys[open_[-1]]):
            open_.pop()
        out.append(open_[-1] if open_ else -1)
        open_.append(i)
    return out


def chain(outer: list[int], i: int) -> list[int]:
    """The place and all it is nested in, the outermost first."""
    out = []
    while i >= 0:
        out.append(i)
        i = outer[i]
    return out[::-1]


class _Paths:
    """The path rules of one host: sorted, each with the rule it is nested in."""

    def __init__(self, rules: list[tuple[str, str]]):
        best: dict[str, str] = {}
        for path, verdict in rules:
            best[path] = "block" if "block" in (verdict, best.get(path)) else verdict
        self.paths = sorted(best)
        self.verdicts = [best[p] for p in self.paths]
        self.outer = outer_intervals(self.paths)

    def longest(self, path: str) -> int:
        i = bisect_right(self.paths, path) - 1
        while i >= 0 and not path.startswith(self.paths[i]):
            i = self.outer[i]
        return i


class Sweep:
    """Rules sorted by key; `run` merges sorted url keys with them."""

    def __init__(self, rules: list[Rule]):
        by_host: dict[str, list[tuple[str, str]]] = {}
        for host, path, verdict in rules:
            if host is not None and path is not None and verdict is not None:
                by_host.setdefault(host.lower(), []).append((path, verdict))
        self.hosts = sorted((key_of(h), h, _Paths(r)) for h, r in by_host.items())
        self.keys = [k for k, _, _ in self.hosts]
        self.outer = outer_intervals(self.keys)

    def run(self, hosts: list[str], paths: list[str], default: str) -> tuple[list[str | None], list[str]]:
        keys = [key_of(h) if h else "" for h in hosts]
        order = sorted(range(len(keys)), key=keys.__getitem__)
        rule: list[str | None] = [None] * len(keys)
        verdict = [default] * len(keys)
        open_: list[int] = []
        at = 0
        for i in order:
            key = keys[i]
            to = bisect_right(self.keys, key, at)
            if to - at > _FAR:  # none of the intervals passed over is open but those around the last
                open_, at = chain(self.outer, to - 1), to
            for at in range(at, to):  # noqa: B020
                while open_ and not self.keys[at].startswith(self.keys[open_[-1]]):
                    open_.pop()
                open_.append(at)
            at = to
            while open_ and not key.startswith(self.keys[open_[-1]]):
                open_.pop()
            best = -1
            for k in reversed(open_):
                _, host, own = self.hosts[k]
                j = own.longest(paths[i])
                if j >= 0 and len(host) + len(own.paths[j]) > best:
                    best = len(host) + len(own.paths[j])
                    rule[i], verdict[i] = host + own.paths[j], own.verdicts[j]
        return rule, verdict


def _sweep_batches(batches: Iterator[pa.RecordBatch], sweep: Sweep, default: str) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rule, verdict = sweep.run(b.column("host").to_pylist(), b.column("path").to_pylist(), default)
        yield pa.RecordBatch.from_arrays([*b.columns, pa.array(rule, pa.string()), pa.array(verdict, pa.string())], names=[*b.schema.names, "rule", "verdict"])


def judge_urls(
    pages: DataFrame,
    rules: list[Rule] | DataFrame,
    *,
    page_id: str = "page_id",
    url: str = "url",
    default: str = "allow",
    broadcast_rules: int = 200_000,
    ranges: int | None = None,
) -> DataFrame:
    """page_id, host, path, rule (null where none fits) and verdict, a row for each url.

    `rules`: a list, or a table (host, path, verdict) of any size. `ranges`: of the keys, where rules
    are many; by default as many as there are shuffle partitions.
    """
    spark = pages.sparkSession
    found = with_host_and_path(pages.select(page_id, url), url).select(page_id, "host", "path")
    schema = StructType([*found.schema.fields, StructField("rule", StringType()), StructField("verdict", StringType())])
    if isinstance(rules, list):
        if len(rules) <= broadcast_rules:
            return _by_broadcast(found, rules, schema, default)
        rules = spark.createDataFrame(rules, "host string, path string, verdict string")
    rows = rules.select("host", "path", "verdict").limit(broadcast_rules + 1).collect()
    if len(rows) <= broadcast_rules:
        return _by_broadcast(found, [tuple(r) for r in rows], schema, default)
    return _by_ranges(found, rules, default, page_id, ranges or int(spark.conf.get("spark.sql.shuffle.partitions")))


def _by_broadcast(found: DataFrame, rules: list[Rule], schema, default: str) -> DataFrame:
    shared = found.sparkSession.sparkContext.broadcast(rules)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return _sweep_batches(batches, Sweep(shared.value), default)

    return found.mapInArrow(run, schema)


def _bounds(keys: DataFrame, ranges: int, a_range: int = 64) -> list[str]:
    """At most `ranges` - 1 ascending quantiles of the column `key`, from a sample by hash of about `a_range` keys for each range."""
    n = keys.count()
    share = min(1.0, ranges * a_range / max(n, 1))
    picked = sorted(r[0] for r in keys.filter(F.pmod(F.xxhash64("key"), F.lit(1 << 20)) < math.ceil(share * (1 << 20))).select("key").collect())
    return sorted({picked[len(picked) * i // ranges] for i in range(1, ranges)}) if picked else []


def dealt(rows: DataFrame, bounds: list[str]) -> DataFrame:
    """`rows` with `range`, the number of bounds at or below `key`."""
    shared = rows.sparkSession.sparkContext.broadcast(bounds)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.append_column("range", pa.array([bisect_right(shared.value, k) for k in b.column("key").to_pylist()], pa.int32()))

    return rows.mapInArrow(run, StructType([*rows.schema.fields, StructField("range", IntegerType())]))


def _starts(rules: DataFrame, bounds: list[str]) -> dict[int, list[tuple[str, str]]]:
    """Of each range but the first, the rules (key, what) whose interval its lower bound lies in; these nest, so they are few."""
    shared = rules.sparkSession.sparkContext.broadcast(bounds)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[tuple] = []
            for k, what in zip(b.column("key").to_pylist(), b.column("what").to_pylist(), strict=True):
                for i in range(bisect_right(shared.value, k), len(shared.value)):
                    if not shared.value[i].startswith(k):
                        break
                    out.append((i + 1, k, what))
            cols = list(zip(*out, strict=True)) or [[], [], []]
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), pa.array(cols[1], pa.string()), pa.array(cols[2], pa.string())], names=["range", "key", "what"])

    found: dict[int, list[tuple[str, str]]] = {}
    for r in rules.select("key", "what").mapInArrow(run, "range int, key string, what string").collect():
        found.setdefault(r["range"], []).append((r["key"], r["what"]))
    return {i: sorted(x) for i, x in found.items()}


def swept(keys: DataFrame, rules: DataFrame, ranges: int) -> DataFrame:
    """(key, found): of each of the distinct `key`s, the `what`s of all rules whose key it starts with, the longest first.

    `rules`: (key, what) with distinct keys.
    """
    both = rules.select("key", "what", F.lit(0).alias("side")).union(keys.select("key", F.lit(None).cast("string").alias("what"), F.lit(1).alias("side")))
    bounds = _bounds(both.select("key"), ranges)
    starts = both.sparkSession.sparkContext.broadcast(_starts(rules, bounds))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, open_ = 0, []
        for b in batches:
            out_keys, out_found = [], []
            for at, key, what, side in zip(*(b.column(c).to_pylist() for c in ("range", "key", "what", "side")), strict=True):
                if at != now:
                    now, open_ = at, list(starts.value.get(at, ()))
                while open_ and not key.startswith(open_[-1][0]):
                    open_.pop()
                if side == 0:
                    open_.append((key, what))
                else:
                    out_keys.append(key)
                    out_found.append([w for _, w in reversed(open_)])
            yield pa.RecordBatch.from_arrays([pa.array(out_keys, pa.string()), pa.array(out_found, pa.list_(pa.string()))], names=["key", "found"])

    sorted_ = dealt(both, bounds).repartition(ranges, "range").sortWithinPartitions("range", "key", "side")
    return sorted_.mapInArrow(run, "key string, found array<string>")


def _by_ranges(found: DataFrame, rules: DataFrame, default: str, page_id: str, ranges: int) -> DataFrame:
    host_key = F.concat(F.array_join(F.reverse(F.split("host", r"\.")), "."), F.lit("."))
    lower = F.lower("host").alias("host")
    # of rules alike, block beats allow
    rules = parked(rules.dropna().groupBy(lower, "path").agg(F.max("verdict").alias("any"), F.max(F.when(F.col("verdict") == "block", "block")).alias("block")).select("host", "path", F.coalesce("block", "any").alias("verdict")), "rules")
    urls = parked(found.groupBy("host", "path").agg(F.count("*").alias("n")), "urls")
    total = urls.agg(F.sum("n")).first()[0] or 0
    hosts = urls.filter("host <> ''").groupBy("host").agg(F.count("*").alias("paths"))
    rule_hosts = rules.select("host").distinct().select(host_key.alias("key"), F.col("host").alias("what"))
    by_host = parked(swept(hosts.select(host_key.alias("key")), rule_hosts, ranges).filter(F.size("found") > 0), "hosts")
    by_host = parked(hosts.withColumn("key", host_key).join(by_host, "key").select("host", "paths", "found"), "hosts")
    n_urls = by_host.agg(F.sum("paths")).first()[0] or 0
    # no host and no path holds a zero, so (rule host, path) pairs nest as their paths do
    pair = lambda h, p: F.concat(h, F.lit("\x00"), p)
    met = joined_by_key(urls, by_host, "host", "paths", n_urls).select("host", "path", F.explode("found").alias("rule_host"))
    met = parked(met.withColumn("key", pair(F.col("rule_host"), F.col("path"))), "met")
    by_path = swept(met.select("key").distinct(), rules.select(pair(F.col("host"), F.col("path")).alias("key"), F.concat("verdict", F.lit("\x00"), "path").alias("what")), ranges)
    by_path = by_path.filter(F.size("found") > 0).select("key", F.element_at("found", 1).alias("what"))
    # a key is met by as many urls as there are hosts with that path below the rule's host
    keyed = met.groupBy("key").agg(F.count("*").alias("m")).join(by_path, "key")
    best = joined_by_key(met, parked(keyed, "paths"), "key", "m", met.count())
    verdict = F.substring_index("what", "\x00", 1)
    rule_path = F.substring(F.col("what"), F.length(verdict) + 2, F.length("what"))
    order = F.struct((F.length("rule_host") + F.length(rule_path)).alias("whole"), F.length("rule_host").alias("part"), F.concat("rule_host", rule_path).alias("rule"), verdict.alias("verdict"))
    best = best.groupBy("host", "path").agg(F.max(order).alias("b"))
    judged = urls.join(best, ["host", "path"], "left").select(F.struct("host", "path").alias("_url"), F.col("n").alias("_n"), F.col("b.rule").alias("rule"), F.coalesce("b.verdict", F.lit(default)).alias("verdict"))
    out = joined_by_key(found.withColumn("_url", F.struct("host", "path")), parked(judged, "judged"), "_url", "_n", total)
    return out.select(page_id, "host", "path", "rule", "verdict")
