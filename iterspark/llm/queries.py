"""The registered queries of this subpackage, and SQL where it can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from iterspark.llm import fingerprints, fixity, mixing, near_dup, packing, quality_classifier, quality_rules, sharding, toxicity, url_filter
from iterspark.llm.common import fresh_path, table


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


#: What befalls the second replica, by page_id modulo these: the first character lost, the record lost, one more record.
_DAMAGE, _LOSS, _EXTRA = 97, 89, 83


def _second_replica(pages: DataFrame) -> DataFrame:
    damaged = F.when(F.col("page_id") % _DAMAGE == 13, F.substring("html", 2, 2_000_000_000)).otherwise(F.col("html"))
    held = pages.select("page_id", "url", "html").filter(F.coalesce(F.col("page_id") % _LOSS != 5, F.lit(True)))
    more = pages.filter(F.col("page_id") % _EXTRA == 7).select((-1 - F.col("page_id")).alias("page_id"), "url", "html")
    return held.select("page_id", "url", damaged.alias("html")).union(more)


def op2_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    numbers = ["file", "seq", "offset", "length", "copies", "replica_offset"]  # -1 where a replica has no such record
    return fixity.compare(pages, _second_replica(pages)).fillna(-1, numbers).withColumnRenamed("record_id", "page_id")


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_classifier.classify_quality(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge_urls(table(spark, sf_dir, "pages"), url_filter.RULES)


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score_toxicity(docs, toxicity.fit_toxicity(docs, table(spark, sf_dir, "labels")))


def op6_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.fingerprint_documents(table(spark, sf_dir, "documents"))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.divergence_rules(table(spark, sf_dir, "documents")).drop("lang")


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), packing.default_ranks())


def op9_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    store = sharding.compacted(table(spark, sf_dir, "documents"), fresh_path(spark, "shards"))
    store.expire(1)
    rows = store.read(shard_column="shard").select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), F.sha2("text", 256).alias("text_sha256"), "shard")
    live = store.manifest()[1]
    return rows.select("doc_id", "n_bytes", "text_sha256", F.col("shard.number").alias("shard"), F.col("shard.merges").alias("merges"), F.lit(len(live)).alias("live_shards"))


def op10_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(table(spark, sf_dir, "documents")).select("doc_id", "class_id", "class_size", F.lower(F.hex("label")).alias("class_key"), "kept")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_mixing, op2_fixity, op3_quality, op4_url_rules, op5_toxicity, op6_fingerprints, op7_quality_rules, op8_packing, op9_sharding, op10_near_duplicates)}


def _fixity_sql(per_file: int = 1024) -> str:
    """For distinct (page_id, url), as in the given pages."""
    end = "chr(13) || chr(10)"

    def side(name: str, rows: str) -> str:
        return f"""{name}0 AS (
  SELECT page_id, sha256(coalesce(page_id::VARCHAR, '') || chr(10) || coalesce(url, '')) AS k,
    'WARC/1.1' || {end} || 'WARC-Type: resource' || {end} || 'WARC-Record-ID: <urn:record:' || coalesce(page_id::VARCHAR, '') || '>' || {end} || 'WARC-Target-URI: ' || coalesce(url, '') || {end}
      || 'Content-Length: ' || strlen(coalesce(html, '')) || {end} || {end} || coalesce(html, '') || {end} || {end} AS record FROM ({rows})
), {name} AS (
  SELECT *, row_number() OVER w - 1 AS seq, CAST(coalesce(sum(length) OVER (PARTITION BY file ORDER BY slot, k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS "offset"
  FROM (SELECT min(page_id) AS page_id, k, sha256(record) AS sha256, min(strlen(record)) AS length, count(*) AS copies, CAST('0x' || substr(k, 1, 8) AS BIGINT) % (SELECT n FROM files) AS file,
               CAST('0x' || substr(k, 9, 8) AS BIGINT) % {fixity.SLOTS} AS slot FROM {name}0 GROUP BY k, record) WINDOW w AS (PARTITION BY file ORDER BY slot, k)
)"""

    second = f"""SELECT page_id, url, CASE WHEN page_id % {_DAMAGE} = 13 THEN substr(html, 2) ELSE html END AS html FROM pages WHERE page_id % {_LOSS} <> 5
    UNION ALL SELECT -1 - page_id, url, html FROM pages WHERE page_id % {_EXTRA} = 7"""
    return f"""
WITH files AS (SELECT greatest(1, CAST(ceil(count(DISTINCT (page_id, url)) / {per_file}.0) AS BIGINT)) AS n FROM pages),
{side("a", "SELECT page_id, url, html FROM pages")}, {side("b", second)}
SELECT coalesce(a.page_id, b.page_id) AS page_id, coalesce(a.file, -1) AS file, coalesce(a.seq, -1) AS seq, coalesce(a."offset", -1) AS "offset", coalesce(a.length, -1) AS length,
       coalesce(a.copies, -1) AS copies, a.sha256, coalesce(b."offset", -1) AS replica_offset, b.sha256 AS replica_sha256,
       CASE WHEN a.k IS NULL THEN 'extra' WHEN b.k IS NULL THEN 'lost' WHEN a.sha256 <> b.sha256 THEN 'damaged' ELSE 'sound' END AS state
FROM a FULL JOIN b ON a.k = b.k"""


def _url_sql() -> str:
    rules = ", ".join(f"('{h}', '{p}', '{v}')" for h, p, v in url_filter.RULES)
    return f"""
WITH rules(rhost, rpath, verdict) AS (VALUES {rules}),
a AS (
  SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages
), b AS (
  SELECT page_id, lower(regexp_extract(rest, '^[^/?#]*')) AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM a
), m AS (
  SELECT b.*, rhost || rpath AS rule, r.verdict,
         row_number() OVER (PARTITION BY page_id ORDER BY length(rhost || rpath) DESC NULLS LAST, length(rhost) DESC) AS k
  FROM b LEFT JOIN rules r ON (b.host = rhost OR suffix(b.host, '.' || rhost)) AND starts_with(b.path, rpath)
)
SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM m WHERE k = 1"""


def oracle_sql() -> dict[str, str]:
    return {
        "op2_fixity": _fixity_sql(),
        "op4_url_rules": _url_sql(),
        # tables whose arrivals are all below four megabytes, in tier 0: the first four are merged, and then with three more
        "op9_sharding": "SELECT doc_id, CAST(strlen(text) AS BIGINT) AS n_bytes, sha256(text) AS text_sha256, CASE WHEN doc_id % 8 = 7 THEN 7 ELSE 0 END AS shard, CASE WHEN doc_id % 8 = 7 THEN 0 ELSE 2 END AS merges, 2 AS live_shards FROM documents",
    }
