"""Merkle fixity audit of two replicas of a web archive.

A replica is a table of records (id, url, payload), laid out in archive files by
itself: a record's file and slot follow from the hash of its id and url, so they do
not change with its payload, and its byte offset from the records before it in that
replica. A leaf of a file's tree hashes the digests of the records in one of `SLOTS`
slots, every level above hashes `fanout` neighbours, and a node covers a range of
offsets in each replica. The replicas are compared at their roots; only nodes that
differ are looked at further down. In the slots that differ, records are matched by
id, url and digest: a lost record or a changed length moves the offsets after it, but
makes no other record look damaged.

Defined results: null urls and payloads count as empty, a null id as no id. Rows
alike in id, url and payload are one record with a number of copies. Of an id and url
with one unmatched record in either replica, that record is `damaged`. A record that
only the first replica has is `lost`, one that only the second has `extra`, and one
whose copies differ in number `recount`. Several records that share id and url (ties)
are laid out by digest too; if just one of them is changed it is damaged, of more the
old ones are lost and the new ones extra. An empty table has no files. Very long payloads are hashed whole. Columns other than these
three are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from iterspark.llm.common import cut, joined_by_key

#: Leaves of a file's tree, a power of 16.
SLOTS = 4096


def record_text(record_id: Column, url: Column, payload: Column) -> Column:
    """A WARC/1.1 resource record: header lines, the payload, two line ends."""
    body = F.coalesce(payload, F.lit(""))
    lines = [F.lit("WARC/1.1"), F.lit("WARC-Type: resource"), F.concat(F.lit("WARC-Record-ID: <urn:record:"), F.coalesce(record_id.cast("string"), F.lit("")), F.lit(">")), F.concat(F.lit("WARC-Target-URI: "), F.coalesce(url, F.lit(""))), F.concat(F.lit("Content-Length: "), F.octet_length(body).cast("string"))]
    end = F.lit("\r\n")
    return F.concat(*[x for line in lines for x in (line, end)], end, body, end, end)


def records(table: DataFrame, record_id: str = "page_id", url: str = "url", payload: str = "html") -> DataFrame:
    """(record_id, digest, identity, length, copies, key): the distinct records; `key` is what places a record."""
    text = record_text(F.col(record_id), F.col(url), F.col(payload))
    name = F.concat(F.coalesce(F.col(record_id).cast("string"), F.lit("")), F.lit("\n"), F.coalesce(F.col(url), F.lit("")))
    slim = table.select(F.col(record_id).alias("record_id"), F.sha2(name, 256).alias("identity"), F.sha2(text, 256).alias("digest"), F.octet_length(text).cast("long").alias("length"))
    one = cut(slim.groupBy("identity", "digest").agg(F.first("record_id").alias("record_id"), F.first("length").alias("length"), F.count("*").alias("copies")))
    n = one.groupBy("identity").agg(F.count("*").alias("n"))
    placed = joined_by_key(one, n, "identity", "n", one.count())
    return placed.withColumn("key", F.when(F.col("n") == 1, F.col("identity")).otherwise(F.sha2(F.concat("identity", "digest"), 256))).drop("n")


def layout(found: DataFrame, n_files: int) -> DataFrame:
    """Adds file, slot, seq and offset to records: the file from the first 32 bits of the key, the slot from the next."""
    file = F.conv(F.substring("key", 1, 8), 16, 10).cast("long") % n_files
    slot = F.conv(F.substring("key", 9, 8), 16, 10).cast("long") % SLOTS
    order = Window.partitionBy("file").orderBy("slot", "key", "digest")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    laid = found.withColumn("file", file).withColumn("slot", slot)
    return laid.withColumn("seq", F.row_number().over(order).cast("long") - 1).withColumn("offset", F.coalesce(F.sum("length").over(before), F.lit(0)))


def archive_files(laid_out: DataFrame, record: str = "record") -> DataFrame:
    """(file, content): the records of each file in order; a file holds about `per_file` records."""
    parts = F.transform(F.array_sort(F.collect_list(F.struct("seq", F.col(record).alias("r")))), lambda x: x["r"])
    return laid_out.groupBy("file").agg(F.array_join(parts, "").cast("binary").alias("content"))


def _hashed(parts: Column) -> Column:
    return F.sha2(F.array_join(F.transform(F.array_sort(parts), lambda x: x["digest"]), ""), 256)


def tree(laid: DataFrame, *, fanout: int = 16) -> list[DataFrame]:
    """Levels from the slots up to one root a file: (file, node, digest, first_byte, end_byte)."""
    span = [F.min("first_byte").alias("first_byte"), F.max("end_byte").alias("end_byte")]
    leaf = F.struct("seq", F.concat("digest", F.lit("*"), F.col("copies").cast("string")).alias("digest"))
    rows = laid.select("file", F.col("slot").alias("node"), leaf.alias("leaf"), F.col("offset").alias("first_byte"), (F.col("offset") + F.col("length")).alias("end_byte"))
    levels = [cut(rows.groupBy("file", "node").agg(_hashed(F.collect_list("leaf")).alias("digest"), *span))]
    nodes = SLOTS
    while nodes > 1:
        nodes = -(-nodes // fanout)
        up = levels[-1].groupBy("file", F.floor(F.col("node") / fanout).cast("long").alias("up")).agg(_hashed(F.collect_list(F.struct("node", "digest"))).alias("digest"), *span)
        levels.append(cut(up.withColumnRenamed("up", "node")))
    return levels


def audit(left: list[DataFrame], right: list[DataFrame], *, fanout: int = 16) -> DataFrame:
    """The slots that differ: (file, node, first_byte, end_byte, replica_first_byte, replica_end_byte)."""
    under = None
    for a, b in zip(reversed(left), reversed(right), strict=True):
        sides = []
        for nodes, name in ((a, "own"), (b, "other")):
            if under is not None:
                nodes = nodes.withColumn("up", F.floor(F.col("node") / fanout).cast("long")).join(under.select("file", F.col("node").alias("up")), ["file", "up"], "left_semi").drop("up")
            sides.append(nodes.select("file", "node", F.col("digest").alias(name), F.col("first_byte").alias(f"first_{name}"), F.col("end_byte").alias(f"end_{name}")))
        bad = sides[0].join(sides[1], ["file", "node"], "full").filter(~F.col("own").eqNullSafe(F.col("other")))
        under = cut(bad.select("file", "node", F.col("first_own").alias("first_byte"), F.col("end_own").alias("end_byte"), F.col("first_other").alias("replica_first_byte"), F.col("end_other").alias("replica_end_byte")))
    return under


def compare(pages: DataFrame, replica: DataFrame, *, record_id: str = "page_id", url: str = "url", payload: str = "html", per_file: int = 1024, fanout: int = 16) -> DataFrame:
    """record_id, file, seq, offset, length, copies, sha256, replica_offset, replica_sha256, state.

    A row for each record of either replica. `file` to `sha256` are null for extra
    records, `replica_offset` and `replica_sha256` for lost ones.
    """
    columns = {"record_id": record_id, "url": url, "payload": payload}
    own, other = (records(t, **columns) for t in (pages, replica))
    n_files = max(1, -(-own.count() // per_file))
    own, other = cut(layout(own, n_files)), cut(layout(other, n_files))
    slots = audit(tree(own, fanout=fanout), tree(other, fanout=fanout), fanout=fanout).select("file", F.col("node").alias("slot"))
    a = own.join(slots, ["file", "slot"], "left_semi").select("identity", "digest", "record_id", "copies")
    b = other.join(slots, ["file", "slot"], "left_semi").select("identity", "digest", F.col("record_id").alias("other_id"), F.col("offset").alias("replica_offset"), F.col("copies").alias("replica_copies"))
    both = cut(a.join(b, ["identity", "digest"], "full"))
    lone = both.filter("copies is null or replica_copies is null")
    # an id and url with one unmatched record on either side: the same record with another payload
    sides = lone.groupBy("identity").agg(F.count("copies").alias("lost"), F.count("replica_copies").alias("extra"), *[F.max(F.when(F.col("replica_copies").isNotNull(), F.col(c))).alias(n) for c, n in (("digest", "found"), ("replica_offset", "at"))]).filter("lost = 1 and extra = 1")
    pairs = cut(sides.select("identity", "found", "at"))
    changed = lone.filter("copies is not null").join(pairs, "identity", "left").select("identity", "digest", F.col("at").alias("bad_at"), F.col("found").alias("bad_digest"), F.when(F.col("found").isNull(), "lost").otherwise("damaged").alias("bad"))
    recount = both.filter("copies <> replica_copies").select("identity", "digest", F.col("replica_offset").alias("bad_at"), F.col("digest").alias("bad_digest"), F.lit("recount").alias("bad"))
    sound = other.select("identity", "digest", F.col("offset").alias("sound_at"))
    rows = own.join(changed.union(recount), ["identity", "digest"], "left").join(sound, ["identity", "digest"], "left")
    state = F.coalesce("bad", F.lit("sound"))
    rows = rows.select("record_id", "file", "seq", "offset", "length", "copies", F.col("digest").alias("sha256"), F.coalesce("bad_at", "sound_at").alias("replica_offset"), F.when(state == "sound", F.col("digest")).otherwise(F.col("bad_digest")).alias("replica_sha256"), state.alias("state"))
    extra = lone.filter("copies is null").join(pairs, "identity", "left_anti")
    none = [F.lit(None).cast(rows.schema[c].dataType).alias(c) for c in ("file", "seq", "offset", "length", "copies", "sha256")]
    return rows.unionByName(extra.select(F.col("other_id").alias("record_id"), *none, "replica_offset", F.col("digest").alias("replica_sha256"), F.lit("extra").alias("state")))
