"""Size-tiered compaction of immutable shards under a versioned manifest.

A store is a folder with `shards/` and `manifests/`. A shard is a folder of Parquet
files that is never changed. A manifest names the live shards with their columns; the
highest version counts. A commit writes a file of its own and renames it to the next
version's name, which fails if another writer has taken it; the loser reads the new
manifest and tries again. A shard's tier is the whole logarithm, base `fan_in`, of its
size over `base_bytes`. Where a tier holds `fan_in` shards, the oldest are merged into
one, in files of about `file_bytes`, and go to the tier above; so a row is written
again once for each tier.

Readers take a manifest's paths, so they see a whole version, also while shards are
merged: `compact` removes nothing. `expire` drops all but the last `retain` versions,
and shards that none of these names. `sweep` removes what dead writers have left,
folders that no version names and that have not been touched for `grace_s` seconds;
a writer at work is younger than that.

Defined results: nulls and texts of any length are kept as they are, repeated rows
each, and ties do not arise. An empty arrival makes a shard without rows. All columns
are kept, whatever their names: a version has every column that one of its shards has,
null in the rows of the others. An arrival whose column has another type than the
store's is an error and changes nothing.
"""

from __future__ import annotations

import hashlib
import json
import math
import time
import uuid
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from iterspark.llm.common import remove


@dataclass(frozen=True)
class Shard:
    path: str
    bytes: int
    number: int  # order of arrival; of a merged shard, its oldest part's
    merges: int = 0
    schema: str = ""  # its key in the manifest's schemas


def free_name(columns: list[str], wanted: str) -> str:
    """`wanted`, or with underscores before it where the columns hold that (in any case)."""
    taken = {c.lower() for c in columns}
    while wanted.lower() in taken:
        wanted = f"_{wanted}"
    return wanted


class ShardStore:
    def __init__(self, spark: SparkSession, root: str, *, fan_in: int = 4, base_bytes: int = 1 << 20, file_bytes: int = 64 << 20, retain: int = 10, grace_s: float = 86_400.0):
        self.spark, self.root, self.fan_in, self.base_bytes, self.file_bytes, self.retain, self.grace_s = spark, root.rstrip("/"), fan_in, base_bytes, file_bytes, retain, grace_s
        jvm = spark.sparkContext._jvm
        self._path = jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(root).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        for folder in ("manifests", "shards"):
            self._fs.mkdirs(self._path(f"{self.root}/{folder}"))

    # manifests

    def versions(self) -> list[int]:
        names = [s.getPath().getName() for s in self._fs.listStatus(self._path(f"{self.root}/manifests"))]
        return sorted(int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json"))

    def _read(self, version: int | None = None) -> tuple[int, list[Shard], dict[str, str]]:
        known = self.versions()
        if version is None:
            if not known:
                return 0, [], {}
            version = known[-1]
        stream = self._fs.open(self._path(self._name(version)))
        try:
            found = json.loads(self.spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()
        return version, [Shard(**x) for x in found["shards"]], found["schemas"]

    def manifest(self, version: int | None = None) -> tuple[int, list[Shard]]:
        return self._read(version)[:2]

    def _name(self, version: int) -> str:
        return f"{self.root}/manifests/v{version:010d}.json"

    def commit(self, change, schemas: dict[str, str] | None = None, tries: int = 20) -> int:
        """Replace the shards by `change(shards)`; tried again when another writer was first."""
        for _ in range(tries):
            version, shards, known = self._read()
            now = change(shards)
            known = {k: v for k, v in (known | (schemas or {})).items() if k in {s.schema for s in now}}
            merged_schema(known.values())
            own = self._path(f"{self.root}/manifests/{uuid.uuid4().hex}.tmp")
            out = self._fs.create(own, True)
            out.write(bytearray(json.dumps({"shards": [asdict(s) for s in now], "schemas": known}).encode()))
            out.close()
            target = self._path(self._name(version + 1))
            if not self._fs.exists(target) and self._fs.rename(own, target):
                return version + 1
            self._fs.delete(own, False)
        raise RuntimeError("other writers were always first")

    # shards

    def _bytes(self, path: str) -> int:
        return self._fs.getContentSummary(self._path(path)).getLength()

    def _fresh(self) -> str:
        return f"{self.root}/shards/{uuid.uuid4().hex}"

    def append(self, arrival: DataFrame) -> int:
        self._check(arrival.schema)
        path = self._fresh()
        arrival.write.parquet(path)
        return self.add([path], arrival.schema)

    def append_split(self, rows: DataFrame, by) -> int:
        """Rows of each value of the expression `by` as an arrival of its own, in one job."""
        self._check(rows.schema)
        path, part = self._fresh(), free_name(rows.columns, "_arrival")
        rows.withColumn(part, by).write.partitionBy(part).parquet(path)
        found = [s.getPath() for s in self._fs.listStatus(self._path(path)) if s.isDirectory()]
        return self.add([f"{path}/{p.getName()}" for p in sorted(found, key=lambda p: p.getName())], rows.schema)

    def _check(self, schema: StructType) -> None:
        merged_schema([*self._read()[2].values(), schema.json()])

    def add(self, paths: list[str], schema: StructType) -> int:
        text = schema.json()
        key = hashlib.sha256(text.encode()).hexdigest()[:16]
        sized = [(p, self._bytes(p)) for p in paths]

        def change(shards: list[Shard]) -> list[Shard]:
            start = 1 + max((s.number for s in shards), default=-1)
            return shards + [Shard(p, n, start + i, 0, key) for i, (p, n) in enumerate(sized)]

        return self.commit(change, {key: text})

    def tier(self, shard: Shard) -> int:
        return max(0, math.floor(math.log(max(shard.bytes, 1) / self.base_bytes, self.fan_in))) if shard.bytes > self.base_bytes else 0

    def plan(self, shards: list[Shard]) -> list[Shard]:
        """The next shards to merge, of the lowest tier that is full; none if none is."""
        tiers: dict[int, list[Shard]] = {}
        for s in shards:
            tiers.setdefault(self.tier(s), []).append(s)
        for _, own in sorted(tiers.items()):
            if len(own) >= self.fan_in:
                return sorted(own, key=lambda s: s.number)[: self.fan_in]
        return []

    def compact(self) -> int:
        """Merge until no tier is full; the version reached."""
        version, shards, schemas = self._read()
        while chosen := self.plan(shards):
            path, schema = self._fresh(), merged_schema(schemas[s.schema] for s in chosen)
            files = max(1, -(-sum(s.bytes for s in chosen) // self.file_bytes))
            self.spark.read.schema(schema).parquet(*[s.path for s in chosen]).coalesce(files).write.parquet(path)
            text = schema.json()
            merged = Shard(path, self._bytes(path), min(s.number for s in chosen), 1 + max(s.merges for s in chosen), hashlib.sha256(text.encode()).hexdigest()[:16])

            def change(now: list[Shard], chosen: list[Shard] = chosen, merged: Shard = merged) -> list[Shard]:
                if not set(chosen) <= set(now):
                    raise RuntimeError("another writer merged these shards")
                return [s for s in now if s not in chosen] + [merged]

            version = self.commit(change, {merged.schema: text})
            _, shards, schemas = self._read()
        return version

    # leftovers

    def _tops(self, versions: list[int]) -> dict[str, set[str]]:
        """Of the given versions, the folders below shards/ that they name, each with the paths used of it."""
        out: dict[str, set[str]] = {}
        for v in versions:
            for s in self.manifest(v)[1]:
                tail = s.path.removeprefix(f"{self.root}/shards/").split("/")
                out.setdefault(tail[0], set()).add(s.path)
        return out

    def expire(self, retain: int | None = None) -> list[int]:
        """Keep the last `retain` versions and what they name; returns the versions dropped."""
        known = self.versions()
        old = known[: -max(1, self.retain if retain is None else retain)]
        dead, live = self._tops(old), self._tops([v for v in known if v not in old])
        for v in old:
            self._fs.delete(self._path(self._name(v)), False)
        for top, paths in dead.items():
            for path in [f"{self.root}/shards/{top}"] if top not in live else paths - live[top]:
                remove(self.spark, path)
        return old

    def sweep(self) -> None:
        """Remove folders and unfinished manifests that no version names, if nothing in them is younger than `grace_s`."""
        live = self._tops(self.versions())
        for folder, named in (("shards", live), ("manifests", {f"v{v:010d}.json" for v in self.versions()})):
            for status in self._fs.listStatus(self._path(f"{self.root}/{folder}")):
                if status.getPath().getName() not in named and time.time() - self._touched(status) > self.grace_s:
                    self._fs.delete(status.getPath(), True)

    def _touched(self, status) -> float:
        own = status.getModificationTime() / 1000
        return max([own, *[self._touched(s) for s in self._fs.listStatus(status.getPath())]]) if status.isDirectory() else own

    # readers

    def read(self, version: int | None = None, *, shard_column: str | None = None) -> DataFrame:
        """Rows of a version. With `shard_column`, a struct (number, merges) of the shard that holds each row."""
        _, shards, schemas = self._read(version)
        if not shards:
            raise ValueError("the store has no shards")
        schema = merged_schema(schemas[s.schema] for s in shards)
        rows = self.spark.read.schema(schema).parquet(*[s.path for s in shards])
        if shard_column is None:
            return rows
        if shard_column.lower() in {c.lower() for c in rows.columns}:
            raise ValueError(f"the store has a column {shard_column}")
        # one row for each shard of the manifest, which the driver holds anyway
        names = {s.path.removeprefix(f"{self.root}/shards/"): (s.number, s.merges) for s in shards}
        key = free_name(rows.columns, "_folder")
        known = self.spark.createDataFrame([(k, v) for k, v in names.items()], f"{key} string, {shard_column} struct<number:int,merges:int>")
        folder = F.regexp_extract(F.input_file_name(), r"/shards/([0-9a-f]{32}(?:/_+arrival=[^/]+)?)/[^/]+$", 1)
        return rows.withColumn(key, folder).join(F.broadcast(known), key).drop(key)


def merged_schema(schemas) -> StructType:
    """Every column of the schemas (JSON), in order of first sight; a column of two types is an error."""
    out: dict[str, object] = {}
    for text in schemas:
        for f in StructType.fromJson(json.loads(text)).fields:
            known = out.setdefault(f.name.lower(), f)
            if known.dataType.simpleString() != f.dataType.simpleString():
                raise ValueError(f"column {f.name}: {known.dataType.simpleString()} and {f.dataType.simpleString()}")
    schema = StructType()
    for f in out.values():
        schema.add(f.name, f.dataType, True)
    return schema


def compacted(docs: DataFrame, root: str, *, arrivals: int = 8, doc_id: str = "doc_id", **options) -> ShardStore:
    """A store at `root` of `docs` in `arrivals` shards by id, compacted."""
    store = ShardStore(docs.sparkSession, root, **options)
    store.append_split(docs, F.pmod(F.coalesce(F.col(doc_id), F.lit(0)), F.lit(arrivals)).cast("int"))
    store.compact()
    return store
