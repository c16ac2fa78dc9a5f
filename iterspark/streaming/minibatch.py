"""Workflows over mini-batches: what to keep is measured and decided on the first batch, then repeated."""

from __future__ import annotations

import json
import time
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from iterspark.plans.dag import Dag
from iterspark.plans.keep import OnlineKeep, cumulative_time
from iterspark.plans.reuse import COMPUTE
from iterspark.plans.store import CostModel, Files


class StreamRunner:
    """`steps`: (name, parents, function of the parents' frames); the first has no parents and gets the batch.

    Kept steps are appended for each batch under `root/kept/<step>/batch=<id>`; a
    batch that is run again overwrites its own part. Decisions survive a restart.
    """

    def __init__(self, spark: SparkSession, root: str, steps: list[tuple[str, list[str], Callable]], outputs: list[str], budget_bytes: int = 10 * 10**9, cost: CostModel | None = None):
        self.spark, self.root, self.steps, self.outputs, self.budget = spark, root.rstrip("/"), steps, outputs, budget_bytes
        self.cost, self.files = cost or CostModel(), Files(spark, root)
        self.dag = Dag.from_edges([s[0] for s in steps], [(p, n) for n, ps, _ in steps for p in ps])

    @property
    def decision(self) -> dict | None:
        return json.loads(self.files.get("decision.json")) if self.files.exists("decision.json") else None

    def on_batch(self, batch: DataFrame, batch_id: int) -> None:
        chosen, values, took = self.decision, {}, {}
        for name, parents, fn in self.steps:
            began = time.perf_counter()
            values[name] = fn(*[values[p] for p in parents]) if parents else fn(batch)
            if chosen is None:
                values[name] = values[name].persist()
                values[name].write.format("noop").mode("overwrite").save()
                took[name] = time.perf_counter() - began
        if chosen is None:
            size = {n: float(str(v._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) / 3 for n, v in values.items()}
            micro = {n: round(t * 1e6) for n, t in took.items()}
            total = cumulative_time(self.dag, dict.fromkeys(self.dag.nodes, COMPUTE), micro, micro)
            rule = OnlineKeep(self.budget)
            for n in self.dag.order():
                rule.decide(n, total[n], self.cost.load_s(size[n]) * 1e6, int(size[n]), self.cost.write_s(size[n]) * 1e6)
            chosen = {"keep": sorted(rule.kept), "first_batch": batch_id, "seconds": took}
            self.files.put("decision.json", json.dumps(chosen))
        for n in sorted(set(chosen["keep"]) | set(self.outputs)):
            values[n].write.mode("overwrite").parquet(f"{self.root}/kept/{n}/batch={batch_id}")
        for v in values.values():
            v.unpersist()

    def start(self, stream: DataFrame, checkpoint: str):
        """Takes all that is there, in batches, and stops."""
        return stream.writeStream.foreachBatch(self.on_batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()

    def read(self, step: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.root}/kept/{step}")


def _timed(events: DataFrame, late: str | None) -> DataFrame:
    """With a watermark, which needs a time with a zone: times without one are read in the session's."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late) if late else events


def tumbling_counts(events: DataFrame, width: str = "1 hour", late: str | None = None) -> DataFrame:
    """(window_start, event_type, n, total); the same for a stream and for a batch."""
    events = _timed(events, late)
    out = events.groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return out.select(F.col("window.start").alias("window_start"), "event_type", "n", "total")


def sliding_counts(events: DataFrame, width: str = "2 hours", step: str = "1 hour", late: str | None = None) -> DataFrame:
    events = _timed(events, late)
    return events.groupBy(F.window("ts", width, step), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("window_start"), "event_type", "n")


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str | None = None) -> DataFrame:
    events = _timed(events, late)
    return events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("session_start"), "user_id", "n")


def deduplicated(events: DataFrame, key: str, late: str = "1 hour") -> DataFrame:
    return _timed(events, late).dropDuplicatesWithinWatermark([key])


def replayed(spark: SparkSession, source: str, folder: str, parts: int) -> DataFrame:
    """A batch table as a file stream: its rows in time order, in `parts` files."""
    df = spark.read.parquet(source)
    if not Files(spark, folder).exists("_SUCCESS"):
        df.repartitionByRange(parts, "ts").sortWithinPartitions("ts").write.mode("overwrite").parquet(folder)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(folder)


def enriched(events: DataFrame, static: DataFrame, on: str, columns: list[str]) -> DataFrame:
    """A stream with columns of a batch table, matched by one key."""
    return events.join(static.select(on, *columns), on)


def running_totals(events: DataFrame, by: str, value: str) -> DataFrame:
    """(by, n, total) so far, after each batch, for the keys that it holds; a custom state for each key.

    The state is two numbers; a key's rows come in chunks, so none is held whole.
    """

    def fold(key, chunks, state):
        n, total = state.get if state.exists else (0, 0.0)
        for c in chunks:
            n, total = n + len(c), total + float(c[value].sum())
        state.update((n, total))
        yield pd.DataFrame({by: [key[0]], "n": [n], "total": [total]})

    schema = f"{by} {events.schema[by].dataType.simpleString()}, n long, total double"
    return events.select(by, value).groupBy(by).applyInPandasWithState(fold, schema, "n long, total double", "update", GroupStateTimeout.NoTimeout)


def drained(stream: DataFrame, folder: str, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there and reads what it gave; `batch` tells rows of one batch from another's.

    A batch that is run again overwrites its own rows. `complete` keeps the last batch's result only.
    """

    def save(rows: DataFrame, batch_id: int) -> None:
        rows.write.mode("overwrite").parquet(f"{folder}/rows/batch={0 if mode == 'complete' else batch_id}")

    job = stream.writeStream.outputMode(mode).foreachBatch(save).option("checkpointLocation", f"{folder}/progress").trigger(availableNow=True).start()
    job.awaitTermination()
    return stream.sparkSession.read.parquet(f"{folder}/rows")
