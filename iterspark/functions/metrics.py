"""Measures over iteration logs, plans and predictions."""

from __future__ import annotations

import threading

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def cumulative(log: DataFrame) -> DataFrame:
    """(workload, policy, iteration, cumulative_s): the mean over runs of the time up to each iteration."""
    wall = F.col("prep_s") + F.col("learn_s") + F.col("post_s") + F.col("materialize_s")
    per_run = log.withColumn("c", F.sum(wall).over(Window.partitionBy("workload", "policy", "run").orderBy("iteration")))
    return per_run.groupBy("workload", "policy", "iteration").agg(F.avg("c").alias("cumulative_s"))


def iteration_times(log: DataFrame) -> DataFrame:
    """The mean time of each phase by iteration."""
    return log.groupBy("workload", "policy", "iteration").agg(*[F.avg(c).alias(c) for c in ("prep_s", "learn_s", "post_s", "materialize_s")])


def speedup(log: DataFrame, base: str, other: str) -> DataFrame:
    """(workload, speedup): last cumulative time of `base` over that of `other`."""
    last = cumulative(log).groupBy("workload", "policy").agg(F.max_by("cumulative_s", "iteration").alias("s"))
    a, b = (last.filter(F.col("policy") == p).select("workload", F.col("s").alias(n)) for p, n in ((base, "a"), (other, "b")))
    return a.join(b, "workload").select("workload", (F.col("a") / F.col("b")).alias("speedup"))


def storage(log: DataFrame) -> DataFrame:
    return log.groupBy("workload", "policy", "iteration").agg((F.avg("store_bytes") / 1024).alias("store_kb"))


def storage_ratio(log: DataFrame, a: str, b: str) -> DataFrame:
    last = storage(log).groupBy("workload", "policy").agg(F.max_by("store_kb", "iteration").alias("kb"))
    x, y = (last.filter(F.col("policy") == p).select("workload", F.col("kb").alias(n)) for p, n in ((a, "x"), (b, "y")))
    return x.join(y, "workload").select("workload", (F.col("x") / F.col("y")).alias("ratio"))


def state_shares(log: DataFrame) -> DataFrame:
    whole = F.col("n_prune") + F.col("n_load") + F.col("n_compute")
    return log.filter("run = 1").select("workload", "policy", "iteration", *[(F.col(f"n_{s}") / whole).alias(f"{s}_share") for s in ("prune", "load", "compute")])


def same_reuse(a: dict[str, str], b: dict[str, str]) -> list[str]:
    """Nodes whose states differ."""
    return sorted(n for n in a.keys() | b.keys() if a.get(n) != b.get(n))


def overhead(log: DataFrame, policy: str, base: str) -> DataFrame:
    return speedup(log, policy, base).withColumnRenamed("speedup", "overhead")


def content_hash(df: DataFrame) -> tuple[int, str]:
    """Rows, and a sum of row hashes that no order changes."""
    r = df.select(F.xxhash64(*df.columns).cast("decimal(38,0)").alias("h")).agg(F.count("*"), F.sum("h")).first()
    return r[0], str(r[1])


def accuracy(pred: DataFrame, label: str, prediction: str) -> DataFrame:
    return pred.agg(F.avg((F.col(label) == F.col(prediction)).cast("double")).alias("accuracy"))


def precision_recall_f1(pred: DataFrame, label: str, prediction: str) -> DataFrame:
    tp, fp, fn = (F.sum(F.when(c, 1).otherwise(0)) for c in ((F.col(label) == 1) & (F.col(prediction) == 1), (F.col(label) != 1) & (F.col(prediction) == 1), (F.col(label) == 1) & (F.col(prediction) != 1)))
    return pred.agg(tp.alias("tp"), fp.alias("fp"), fn.alias("fn")).select((F.col("tp") / (F.col("tp") + F.col("fp"))).alias("precision"), (F.col("tp") / (F.col("tp") + F.col("fn"))).alias("recall"), (2 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn"))).alias("f1"))


def confusion(pred: DataFrame, label: str, prediction: str) -> DataFrame:
    return pred.groupBy(F.col(label).alias("label"), F.col(prediction).alias("prediction")).agg(F.count("*").alias("n"))


def cluster_purity(df: DataFrame, cluster: str, label: str) -> DataFrame:
    best = df.groupBy(cluster, label).count().groupBy(cluster).agg(F.max("count").alias("top"), F.sum("count").alias("all"))
    return best.agg((F.sum("top") / F.sum("all")).alias("purity"))


def within_cluster_cost(df: DataFrame, vector: str, cluster: str, dims: int) -> DataFrame:
    """(cluster, n, cost): squared distances to the cluster's mean, in one map-side combined pass: the squares less what the mean explains."""
    places = [F.get(vector, F.lit(i)).cast("double") for i in range(dims)]
    square = F.aggregate(F.transform(vector, lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda s, x: s + x)
    sums = df.groupBy(F.col(cluster).alias("cluster")).agg(F.count("*").alias("n"), F.sum(square).alias("_square"), F.array(*[F.sum(x) for x in places]).alias("_sums"))
    explained = F.aggregate(F.transform("_sums", lambda x: x * x), F.lit(0.0), lambda s, x: s + x) / F.col("n")
    return sums.select("cluster", "n", F.greatest(F.col("_square") - explained, F.lit(0.0)).alias("cost"))


class MemorySampler:
    """Peak and mean resident bytes of this process and all below it, sampled each `period_s`."""

    def __init__(self, period_s: float = 1.0):
        self.period, self.samples, self._stop = period_s, [], threading.Event()

    def __enter__(self) -> MemorySampler:
        self._thread = threading.Thread(target=self._watch, daemon=True)
        self._thread.start()
        return self

    def _watch(self) -> None:
        import psutil

        me = psutil.Process()
        while True:
            total = 0
            for p in [me, *me.children(recursive=True)]:
                try:
                    total += p.memory_info().rss
                except psutil.Error:
                    pass
            self.samples.append(total)
            if self._stop.wait(self.period):
                return

    def __exit__(self, *_: object) -> None:
        self._stop.set()
        self._thread.join()

    @property
    def peak(self) -> int:
        return max(self.samples, default=0)

    @property
    def average(self) -> float:
        return sum(self.samples) / max(len(self.samples), 1)


def job_counts(spark, group: str) -> dict[str, int]:
    """Jobs, stages and tasks of a job group so far."""
    tracker = spark.sparkContext.statusTracker()
    jobs = tracker.getJobIdsForGroup(group)
    stages = [s for j in jobs if (i := tracker.getJobInfo(j)) for s in i.stageIds]
    infos = [i for s in stages if (i := tracker.getStageInfo(s))]
    return {"jobs": len(jobs), "stages": len(stages), "tasks": sum(i.numTasks for i in infos)}
