"""The experiments: workloads under policies, and what is measured of them."""

from __future__ import annotations

import time

from pyspark.sql import SparkSession

from iterspark.functions.metrics import MemorySampler, same_reuse
from iterspark.plans.session import Policy, Session
from iterspark.plans.store import Files
from iterspark.registry import work_folder
from iterspark.workloads import digit_vectors, entity_clusters, library_parity, pair_extraction, price_class

WORKLOADS = {
    "price_class": (lambda d, i: price_class.price_class(f"{d}/lineitem.parquet", i), len(price_class.EDITS)),
    "price_class_10x": (lambda d, i: price_class.price_class(f"{d}/lineitem.parquet", i, copies=10), len(price_class.EDITS)),
    "entity_clusters": (lambda d, i: entity_clusters.entity_clusters(d, i), len(entity_clusters.EDITS)),
    "pair_extraction": (lambda d, i: pair_extraction.pair_extraction(d, i), len(pair_extraction.EDITS)),
    "digit_vectors": (lambda d, i: digit_vectors.digit_vectors(d, i), len(digit_vectors.EDITS)),
    "library_parity": (lambda d, i: library_parity.library_parity(d, i), len(library_parity.EDITS)),
}
POLICIES = {"optimal": Policy.optimal, "one_shot": Policy.one_shot, "one_shot_uncached": lambda: Policy.one_shot(False), "keep_all": Policy.keep_all, "keep_none": Policy.keep_none, "dump_rerun": Policy.dump_rerun}

#: Which systems can run which workload as it stands: all edits, prep edits only, or not.
SUPPORT = {
    "optimal": dict.fromkeys(("price_class", "entity_clusters", "pair_extraction", "digit_vectors"), "all"),
    "one_shot": {"price_class": "all", "entity_clusters": "all", "pair_extraction": "all", "digit_vectors": "all"},
    "dump_rerun": {"price_class": "prep", "entity_clusters": "none", "pair_extraction": "all", "digit_vectors": "none"},
}


def run(spark: SparkSession, sf_dir: str, workload: str, policy: str, iterations: int | None = None, run_no: int = 1, limit_s: float | None = None) -> dict:
    """Records of all iterations, plans, and memory. Stops once `limit_s` is used up (not finished)."""
    make, n = WORKLOADS[workload]
    root = work_folder(spark)
    out: dict = {"workload": workload, "policy": policy, "run": run_no, "records": [], "states": [], "finished": True}
    try:
        session, began = Session(spark, root, POLICIES[policy]()), time.perf_counter()
        with MemorySampler() as memory:
            for i in range(iterations or n):
                if limit_s is not None and time.perf_counter() - began > limit_s:
                    out["finished"] = False
                    break
                try:
                    res = session.run(make(sf_dir, i))
                except ValueError:  # a policy that takes prep edits only
                    break
                out["records"].append(res.record)
                out["states"].append(res.states)
                spark.catalog.clearCache()
        out |= {"seconds": sum(r["wall_s"] for r in out["records"]), "peak_bytes": memory.peak, "average_bytes": memory.average}
    finally:
        Files(spark, root).delete("")
    return out


def compared(spark: SparkSession, sf_dir: str, workload: str, policies: list[str], iterations: int | None = None, runs: int = 1) -> dict:
    """Mean cumulative seconds, speed-up over each policy, storage ratio, and whether plans agree with keep_all's."""
    got = {p: [run(spark, sf_dir, workload, p, iterations, k + 1) for k in range(runs)] for p in policies}
    mean = {p: sum(x["seconds"] for x in xs) / runs for p, xs in got.items()}
    out: dict = {"seconds": {p: round(v, 2) for p, v in mean.items()}, "by_iteration": {p: [round(r["wall_s"], 2) for r in xs[0]["records"]] for p, xs in got.items()}}
    out["speedup"] = {p: round(v / mean["optimal"], 2) for p, v in mean.items() if p != "optimal" and len(got[p][0]["records"]) == len(got["optimal"][0]["records"])}
    if "keep_all" in got:
        a, b = got["optimal"][0], got["keep_all"][0]
        out["storage_share"] = round(a["records"][-1]["store_bytes"] / max(b["records"][-1]["store_bytes"], 1), 3)
        out["same_states"] = all(not same_reuse(x, y) for x, y in zip(a["states"], b["states"], strict=False))
    return out


def main(arguments: list[str] | None = None) -> None:
    """One workload under one policy as one JSON line.

    For cluster scaling, run it once for each number of workers: under `spark-submit
    --num-executors N`, or here with `--master local[N]`. For data scaling, compare
    `price_class` with `price_class_10x`.
    """
    import argparse
    import json

    ask = argparse.ArgumentParser(description="Run one workload under one policy.")
    ask.add_argument("folder")
    ask.add_argument("--workload", choices=sorted(WORKLOADS), default="price_class")
    ask.add_argument("--policy", choices=sorted(POLICIES), default="optimal")
    ask.add_argument("--iterations", type=int)
    ask.add_argument("--limit", type=float, help="seconds after which no further version is begun")
    ask.add_argument("--master")
    a = ask.parse_args(arguments)
    builder = SparkSession.builder.appName(f"{a.workload} {a.policy}")
    spark = (builder.master(a.master) if a.master else builder).getOrCreate()
    got = run(spark, a.folder, a.workload, a.policy, a.iterations, limit_s=a.limit)
    versions = [round(r["wall_s"], 2) for r in got["records"]]
    print(json.dumps({k: got[k] for k in ("workload", "policy", "finished", "peak_bytes", "average_bytes")} | {k: sum(r[k] for r in got["records"]) for k in ("n_prune", "n_load", "n_compute")} | {"materialize_s": round(sum(r["materialize_s"] for r in got["records"]), 2), "store_bytes": [r["store_bytes"] for r in got["records"]]} | {"tasks": spark.sparkContext.defaultParallelism, "seconds": round(got["seconds"], 2), "versions": versions}))


if __name__ == "__main__":
    main()
