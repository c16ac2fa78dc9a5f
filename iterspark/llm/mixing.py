"""Mixing sources to target weights by entropy balancing.

A document of source s and size z (in words) gets a rate r. Of all rates that
meet the sources' targets, sum(r * z) = target, and stay in 0..cap, those nearest
to 1 in relative entropy are r = min(cap, exp(lambda_s * z / scale_s)): an
exponential tilt by what the document adds to the constraint. The lambdas
maximise a concave dual; Newton steps, halved while they would overshoot, solve it.
Gradient and curvature are sums over the distinct sizes of a source with their
counts, which lose nothing and are summed on the executors; only (source, two
sums) come to the driver in each step.

Rates are rounded to copies by a hash of the document: floor, plus one where the
hash falls below the rest. A shift of that threshold, found for each source from
histograms of the hash margins, then brings its taken words next to its target.

Defined results: a null or empty text has size 0 and is taken as its rate says
without adding words; null sources are a source of their own, last in order.
Repeated rows count each; rows alike in id and text share a hash and are rounded
alike. A source of no words has target 0; no rows give no rows. Very long texts
are counted whole. Columns other than id, text and source are carried only where
`keep` names them.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from iterspark.llm.common import collect_bounded, cut, n_words, parked

MOST_SOURCES = 1_000_000
_BINS = 1024


def targets(sizes: dict, weights: tuple[float, ...], total_share: float, cap: float) -> dict:
    """Target words of each source; `sizes` by source in code-point order, null last.

    Weights repeat over the sources and share `total_share` of all words; a target
    stops at cap times its source's size and the excess is shared anew by weight.
    """
    order = sorted((s for s in sizes if s is not None), key=lambda s: [ord(c) for c in s]) + [s for s in sizes if s is None]
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    out, free, left = {}, set(order), total_share * sum(sizes.values())
    while free:
        whole = sum(weight[s] for s in free)
        over = {s for s in free if left * weight[s] >= cap * sizes[s] * whole} if whole else set()
        if not over:
            for s in free:
                out[s] = left * weight[s] / whole if whole else 0.0
            break
        for s in over:
            out[s] = float(cap * sizes[s])
        left = max(0.0, left - sum(out[s] for s in over))
        free -= over
    return out


def _newton(stats: DataFrame, want: dict, scale: dict, cap: float, steps: int = 60, close: float = 1e-9) -> dict:
    """lambda of each source whose target lies strictly between 0 and cap times its size."""
    spark = stats.sparkSession
    lam, low, high = dict.fromkeys(want, 0.0), dict.fromkeys(want, -math.inf), dict.fromkeys(want, math.inf)
    open_ = set(want)
    for _ in range(steps):
        if not open_:
            break
        now = spark.createDataFrame([(s is None, s or "", lam[s], scale[s]) for s in open_], "_none boolean, _key string, _lam double, _scale double")
        x = F.col("size") / F.col("_scale")
        tilt = F.exp(F.least(F.col("_lam") * x, F.lit(math.log(cap) + 1)))
        rate = F.least(tilt, F.lit(float(cap)))
        # decimals add up alike in any order, so that runs agree to the bit
        exact = lambda v: F.sum(v.cast("decimal(38,8)")).cast("double")
        sums = stats.join(F.broadcast(now), ["_none", "_key"]).groupBy("_none", "_key").agg(
            exact(rate * F.col("size") * F.col("n")).alias("g"), exact(F.when(tilt < cap, tilt * x * F.col("size") * F.col("n")).otherwise(0.0)).alias("h")
        )
        for r in sums.collect():
            s = None if r["_none"] else r["_key"]
            gap = want[s] - r["g"]
            if abs(gap) <= close * want[s]:
                open_.discard(s)
                continue
            if gap > 0:
                low[s] = lam[s]
            else:
                high[s] = lam[s]
            step = lam[s] + gap / r["h"] if r["h"] > 0 else math.nan
            if not low[s] < step < high[s]:  # left the bracket: widen, or halve
                step = (low[s] + high[s]) / 2 if math.isfinite(low[s] + high[s]) else lam[s] * 2 + (1 if gap > 0 else -1)
            if step == lam[s]:
                open_.discard(s)
            lam[s] = step
    return lam


def mix(
    docs: DataFrame,
    *,
    doc_id: str = "doc_id",
    text: str = "text",
    source: str = "source",
    weights: tuple[float, ...] = (3, 1, 2),
    total_share: float = 1.5,
    cap: int = 2,
    keep: tuple[str, ...] = (),
) -> DataFrame:
    """`keep`, doc_id, size, source_size, target, taken, copies, rate; a row for each document."""
    slim = docs.select(
        *[F.col(c).alias(f"_keep_{i}") for i, c in enumerate(keep)],
        F.col(doc_id).alias("doc_id"),
        F.col(source).isNull().alias("_none"),
        F.coalesce(F.col(source), F.lit("")).alias("_key"),
        n_words(F.col(text)).alias("size"),
        F.xxhash64(F.col(doc_id).cast("string"), F.col(text)).alias("_hash"),
    )
    slim = parked(slim, "mix") if keep else cut(slim)
    stats = cut(slim.groupBy("_none", "_key", "size").agg(F.count("*").alias("n")))
    rows = collect_bounded(stats.groupBy("_none", "_key").agg(F.sum(F.col("size") * F.col("n")).alias("words"), F.sum("n").alias("n")), MOST_SOURCES, "sources")
    sizes = {None if r["_none"] else r["_key"]: r["words"] for r in rows}
    count = {None if r["_none"] else r["_key"]: r["n"] for r in rows}
    goal = targets(sizes, weights, total_share, cap)
    scale = {s: max(1.0, sizes[s] / count[s]) for s in sizes}
    inner = {s: goal[s] for s in sizes if 0 < goal[s] < cap * sizes[s] * (1 - 1e-12)}
    lam = _newton(stats, inner, scale, cap)
    fixed = {s: (float(cap) if goal[s] > 0 else 0.0) for s in sizes if s not in inner}
    spark = docs.sparkSession
    plan_rows = [(s is None, s or "", sizes[s], float(goal[s]), lam.get(s, 0.0), scale[s], fixed.get(s)) for s in sizes]
    plan = spark.createDataFrame(plan_rows, "_none boolean, _key string, source_size long, target double, _lam double, _scale double, _fixed double")
    tilt = F.exp(F.least(F.col("_lam") * F.col("size") / F.col("_scale"), F.lit(math.log(cap) + 1)))
    chance = (F.shiftrightunsigned(F.col("_hash"), 11)).cast("double") * F.lit(2.0**-53)
    rated = slim.join(F.broadcast(plan), ["_none", "_key"]).withColumn("rate", F.coalesce(F.col("_fixed"), F.least(tilt, F.lit(float(cap)))))
    rated = rated.withColumn("_whole", F.floor("rate")).withColumn("_margin", chance - (F.col("rate") - F.col("_whole")))
    shifts = _shifts(rated.filter(F.col("_fixed").isNull() & (F.col("size") > 0)), inner, cap)
    shift = spark.createDataFrame([(s is None, s or "", v) for s, v in shifts.items()] or [(False, "", 0.0)], "_none boolean, _key string, _shift double")
    out = rated.join(F.broadcast(shift), ["_none", "_key"], "left")
    extra = (F.col("_margin") < F.coalesce(F.col("_shift"), F.lit(0.0))) & F.col("_fixed").isNull() & (F.col("_whole") < cap)
    copies = (F.col("_whole") + F.when(extra, 1).otherwise(0)).cast("long")
    return out.withColumn("copies", copies).select(
        *[F.col(f"_keep_{i}").alias(c) for i, c in enumerate(keep)],
        *[F.col(c) for c in ("doc_id",) if c not in keep],
        *[F.col(c) for c in ("size", "source_size", "target") if c not in keep],
        (F.col("copies") * F.col("size")).alias("taken"),
        "copies",
        "rate",
    )


def _shifts(rated: DataFrame, want: dict, cap: int, levels: int = 3) -> dict:
    """Of each source, the threshold shift whose taken words come nearest to the target.

    Every level splits the bin in which the target is met into `_BINS` finer ones.
    """
    spark = rated.sparkSession
    low, width, below = dict.fromkeys(want, -1.0), dict.fromkeys(want, 2.0), {}
    for level in range(levels):
        if not want:
            break
        now = spark.createDataFrame([(s is None, s or "", low[s], width[s] / _BINS) for s in want], "_none boolean, _key string, _low double, _step double")
        # a document at its cap takes no further copy
        gain = F.when(F.col("_whole") < cap, F.col("size")).otherwise(0)
        bins = rated.join(F.broadcast(now), ["_none", "_key"]).withColumn("_bin", F.least(F.greatest(F.floor((F.col("_margin") - F.col("_low")) / F.col("_step")), F.lit(-1)), F.lit(_BINS)))
        sums = bins.groupBy("_none", "_key", "_bin").agg(F.sum(gain).alias("w"), F.sum(F.when(F.lit(level == 0), F.col("_whole") * F.col("size")).otherwise(0)).alias("base"))
        got: dict = {}
        for r in sums.collect():
            s = None if r["_none"] else r["_key"]
            got.setdefault(s, {})[int(r["_bin"])] = (r["w"], r["base"])
        for s, by_bin in got.items():
            if level == 0:
                below[s] = sum(b for _, b in by_bin.values())
            total, i = below[s], 0
            while i < _BINS and total + by_bin.get(i, (0, 0))[0] <= want[s]:
                total += by_bin.get(i, (0, 0))[0]
                i += 1
            below[s] = total
            step = width[s] / _BINS
            low[s], width[s] = low[s] + i * step, step if i < _BINS else 0.0
            if level == levels - 1 and i < _BINS and total + by_bin[i][0] - want[s] < want[s] - total:
                low[s] += step
            if not width[s]:
                width[s] = step
    return low


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as many times as the mix takes it; all columns."""
    mixed = mix(docs.select(F.struct("*").alias("_row"), "doc_id", "text", "source"), keep=("_row",))
    return mixed.select("_row", F.explode(F.array_repeat(F.lit(1), F.col("copies").cast("int")))).select("_row.*")
