"""Document fingerprints: threshold-scaled sketches of word shingles.

A sketch keeps every shingle hash below a fixed fraction of the hash range, so its
size follows the text's, and sketches of parts merge to that of the whole. A text
that keeps fewer than `least` this way keeps its `least` smallest hashes instead,
or all if it has no more: its own threshold is then higher. Two sketches are compared below the
lower of their thresholds, so nothing is compared that one of them could not hold.
Likeness is the estimated resemblance; containment the estimated share of one
text's shingles in the other, which holds for texts of very unequal length.

A fingerprint is the sorted hashes, 12 hex digits each, joined.

Defined results: null and empty texts, and texts of white space, have the empty
fingerprint; two of these are alike (1), one and any other are not (0). Texts of
one to four words have one shingle. Null ids come last. Rows with the same doc_id (ties)
follow each other by the text's hash, and rows alike in both in any order, which changes
no result. With one row the next document is the row itself. An empty table gives an
empty table. Very long texts are sketched whole. Columns other than
the id and the text are not read.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from iterspark.llm.textvec import blocks, counted, shingles, words

BITS = 48


def sketches(column: pa.Array, *, fraction: float = 0.125, least: int = 16, size: int = 5) -> list[np.ndarray]:
    """Of each text, its kept hashes, ascending (uint64 below 2^48)."""
    limit = np.uint64(fraction * 2**BITS)
    out: list[np.ndarray] = []
    for block in blocks(column):
        h, d = shingles(words(block), size)
        h = h >> np.uint64(64 - BITS)
        n = len(block.bounds) - 1
        under = h < limit
        low, of, _ = counted(h[under], d[under])
        few = np.bincount(of, minlength=n) < least  # of distinct hashes: repeats count once
        use = few[d]
        rest, of_rest, _ = counted(h[use], d[use])
        h, d = np.concatenate((low[~few[of]], rest)), np.concatenate((of[~few[of]], of_rest))
        order = np.argsort(d, kind="stable")
        h, d = h[order], d[order]
        ends = np.searchsorted(d, np.arange(n + 1))
        for i in range(n):
            own = h[ends[i] : ends[i + 1]]
            out.append(own[:least] if few[i] else own)
    return out


def encode(sketch: np.ndarray) -> str:
    return sketch.astype(">u8").view(np.uint8).reshape(-1, 8)[:, 2:].tobytes().hex()


def decode(fingerprint: str) -> np.ndarray:
    raw = np.frombuffer(bytes.fromhex(fingerprint), dtype=np.uint8).reshape(-1, 6)
    return np.concatenate((np.zeros((len(raw), 2), dtype=np.uint8), raw), axis=1).reshape(-1).view(">u8").astype(np.uint64)


def threshold(sketch: np.ndarray, *, fraction: float = 0.125, least: int = 16) -> int:
    """The hash below or at which the sketch holds all of its text."""
    limit = int(fraction * 2**BITS)
    if len(sketch) < least:
        return 2**BITS
    return max(limit - 1, int(sketch[-1]))


def merged(a: np.ndarray, b: np.ndarray, **how) -> np.ndarray:
    """The sketch of two texts' shingles together, from their sketches."""
    both = np.union1d(a, b)
    return both[both <= np.uint64(min(threshold(a, **how), threshold(b, **how)))]


def compare(a: np.ndarray, b: np.ndarray, **how) -> tuple[float, float, float]:
    """Likeness, share of a in b, share of b in a."""
    if not len(a) or not len(b):
        same = float(len(a) == len(b))
        return same, same, same
    top = np.uint64(min(threshold(a, **how), threshold(b, **how)))
    x, y = a[a <= top], b[b <= top]
    both = np.concatenate((x, y))
    both.sort(kind="stable")
    common = int(np.count_nonzero(both[1:] == both[:-1]))
    return common / max(len(both) - common, 1), common / max(len(x), 1), common / max(len(y), 1)


def _above(edges: list[int], value: Column) -> Column:
    """Number of (ascending) edges above the value; looks at about twice the root of their number."""
    step = max(1, math.isqrt(len(edges)))
    coarse, fine = F.lit(edges[::step]), F.lit(edges)
    rough = F.size(F.filter(coarse, lambda e: e <= value))
    start = F.greatest(rough - 1, F.lit(0)) * step
    at_or_below = F.when(rough > 0, start + F.size(F.filter(F.slice(fine, start + 1, F.lit(step)), lambda e: e <= value))).otherwise(0)
    return len(edges) - at_or_below


def with_next(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", rows_per_range: int = 2000, most_ranges: int = 20_000) -> DataFrame:
    """doc_id, text, n_chars, edited, following: each document with its successor in descending id.

    Documents are dealt to ranges of the id between quantiles, each a window of its
    own; the last of a range takes the first of the next as its successor. An id that
    spans several quantiles (or null, where many ids are null) is a range of its own,
    dealt on by parts of the text's hash, in which its rows are ordered.
    """
    base = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    count, low, nulls = base.agg(F.count("*"), F.min("doc_id"), F.count_if(F.col("doc_id").isNull())).first()
    wanted = min(most_ranges, max(1, -(-count // rows_per_range)))
    edges: list[int] = []
    parts: dict[int | None, int] = {}
    if wanted > 1 and low is not None:
        cuts = base.agg(F.percentile_approx("doc_id", [i / wanted for i in range(1, wanted)], 10 * wanted)).first()[0]
        parts = {i: n + 1 for i, n in Counter(cuts).items() if n > 1}
        beyond = {i + 1 for i in parts if i < 2**63 - 1}
        edges = sorted((set(cuts) | beyond) - {low})
    if nulls > max(1, count // wanted):
        parts[None] = -(-nulls * wanted // count)
    last = len(edges) + (1 if nulls else 0) if low is not None else 0
    where = _above(edges, F.col("doc_id")) if edges else F.lit(0)
    ranged = base.withColumn("_range", F.when(F.col("doc_id").isNull(), F.lit(last)).otherwise(where).cast("int")).withColumn("_tie", F.xxhash64("text"))
    if parts:
        # at most half as many rows as there are ranges
        known = base.sparkSession.createDataFrame([(i is None, i or 0, n) for i, n in parts.items()], "_none boolean, _id long, _parts int")
        ranged = ranged.join(F.broadcast(known), (F.col("doc_id").isNull() == F.col("_none")) & (F.coalesce("doc_id", F.lit(0)) == F.col("_id")), "left")
        part = F.floor((F.col("_tie") / F.lit(2.0**64) + 0.5) * F.col("_parts"))
        ranged = ranged.withColumn("_part", F.coalesce(F.least(part, F.col("_parts") - 1), F.lit(0)).cast("int")).drop("_none", "_id", "_parts")
        order = sorted((r["_range"], r["_part"]) for r in ranged.select("_range", "_part").distinct().collect())
    else:  # every edge is an id that occurs, so no range is empty
        ranged, order = ranged.withColumn("_part", F.lit(0)), [(i, 0) for i in range(last + 1)]
    after = base.sparkSession.createDataFrame([(*own, *order[(i + 1) % len(order)]) for i, own in enumerate(order)] or [(0, 0, 0, 0)], "_range int, _part int, _r int, _p int")
    first = F.struct(F.coalesce("doc_id", F.lit(0)).alias("id"), (-F.col("_tie").cast("decimal(20,0)")).alias("tie"))
    heads = ranged.groupBy("_range", "_part").agg(F.max_by("text", first).alias("_head")).withColumnsRenamed({"_range": "_r", "_part": "_p"})
    heads = heads.join(F.broadcast(after), ["_r", "_p"]).drop("_r", "_p")
    own = Window.partitionBy("_range", "_part").orderBy(F.col("doc_id").desc(), "_tie")
    led = ranged.withColumn("_next", F.lead("text").over(own)).join(heads, ["_range", "_part"])
    following = F.coalesce("_next", "_head")
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substring("text", F.lit(1), n - half), F.substring(following, F.lit(1), half))
    return led.select("doc_id", "text", n.cast("long").alias("n_chars"), edited.alias("edited"), following.alias("following"))


def fingerprint_documents(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", fraction: float = 0.125, least: int = 16, size: int = 5) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next, kept_in_edited, next_in_it."""
    how = {"fraction": fraction, "least": least}
    rows = with_next(docs, doc_id=doc_id, text=text).select("doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), "text", "edited", "following")
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next", "kept_in_edited", "next_in_it"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            own, edited, after = (sketches(b.column(c), **how, size=size) for c in ("text", "edited", "following"))
            to_edited = [compare(x, y, **how) for x, y in zip(own, edited, strict=True)]
            to_next = [compare(x, y, **how) for x, y in zip(own, after, strict=True)]
            cols = [[encode(x) for x in own], [encode(x) for x in edited], [x[0] for x in to_edited], [x[0] for x in to_next], [x[1] for x in to_edited], [x[2] for x in to_next]]
            types = [pa.string(), pa.string(), *[pa.float64()] * 4]
            yield pa.RecordBatch.from_arrays([b.column(i) for i in range(3)] + [pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=names)

    return rows.mapInArrow(run, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, kept_in_edited double, next_in_it double")
