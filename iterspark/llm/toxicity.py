"""Toxicity: boosted trees over dense features, with isotonic calibration.

Features of a text: density of lexicon words as written and after undoing
obfuscation (look-alike digits and signs, punctuation inside words, letters drawn
out), how many of them stand close to a second-person word, capitals, punctuation
and signs, and length. The lexicon is a short list of plain insults joined by
words that the labelled sample shows to come with the label, each learned as written
and as rewritten. A learned word is in a `least_share` of the toxic texts of the
sample at least, so there are at most 1 / `least_share` times as many as a toxic text
has distinct words on average. Trees are fitted on three parts of the sample; their
margins are calibrated by isotonic regression (pool adjacent violators) on the fourth.

To undo obfuscation, an exclamation mark is dropped unless letters or digits stand on
both its sides, look-alikes are read as letters, punctuation is dropped, and a run of
one letter is cut to one, in texts and in the lexicon alike.

Defined results: ties in a margin share a calibrated score; ties between splits go to
the first feature and the lowest edge. An empty table gives an empty table. null and empty texts, and texts of white space, have features of
zero and get the score of those. Repeated rows are scored each. Without labels, or
with labels of one class only, the score is 0, or that class's. Very long texts
count whole. Other columns are not read; `stage` carries them.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from iterspark.llm.common import cut, fold, short_batches
from iterspark.llm.labelled import MOST_LABELLED, training_rows
from iterspark.llm.textvec import Block, blocks, words

# Plain insults, and second-person words of four languages.
INSULTS = ["idiot", "moron", "stupid", "dumb", "loser", "trash", "scum", "worthless", "pathetic", "disgusting", "clown", "fool", "garbage", "hate", "ugly"]
SECOND_PERSON = ["you", "your", "yours", "yourself", "u", "ur", "tu", "toi", "ton", "vous", "votre", "du", "dich", "dir", "dein", "deine", "ihr", "euch", "ti", "usted", "vosotros"]
# Look-alikes and what they stand for.
_LOOKS = dict(zip("0134578@$!", "oieastbasi", strict=True))

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_PLAIN_KEEP = np.ones(256, dtype=bool)
_PLAIN_KEEP[[ord(c) for c in ".,;:?\"'()[]{}-_*|~/\\`^+=#%&<>"]] = False
_LEET = _LOWER.copy()
for _a, _b in _LOOKS.items():
    _LEET[ord(_a)] = ord(_b)
_IS = {
    "upper": np.isin(np.arange(256), np.arange(65, 91)),
    "letter": np.isin(np.arange(256), [*range(65, 91), *range(97, 123), *range(128, 256)]),
    "digit": np.isin(np.arange(256), np.arange(48, 58)),
    "exclaim": np.arange(256) == ord("!"),
    "question": np.arange(256) == ord("?"),
    "mark": np.isin(np.arange(256), [ord(c) for c in ".,;:'\"()-"]),
    "sign": np.isin(np.arange(256), [ord(c) for c in "@#$%&*^~+=<>|_/\\"]),
}
FEATURES = ["lexicon", "lexicon_count", "obfuscated", "obfuscated_count", "near_you", "second_person", "shout_words", "mixed_words", "drawn_out", *_IS, "log_words"]


def _rewritten(block: Block, table: np.ndarray, squeeze: bool) -> Block:
    """The block with bytes mapped and punctuation around words gone; `squeeze` also drops it inside and cuts runs of a letter to one."""
    raw = block.data
    word = _IS["letter"][raw] | _IS["digit"][raw]
    inner = np.zeros(len(raw), dtype=bool)
    inner[1:-1] = word[:-2] & word[2:]
    some = np.diff(block.bounds) > 0  # a text's first and last byte have no neighbour beyond it
    inner[block.bounds[:-1][some]] = inner[block.bounds[1:][some] - 1] = False
    mark = _IS["exclaim"][raw]
    keep = _PLAIN_KEEP[raw] & (inner | ~mark) if squeeze else inner | (_PLAIN_KEEP[raw] & ~mark)
    data = table[raw]
    if squeeze:
        at = np.flatnonzero(keep)  # neighbours once punctuation is gone
        last = data[at]
        again = np.zeros(len(at), dtype=bool)
        again[1:] = (last[1:] == last[:-1]) & _IS["letter"][last[1:]] & (last[1:] < 128)
        text = np.searchsorted(block.bounds, at, side="right")
        again[1:] &= text[1:] == text[:-1]
        keep[at[again]] = False
    places = np.concatenate(([0], np.cumsum(keep)))
    return Block(block.first, block.last, data[keep], places[block.bounds])


def lexicon_hashes(texts: list[str], squeezed: bool = True) -> np.ndarray:
    block = next(blocks(pa.array([" ".join(texts)])))
    return np.unique(words(_rewritten(block, _LEET if squeezed else _LOWER, squeezed)).hash)


@dataclass(frozen=True)
class Lexicon:
    """Hashes of words as written in small letters, and as rewritten."""

    plain: np.ndarray
    rewritten: np.ndarray

    @staticmethod
    def of(texts: list[str]) -> Lexicon:
        return Lexicon(lexicon_hashes(texts, False), lexicon_hashes(texts))

    def joined(self, plain: np.ndarray, rewritten: np.ndarray) -> Lexicon:
        return Lexicon(np.union1d(self.plain, plain), np.union1d(self.rewritten, rewritten))


def _has(hashes: np.ndarray, lexicon: np.ndarray) -> np.ndarray:
    if not len(lexicon):
        return np.zeros(len(hashes), dtype=bool)
    return lexicon[np.minimum(np.searchsorted(lexicon, hashes), len(lexicon) - 1)] == hashes


def features(column: pa.Array, lexicon: Lexicon, near: int = 4) -> np.ndarray:
    you = lexicon_hashes(SECOND_PERSON)
    out = []
    for block in blocks(column):
        n_docs = len(block.bounds) - 1
        plain, leet, raw = words(_rewritten(block, _LOWER, False)), words(_rewritten(block, _LEET, True)), words(block)

        def per_doc(doc: np.ndarray, hit: np.ndarray, n: int = n_docs) -> np.ndarray:
            return np.bincount(doc[hit], minlength=n).astype(float)

        hit_leet = _has(leet.hash, lexicon.rewritten)
        lex, obf = per_doc(plain.doc, _has(plain.hash, lexicon.plain)), per_doc(leet.doc, hit_leet)
        second = _has(leet.hash, you)
        # the nearest second-person word on either side, in the same text
        at = np.arange(len(second))
        before = np.maximum.accumulate(np.where(second, at, -(10**9))) if len(at) else at
        after = np.minimum.accumulate(np.where(second, at, 10**9)[::-1])[::-1] if len(at) else at
        close = np.zeros(len(at), dtype=bool)
        for other in (before, after):
            ok = np.abs(other - at) <= near
            close[ok] |= leet.doc[other[ok]] == leet.doc[at[ok]]
        sums = {k: np.concatenate(([0], np.cumsum(m[block.data]))) for k, m in _IS.items()}
        size = np.maximum(np.diff(block.bounds), 1)
        shares = [np.diff(s[block.bounds]) / size for s in sums.values()]
        ends = raw.start + raw.length

        def within(k: str) -> np.ndarray:
            return sums[k][ends] - sums[k][raw.start]

        n = np.maximum(raw.count, 1)
        shout = (raw.length > 2) & (within("upper") == within("letter")) & (within("letter") > 2)
        mixed = ((within("digit") > 0) | (within("sign") > 0)) & (within("letter") > 0)
        same = np.zeros(len(block.data), dtype=bool)
        same[2:] = (block.data[2:] == block.data[1:-1]) & (block.data[1:-1] == block.data[:-2]) & _IS["letter"][block.data[2:]]
        drawn = np.diff(np.concatenate(([0], np.cumsum(same)))[block.bounds])
        out.append(
            np.column_stack(
                [lex / n, np.minimum(lex, 20), np.maximum(obf - lex, 0) / n, np.minimum(obf, 20), per_doc(leet.doc, hit_leet & close) / n, per_doc(leet.doc, second) / n, per_doc(raw.doc, shout) / n, per_doc(raw.doc, mixed) / n, drawn / size, *shares, np.log1p(raw.count)]
            )
        )
    return np.concatenate(out) if out else np.zeros((0, len(FEATURES)))


class Trees:
    """Boosted regression trees on the logistic loss, from binned features."""

    def __init__(self, rounds: int = 40, depth: int = 3, rate: float = 0.15, bins: int = 32, least: int = 40, shrink: float = 5.0):
        """`least`: rows on either side of a split, fewer where the sample is small."""
        self.rounds, self.depth, self.rate, self.bins, self.least, self.shrink = rounds, depth, rate, bins, least, shrink
        self.trees: list[tuple[list[tuple[int, float]], np.ndarray]] = []

    def fit(self, x: np.ndarray, y: np.ndarray) -> Trees:
        edges = [np.unique(np.quantile(c, np.linspace(0, 1, self.bins + 1)[1:-1])) for c in x.T]
        code = np.column_stack([np.searchsorted(e, c, side="left") for e, c in zip(edges, x.T, strict=True)])
        n_bins = max(len(e) for e in edges) + 1
        least = min(self.least, max(5, len(y) // 200))
        p0 = float(np.clip(y.mean(), 1e-4, 1 - 1e-4))
        self.start = np.log(p0 / (1 - p0))
        margin = np.full(len(y), self.start)
        for _ in range(self.rounds):
            p = 1 / (1 + np.exp(-margin))
            g, h = y - p, p * (1 - p)
            node = np.zeros(len(y), dtype=np.int64)
            splits: list[tuple[int, float]] = []
            for level in range(self.depth):
                width = 1 << level
                best = [(0.0, 0, np.inf)] * width
                for f in range(x.shape[1]):
                    at = node * n_bins + code[:, f]
                    sg, sh, sn = (np.bincount(at, weights=v, minlength=width * n_bins).reshape(width, n_bins).cumsum(1) for v in (g, h, None))
                    tg, th, tn = sg[:, -1:], sh[:, -1:], sn[:, -1:]
                    gain = sg**2 / (sh + self.shrink) + (tg - sg) ** 2 / (th - sh + self.shrink) - tg**2 / (th + self.shrink)
                    gain[(sn < least) | (tn - sn < least)] = 0
                    for k in range(width):
                        b = int(np.argmax(gain[k, : len(edges[f])])) if len(edges[f]) else 0
                        if len(edges[f]) and gain[k, b] > best[k][0] + 1e-9:
                            best[k] = (float(gain[k, b]), f, float(edges[f][b]))
                splits += [(f, t) for _, f, t in best]
                fs, ts = np.array([b[1] for b in best]), np.array([b[2] for b in best])
                node = 2 * node + (x[np.arange(len(y)), fs[node]] > ts[node])
            leaves = 1 << self.depth
            value = self.rate * np.bincount(node, weights=g, minlength=leaves) / (np.bincount(node, weights=h, minlength=leaves) + self.shrink)
            self.trees.append((splits, value))
            margin += value[node]
        return self

    def margin(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.start)
        rows = np.arange(len(x))
        for splits, value in self.trees:
            node, base = np.zeros(len(x), dtype=np.int64), 0
            for level in range(self.depth):
                own = splits[base : base + (1 << level)]
                fs, ts = np.array([f for f, _ in own]), np.array([t for _, t in own])
                node = 2 * node + (x[rows, fs[node]] > ts[node])
                base += 1 << level
            out += value[node]
        return out


def isotonic(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Knots of the non-decreasing least-squares fit (pool adjacent violators)."""
    x, at = np.unique(x, return_inverse=True)
    sums, size = np.bincount(at, weights=y), np.bincount(at).astype(float)
    pools: list[list[float]] = []  # sum, size, first x, last x
    for s, n, v in zip(sums, size, x, strict=True):
        pools.append([s, n, v, v])
        while len(pools) > 1 and pools[-2][0] * pools[-1][1] >= pools[-1][0] * pools[-2][1]:
            s2, n2, _, v2 = pools.pop()
            pools[-1] = [pools[-1][0] + s2, pools[-1][1] + n2, pools[-1][2], v2]
    knots = [(v, p[0] / p[1]) for p in pools for v in dict.fromkeys(p[2:])]
    return np.array([k[0] for k in knots]), np.array([k[1] for k in knots])


class Detector:
    def __init__(self) -> None:
        self.constant: float | None = None
        self.lexicon = Lexicon.of(INSULTS)

    def fit(self, x: np.ndarray, y: np.ndarray, held: np.ndarray) -> Detector:
        if not len(y) or y.min() == y.max():
            self.constant = float(y[0]) if len(y) else 0.0
            return self
        if not held.any() or held.all() or len(set(y[~held])) < 2:
            held = np.zeros(len(y), dtype=bool)
        self.trees = Trees().fit(x[~held], y[~held])
        own = held if held.any() else ~held
        self.knots = isotonic(self.trees.margin(x[own]), y[own])
        return self

    def score(self, column: pa.Array) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(column), self.constant)
        if not len(column):
            return np.zeros(0)
        return np.clip(np.interp(self.trees.margin(features(column, self.lexicon)), *self.knots), 0, 1)


def _learned_lexicon(rows: DataFrame, least_share: float, least_odds: float) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of words that come with the label, as written and as rewritten: in `least_share` of the texts so labelled, odds ratio `least_odds`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            y = b.column("y").to_numpy(zero_copy_only=False)
            for block in blocks(b.column("text")):
                for form, (table, squeeze) in enumerate(((_LOWER, False), (_LEET, True))):
                    w = words(_rewritten(block, table, squeeze))
                    if len(w.hash):
                        pairs = np.unique(np.rec.fromarrays([w.hash, w.doc], names="h,d"))
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(pairs), form, dtype=np.int32)), pa.array(pairs.h.view(np.int64)), pa.array(y[block.first : block.last][pairs.d])], names=["form", "h", "y"])

    counts = rows.agg(F.sum("y"), F.count("*")).first()
    bad, good = float(counts[0] or 0), float((counts[1] or 0) - (counts[0] or 0))
    by_word = rows.filter("part < 4").mapInArrow(run, "form int, h long, y double").groupBy("form", "h").agg(F.sum("y").alias("bad"), (F.count("*") - F.sum("y")).alias("good"))
    odds = (F.col("bad") / max(bad, 1)) / ((F.col("good") + 1) / max(good, 1))
    found = by_word.filter((F.col("bad") >= max(5.0, least_share * bad)) & (odds >= least_odds)).select("form", "h").collect()  # bounded: see the module's text
    return tuple(np.array(sorted(r["h"] for r in found if r["form"] == form), dtype=np.int64).view(np.uint64) for form in (0, 1))


def fit_toxicity(docs: DataFrame, labels: DataFrame, *, label: str = "toxic", most_labelled: int = MOST_LABELLED, least_share: float = 0.02, least_odds: float = 50.0) -> Detector:
    """`most_labelled` bounds the sample."""
    rows = cut(training_rows(docs, labels, label, most_labelled))
    model = Detector()
    model.lexicon = model.lexicon.joined(*_learned_lexicon(rows, least_share, least_odds))
    shared = docs.sparkSession.sparkContext.broadcast(model.lexicon)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = features(b.column("text"), shared.value)
            yield pa.RecordBatch.from_arrays([pa.array([r.tobytes() for r in x], pa.binary()), b.column("y"), b.column("part")], names=["x", "y", "part"])

    got = rows.mapInArrow(run, "x binary, y double, part int").collect()  # `most_labelled` vectors
    got.sort(key=lambda r: (r["part"], r["y"], bytes(r["x"])))
    x = np.frombuffer(b"".join(bytes(r["x"]) for r in got), dtype=np.float64).reshape(-1, len(FEATURES))
    return model.fit(x, np.array([r["y"] for r in got]), np.array([r["part"] == 4 for r in got], dtype=bool))


def score_toxicity(docs: DataFrame, model: Detector, *, threshold: float = 0.5) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            score = shared.value.score(b.column("text"))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("held_out"), pa.array(score, pa.float64()), pa.array((score >= threshold).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (fold(F.col("doc_id")) == 0).alias("held_out"), "text")
    return slim.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str, threshold: float = 0.5) -> DataFrame:
    """The documents that are not toxic; all columns."""
    short_batches(spark)
    model = spark.sparkContext.broadcast(fit_toxicity(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.filter(pa.array(model.value.score(b.column(at)) < threshold))

    return docs.mapInArrow(run, docs.schema)
