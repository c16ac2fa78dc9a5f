"""Quality classifier: random-indexing word vectors, pooled, and a two-layer network.

Every word has an index vector, sparse and of random signs, that follows from its
hash. A word's context vector is the sum of the index vectors of the words near
it, over all documents. Words share `buckets` rows by hash, so that the table's
size is a parameter and does not grow with the vocabulary. A document is the mean
and the spread of its words' vectors, with its length. A network with one hidden
layer, written in numpy, gives a logit; the logit is divided by a temperature that
is fitted on training rows the network did not see.

Context sums are whole numbers and are merged in rounds of at most `_FAN` parts,
so memory is bounded and results do not hang on the order.

Defined results: null and empty texts, and texts of white space, have pooled
vectors of zeros and get the score the network gives those. Repeated rows are
scored each. Without labels, or with labels of one class only, the score is 0.5,
or that class's. Very long texts are pooled whole. Other columns are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from iterspark.llm.common import fold, parked
from iterspark.llm.labelled import MOST_LABELLED, training_rows
from iterspark.llm.textvec import Words, blocks, mix, words

_FAN, _PART = 64, 1024
_ROW = "part int, task long, sums binary"


@dataclass(frozen=True)
class Shape:
    buckets: int = 1 << 15
    dims: int = 64
    marks: int = 2  # places of an index vector that are not zero
    window: int = 2


def _places(bucket: np.ndarray, shape: Shape) -> list[tuple[np.ndarray, np.ndarray]]:
    out = []
    for k in range(shape.marks):
        h = mix(bucket.astype(np.uint64) * np.uint64(2 * k + 3) + np.uint64(1 + k))
        out.append(((h % np.uint64(shape.dims)).astype(np.int64), np.where(h >> np.uint64(63), 1.0, -1.0)))
    return out


def bucket_of(w: Words, shape: Shape) -> np.ndarray:
    return (w.hash % np.uint64(shape.buckets)).astype(np.int64)


def context_vectors(docs: DataFrame, shape: Shape = Shape()) -> np.ndarray:
    """buckets x dims; unit rows, or zeros for buckets that no word falls in."""
    cells = shape.buckets * shape.dims

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(cells)
        table = _places(np.arange(shape.buckets), shape)
        for b in batches:
            for block in blocks(b.column(0)):
                w = words(block)
                bucket = bucket_of(w, shape)
                at, signs = [], []
                for gap in range(1, shape.window + 1):
                    near = np.flatnonzero(w.doc[gap:] == w.doc[:-gap]) if len(w.doc) > gap else np.zeros(0, dtype=np.int64)
                    left, right = bucket[near], bucket[near + gap]
                    for place, sign in table:
                        for own, other in ((left, right), (right, left)):
                            at.append(own * shape.dims + place[other])
                            signs.append(sign[other])
                if at:  # one pass over the cells for each block
                    total += np.bincount(np.concatenate(at), weights=np.concatenate(signs), minlength=cells)
        task = TaskContext.get().partitionId()
        size = _PART * shape.dims
        for i in range(0, cells, size):
            if total[i : i + size].any():
                yield _sums_row(i // size, task, total[i : i + size].astype(np.int64))

    first = parked(docs.select("text").mapInArrow(run, _ROW), "context")
    tasks = (first.agg(F.max("task")).first()[0] or 0) + 1

    def merge(key: tuple[pa.Scalar, ...], group: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for b in group:
            for x in b.column("sums"):
                got = np.frombuffer(zlib.decompress(x.as_py()), dtype=np.int64)
                total = got.copy() if total is None else total + got
        yield _sums_row(key[0].as_py(), key[1].as_py(), total)

    while tasks > 1:
        tasks = -(-tasks // _FAN)
        first = first.withColumn("task", F.floor(F.col("task") / _FAN)).groupBy("part", "task").applyInArrow(merge, _ROW)
    out = np.zeros((shape.buckets, shape.dims))
    for r in first.collect():  # `buckets` rows of numbers at most
        out[r["part"] * _PART : (r["part"] + 1) * _PART] = np.frombuffer(zlib.decompress(bytes(r["sums"])), dtype=np.int64).reshape(-1, shape.dims)
    norm = np.linalg.norm(out, axis=1, keepdims=True)
    return (out / np.maximum(norm, 1)).astype(np.float32)


def _sums_row(part: int, task: int, sums: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([task], pa.int64()), pa.array([zlib.compress(sums.tobytes(), 1)], pa.binary())], names=["part", "task", "sums"])


def pooled(column: pa.Array, vectors: np.ndarray, shape: Shape) -> np.ndarray:
    """Of each text: mean and spread of its words' vectors, likeness of neighbours, and log words."""
    out = []
    for block in blocks(column):
        w = words(block)
        n_docs, count = len(block.bounds) - 1, w.count
        bucket = bucket_of(w, shape)
        got = np.zeros((n_docs, 2 * shape.dims + 2))
        some = np.flatnonzero(count)
        if len(some):
            v = vectors[bucket]
            mean = np.add.reduceat(v, w.first[some], axis=0, dtype=np.float64) / count[some][:, None]
            square = np.add.reduceat(v * v, w.first[some], axis=0, dtype=np.float64) / count[some][:, None]
            got[some, : shape.dims] = mean
            got[some, shape.dims : 2 * shape.dims] = np.sqrt(np.maximum(square - mean * mean, 0))
            alike = np.zeros(len(v))
            alike[1:] = np.where(w.doc[1:] == w.doc[:-1], np.einsum("ij,ij->i", v[1:], v[:-1]), 0)
            got[some, -2] = np.add.reduceat(alike, w.first[some]) / count[some]
            got[some, -1] = np.log1p(count[some])
        out.append(got)
    return np.concatenate(out) if out else np.zeros((0, 2 * shape.dims + 2))


class Network:
    """One hidden layer of tanh units; logit / temperature."""

    def __init__(self, hidden: int = 32, epochs: int = 40, rate: float = 0.01, decay: float = 1e-4, seed: int = 11):
        self.hidden, self.epochs, self.rate, self.decay, self.seed = hidden, epochs, rate, decay, seed
        self.constant: float | None = None
        self.temperature = 1.0

    def fit(self, x: np.ndarray, y: np.ndarray, held: np.ndarray) -> Network:
        """`held`: rows that fit the temperature only."""
        if not len(y) or y.min() == y.max():
            self.constant = float(y[0]) if len(y) else 0.5
            return self
        train = ~held if 0 < (~held).sum() and len(set(y[~held])) == 2 else np.ones(len(y), dtype=bool)
        self.mean, self.std = x[train].mean(0), x[train].std(0) + 1e-6
        x = (x - self.mean) / self.std
        rng = np.random.default_rng(self.seed)
        self.w = [rng.normal(0, x.shape[1] ** -0.5, (x.shape[1], self.hidden)), np.zeros(self.hidden), rng.normal(0, self.hidden**-0.5, self.hidden), np.zeros(1)]
        first, second, step = [np.zeros_like(a) for a in self.w], [np.zeros_like(a) for a in self.w], 0
        tx, ty = x[train], y[train]
        for _ in range(self.epochs):
            order = rng.permutation(len(ty))
            for i in range(0, len(ty), 256):
                bx, by = tx[order[i : i + 256]], ty[order[i : i + 256]]
                h = np.tanh(bx @ self.w[0] + self.w[1])
                d = (1 / (1 + np.exp(-(h @ self.w[2] + self.w[3]))) - by) / len(by)
                dh = np.outer(d, self.w[2]) * (1 - h * h)
                grads = [bx.T @ dh + self.decay * self.w[0], dh.sum(0), h.T @ d + self.decay * self.w[2], np.array([d.sum()])]
                step += 1
                for k, g in enumerate(grads):
                    first[k] = 0.9 * first[k] + 0.1 * g
                    second[k] = 0.999 * second[k] + 0.001 * g * g
                    self.w[k] = self.w[k] - self.rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
        z, ly = (self._logit(x[held]), y[held]) if held.any() else (self._logit(tx), ty)
        loss = {t: float(np.mean(np.logaddexp(0, np.where(ly > 0.5, -z, z) / t))) for t in np.geomspace(0.25, 8, 71)}
        self.temperature = float(min(loss, key=loss.get))
        return self

    def _logit(self, x: np.ndarray) -> np.ndarray:
        return np.tanh(x @ self.w[0] + self.w[1]) @ self.w[2] + self.w[3]

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(x), self.constant)
        return 1 / (1 + np.exp(-np.clip(self._logit((x - self.mean) / self.std) / self.temperature, -40, 40)))


def fit_quality(docs: DataFrame, labels: DataFrame, *, label: str = "quality", most_labelled: int = MOST_LABELLED, shape: Shape = Shape()) -> tuple[np.ndarray, Network]:
    """Word vectors of all documents, and the network from the labelled sample."""
    vectors = context_vectors(docs, shape)
    shared = docs.sparkSession.sparkContext.broadcast(vectors)
    width = 2 * shape.dims + 2

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = pooled(b.column("text"), shared.value, shape).astype(np.float32)
            yield pa.RecordBatch.from_arrays([pa.array([r.tobytes() for r in x], pa.binary()), b.column("y"), b.column("part")], names=["x", "y", "part"])

    rows = training_rows(docs, labels, label, most_labelled).mapInArrow(run, "x binary, y double, part int").collect()  # `most_labelled` vectors
    rows.sort(key=lambda r: (r["part"], r["y"], bytes(r["x"])))  # the order of arrival must not show
    x = np.frombuffer(b"".join(bytes(r["x"]) for r in rows), dtype=np.float32).reshape(-1, width).astype(np.float64)
    return vectors, Network().fit(x, np.array([r["y"] for r in rows]), np.array([r["part"] == 4 for r in rows], dtype=bool))


def score_quality(docs: DataFrame, vectors: np.ndarray, network: Network, *, threshold: float = 0.3, shape: Shape = Shape()) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    shared = docs.sparkSession.sparkContext.broadcast((vectors, network))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v, net = shared.value
        for b in batches:
            score = net.score(pooled(b.column("text"), v, shape))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("held_out"), pa.array(score, pa.float64()), pa.array((score >= threshold).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (fold(F.col("doc_id")) == 0).alias("held_out"), "text")
    return slim.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def classify_quality(spark: SparkSession, docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    vectors, network = fit_quality(docs, labels, **options)
    return score_quality(docs, vectors, network)
