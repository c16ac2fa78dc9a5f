"""Skip-gram word vectors with a hierarchical softmax, trained part by part in numpy; the parts' vectors are averaged in Spark.

Each word at most `window` places before or after a place (the reach of each place is drawn from 1 to `window`) learns
the turns of the path to that place's word in a Huffman tree of the counts. Steps are made over blocks of places, as
products of small matrices: the nodes nearest to the root are on most paths and are held against all words of a block,
the others only against the neighbours of their own place.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Places in a block, blocks in a step, and nodes held against whole blocks. Products of this size stay in one thread of the library.
BLOCK, BLOCKS, TOP = 16, 48, 64
RATE, LEAST_RATE = 0.025, 0.0000025
#: The most that the rates of a node's pairs add up to in one step, and the most that a step moves a row.
MOST_RATE, MOST_MOVE = 2.0, 0.5
#: Runs of rows up to this length are summed place by place.
SHORT = 3
_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"
#: The text of places that are in none.
NONE = 255
#: Words that one batch of results holds.
WORDS_OUT = 10_000


def vocabulary(docs: DataFrame, tokens: str, min_count: int) -> tuple[pa.Array, np.ndarray]:
    """(words, counts): the words that come `min_count` times or more, sorted. They, not their vectors, sit on the driver and in each task."""
    words = docs.select(F.explode(tokens).alias("word")).filter("word is not null").groupBy("word").agg(F.count("*").alias("n"))
    found = words.filter(F.col("n") >= min_count).toArrow().combine_chunks().sort_by("word")
    return found["word"].combine_chunks(), found["n"].to_numpy()


def huffman(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(parent, turn) of each word and then of each inner node, which are numbered from the root on: node 0 weighs most."""
    n = len(counts)
    order = np.argsort(counts, kind="stable")
    leaves, inner = counts[order].tolist(), []
    left, right = [0] * max(n - 1, 0), [0] * max(n - 1, 0)  # n and more: inner nodes in the order they are made
    i = j = 0
    for k in range(n - 1):
        both = []
        for _ in range(2):
            if j >= len(inner) or (i < n and leaves[i] <= inner[j]):
                both.append((i, leaves[i]))
                i += 1
            else:
                both.append((n + j, inner[j]))
                j += 1
        (left[k], a), (right[k], b) = both
        inner.append(a + b)
    parent, turn = np.full(2 * n - 1, -1, np.int32), np.zeros(2 * n - 1, np.int8)
    place = np.concatenate([order, n + np.arange(n - 2, -1, -1)])
    made = np.arange(n - 2, -1, -1, dtype=np.int32)
    parent[place[left]], parent[place[right]] = made, made
    turn[place[right]] = 1
    return parent, turn


@dataclass
class Paths:
    """Of each of a part's words: the turns at the top nodes (1 and -1, 0 off the path), and the other nodes with their turns (-1 where there are no more)."""

    top: np.ndarray
    deep: np.ndarray
    signs: np.ndarray
    n_nodes: int


def paths(own: np.ndarray, parent: np.ndarray, turn: np.ndarray) -> Paths:
    """The paths of the words `own`; nodes below the top ones are numbered anew, without those on no path."""
    n = (len(parent) + 1) // 2
    at, top, deep, signs = own.astype(np.int64), np.zeros((len(own), TOP), np.int8), [], []
    used = np.zeros(max(n - 1, TOP), bool)
    while True:
        node, sign = parent[at], np.where(turn[at] == 0, 1, -1).astype(np.int8)
        if (node < 0).all():
            break
        high = np.flatnonzero((node >= 0) & (node < TOP))
        top[high, node[high]] = sign[high]
        low = node >= TOP
        if low.any():
            deep.append(np.where(low, node, -1).astype(np.int32))
            signs.append(sign)
            used[node[low]] = True
        at = np.where(node >= 0, n + node, at)
        at[node < 0] = n  # the root
    used[:TOP] = True
    number = np.cumsum(used, dtype=np.int32) - 1
    table, turns = np.full((len(own), max(len(deep), 1)), -1, np.int32), np.ones((len(own), max(len(deep), 1)), np.int8)
    for i, (node, sign) in enumerate(zip(deep, signs, strict=True)):
        table[:, i], turns[:, i] = np.where(node >= 0, number[node], -1), sign
    return Paths(top, table, turns, int(number[-1]) + 1)


def starts(ranks: np.ndarray, size: int, seed: int) -> np.ndarray:
    """First vectors, which follow from a word's rank and the seed, so that all parts start from the same ones."""
    out = np.empty((len(ranks), size), np.float32)
    for low in range(0, len(ranks), WORDS_OUT):
        x = ranks[low : low + WORDS_OUT].astype(np.uint64)[:, None] * np.uint64(size) + np.arange(size, dtype=np.uint64)
        x = (x + np.uint64((seed + 1) * 0xD1B54A32D192ED03 % 2**64)) * np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        out[low : low + WORDS_OUT] = ((x ^ (x >> np.uint64(31))) >> np.uint64(40)) / float(1 << 24) - 0.5
    out /= np.float32(size)
    return out


def _summed(rows: np.ndarray, first: np.ndarray) -> np.ndarray:
    """The sum of the rows from each of `first` to the next; most of these runs are short, which `np.add.reduceat` is slow for."""
    many = np.diff(first, append=len(rows))
    out, left = rows.take(first, 0), np.flatnonzero(many > 1)
    for i in range(1, SHORT):
        out[left] += rows.take(first[left] + i, 0)
        left = left[many[left] > i + 1]
    if len(left):
        rest = many[left] - SHORT
        at = np.cumsum(rest) - rest
        out[left] += np.add.reduceat(rows.take(np.repeat(first[left] + SHORT - at, rest) + np.arange(rest.sum()), 0), at)
    return out


def _move(rows: np.ndarray, at: np.ndarray, steps: np.ndarray, cells: np.ndarray, rates: np.ndarray) -> None:
    """Adds to each row the sum of its steps, which are in `cells` of `steps`, times their rates, cut to the length MOST_MOVE."""
    at, order = np.divmod(np.sort(at * np.int64(len(at)) + np.arange(len(at))), len(at))
    first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
    cells = cells.take(order)
    whole = _summed(steps.take(cells, 0) * rates.take(cells)[:, None], first)
    far = np.sqrt(np.einsum("ij,ij->i", whole, whole))
    whole *= np.minimum(np.float32(1), np.float32(MOST_MOVE) / np.maximum(far, np.float32(1e-12)))[:, None]
    at = at[first]
    rows[at] = rows.take(at, 0) + whole


def _slack(scores: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """weights / (1 + exp(scores)), in place of the scores; 0 where that overflows."""
    np.exp(scores, out=scores)
    scores += np.float32(1)
    return np.divide(weights, scores, out=scores)


def train(ids: np.ndarray, texts: np.ndarray, inner: np.ndarray, tree: Paths, window: int, iters: int, rng: np.random.Generator) -> None:
    """Moves the rows of `inner`, the vectors of the words, by all pairs of `ids` inside a text, `iters` times.

    `texts` is each place's text, counted from 0 to 254 again and again. `window` places before the first one, and `window`
    and a step after the last, are in no text (NONE).
    """
    size, step = inner.shape[1], BLOCK * BLOCKS
    n = len(ids) - 2 * window - step
    nodes = np.zeros((tree.n_nodes + 1, size), np.float32)  # the last stands for no node
    span = BLOCK + 2 * window
    apart = np.abs(np.arange(span)[None, :] - window - np.arange(BLOCK)[:, None])
    apart[apart == 0] = 2 * span  # a place is no neighbour of its own
    apart = apart.astype(np.int16)
    end = -(-n // step) * step
    base = np.arange(0, step, BLOCK)[:, None] + np.arange(span)
    for round_ in range(iters):
        reach = rng.integers(1, window + 1, end, dtype=np.uint8)
        reach[n:] = 0
        for low in range(0, end, step):
            rate = np.float32(max(RATE * (1 - (round_ * n + low) / (iters * n)), LEAST_RATE))
            near, own, told = ids[low + base], ids[low + window : low + window + step], texts[low + base]
            x = inner.take(near, 0)
            xt = x.transpose(0, 2, 1)
            pairs = np.zeros((BLOCKS, BLOCK + 1, span), np.float32)  # the last place of a block stands for none
            pairs[:, :BLOCK] = (apart <= reach[low : low + step].reshape(BLOCKS, BLOCK, 1)) & (told[:, None, :] == told[:, window : window + BLOCK, None])
            # top nodes, against all words of a block
            on = tree.top.take(own, 0).reshape(BLOCKS, BLOCK, TOP)
            to = pairs[:, :BLOCK].transpose(0, 2, 1)
            met = to @ np.abs(on).astype(np.float32)
            high = nodes[:TOP]
            g = to @ (on > 0).astype(np.float32) - _slack(x @ -high.T, met)
            to_x = g @ high
            to_high = (g.transpose(0, 2, 1) @ x).sum(0)
            most = np.minimum(rate, np.float32(MOST_RATE) / np.maximum(met.sum((0, 1)), np.float32(1)))
            # the other nodes, against the neighbours of their place
            rows = tree.deep.take(own, 0)
            found = np.flatnonzero(rows >= 0)
            if len(found):
                place = found // rows.shape[1]
                block = place // BLOCK
                many = np.bincount(block, minlength=BLOCKS)
                width = int(many.max())
                cell = np.arange(len(found)) + (np.arange(BLOCKS) * width - np.cumsum(many) + many).take(block)
                node, at = np.full(BLOCKS * width, tree.n_nodes), np.full(BLOCKS * width, BLOCK)
                sign = np.ones(BLOCKS * width, np.float32)
                node[cell], at[cell], sign[cell] = rows.ravel()[found], place + block, tree.signs.take(own, 0).ravel()[found]
                z = (nodes.take(node, 0) * sign[:, None]).reshape(BLOCKS, width, size)
                h = _slack(z @ xt, pairs.reshape(-1, span).take(at, 0).reshape(BLOCKS, width, span))
                to_x += h.transpose(0, 2, 1) @ z
                _move(nodes, node[cell], (h @ x).reshape(-1, size), cell, sign * rate)
            high += to_high * most[:, None]
            _move(inner, near.ravel(), to_x.reshape(-1, size), np.arange(near.size), np.full(near.size, rate))


def encoded(lists: pa.ListArray, words: pa.Array) -> pa.LargeBinaryArray:
    """Each text's ranks in the vocabulary as 4 bytes each; other words are left out before windows are laid."""
    found = pc.fill_null(pc.index_in(lists.flatten(), value_set=words), -1).to_numpy(zero_copy_only=False)
    many = pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False)
    known = np.concatenate([[0], np.cumsum(found >= 0)])[np.concatenate([[0], np.cumsum(many)])] * 4
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(lists), [None, pa.py_buffer(known), pa.py_buffer(found[found >= 0].astype("<i4"))])


def read(batches: Iterator[pa.RecordBatch], window: int) -> tuple[np.ndarray, np.ndarray]:
    """(ranks, texts) of the places of the encoded texts, as `train` asks for them; a block is too short for texts of the same number to meet."""
    ids, many = np.zeros(window, np.int32), [np.zeros(0, np.int64)]
    for batch in batches:
        cells = batch.column(0)
        many.append(pc.binary_length(cells).to_numpy(zero_copy_only=False) // 4)
        end = len(ids)
        ids.resize(end + many[-1].sum(), refcheck=False)  # grows in place, so that no part is held twice
        ids[end:] = np.frombuffer(b"".join(cells.to_pylist()), "<i4")
    ids.resize(len(ids) + window + BLOCK * BLOCKS, refcheck=False)
    many = np.concatenate(many)
    many = many[many > 0]
    texts = np.full(len(ids), NONE, np.uint8)
    texts[window : -window - BLOCK * BLOCKS] = np.repeat((np.arange(len(many)) % NONE).astype(np.uint8), many)
    return ids, texts


def numbered(ids: np.ndarray, texts: np.ndarray, n_words: int) -> np.ndarray:
    """The ranks that the part has; puts their numbers in place of the ranks in `ids`."""
    there, slices = np.zeros(n_words, bool), [slice(low, low + (1 << 20)) for low in range(0, len(ids), 1 << 20)]
    for part in slices:
        there[ids[part][texts[part] != NONE]] = True
    number = (np.cumsum(there, dtype=np.int32) - 1).clip(0)
    for part in slices:
        ids[part] = number.take(ids[part])
    return np.flatnonzero(there)


def free() -> None:
    """Gives back to the system what earlier work of this process has left, which counts against an executor."""
    pa.default_memory_pool().release_unused()
    if hasattr(libc := ctypes.CDLL(None), "malloc_trim"):
        libc.malloc_trim(0)


def fit(docs: DataFrame, tokens: str, size: int, window: int, min_count: int, iters: int, seed: int, parts: int) -> DataFrame:
    """(word, vector), cached: the mean of the vectors that the parts with the word have trained."""
    spark = docs.sparkSession
    words, counts = vocabulary(docs, tokens, min_count)
    known, tree = spark.sparkContext.broadcast(words), spark.sparkContext.broadcast(huffman(counts))

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.record_batch([batch.column(0), batch.column(1), encoded(batch.column(2), known.value).cast(pa.binary())], ["deal", "turn", "ranks"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        free()
        ids, texts = read(batches, window)
        own = numbered(ids, texts, len(known.value))
        if not len(own):
            return
        vectors, ways = starts(own, size, seed), paths(own, *tree.value)
        free()
        with np.errstate(over="ignore"):  # see _slack
            train(ids, texts, vectors, ways, window, iters, np.random.default_rng([seed, TaskContext.get().partitionId()]))
        for low in range(0, len(own), WORDS_OUT):
            some = vectors[low : low + WORDS_OUT]
            lists = pa.ListArray.from_arrays(np.arange(0, some.size + 1, size, dtype=np.int32), some.ravel())
            yield pa.record_batch([known.value.take(pa.array(own[low : low + WORDS_OUT])), lists], ["word", "vector"])

    # the deal and the order follow from the texts, so that a reloaded input gives the same result
    lists = docs.select(F.xxhash64(tokens).alias("deal"), F.xxhash64(tokens, F.lit(seed)).alias("turn"), tokens)
    dealt = lists.mapInArrow(encode, "deal long, turn long, ranks binary").repartition(parts, "deal").sortWithinPartitions("turn").select("ranks")
    trained = dealt.mapInArrow(run, "word string, vector array<float>")
    # dealt by word first: sums take four times the room of vectors; floats, as the order of a sum may change its last place
    mean = F.array(*[F.avg(F.get("vector", F.lit(i))).cast("float").cast("double") for i in range(size)])
    held = spark.conf.get(_BATCH)
    spark.conf.set(_BATCH, "1000")  # texts may be long
    try:
        out = trained.repartition("word").groupBy("word").agg(mean.alias("vector")).persist()
        out.write.format("noop").mode("overwrite").save()
    finally:
        spark.conf.set(_BATCH, held)
    return out
