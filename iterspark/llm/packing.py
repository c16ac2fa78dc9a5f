"""Cost-balanced packing of tokenised documents into sequences.

A piece of n tokens costs `linear` * n + `quadratic` * n^2, the shape of a
transformer's work on it. Every document is cut into pieces that fill whole
sequences and one rest. The rests of a block of documents go, dearest first, to
the sequence of lowest cost that has room for them; where none has room a rest is
cut, its head filling the emptiest sequence. A block has just so many sequences
as its tokens fill, so all end full. What a partition has left over in the end
goes into sequences of a power of two, which need no padding.

Each task packs the rows it reads, so nothing is shuffled, and a task that is run
again gives the same pieces. Sequence ids hold the task's number in their upper
bits.

Defined results: a null or empty text is its end token alone. Repeated rows are
packed each. An empty table gives none. Very long texts are tokenised whole.
Columns other than the id and the text are not read.
"""

from __future__ import annotations

import base64
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from iterspark.llm.common import short_batches

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, cost double"


#: The special token that the JSON file declares, and its id.
SPECIAL = {"<|endoftext|>": 50256}


class Encoder:
    """Byte-level BPE ids, from the ranks of the vocabulary that the JSON file holds.

    As with the vocabulary's own settings, the string of its one special token is one id.
    """

    def __init__(self, ranks_path: str):
        import public_tokenizers
        import tiktoken

        with open(ranks_path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.own = tiktoken.Encoding("packing", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=SPECIAL)

    def ids(self, text: str, end: int) -> np.ndarray:
        return np.append(np.asarray(self.own.encode(text, allowed_special="all"), dtype="<u4"), np.array([end], dtype="<u4"))


def assign(lengths: np.ndarray, capacity: int, linear: float, quadratic: float) -> list[tuple[int, int, int, int, int]]:
    """(rest, start in it, length, sequence, offset) of a block whose lengths sum to a multiple of `capacity`."""
    n = int(lengths.sum()) // capacity
    if not n:
        return []
    room, cost, out = np.full(n, capacity), np.zeros(n), []

    def put(i: int, start: int, length: int, s: int) -> None:
        out.append((i, start, length, s, capacity - int(room[s])))
        room[s] -= length
        cost[s] += linear * length + quadratic * length * length

    for i in np.argsort(-lengths, kind="stable"):
        start, left = 0, int(lengths[i])
        while left:
            s = int(np.argmin(np.where(room >= left, cost, np.inf)))
            if room[s] >= left:
                put(int(i), start, left, s)
                break
            s = int(np.argmax(room))
            part = int(room[s])
            put(int(i), start, part, s)
            start, left = start + part, left - part
    return out


class _Packer:
    def __init__(self, capacity: int, linear: float, quadratic: float, task: int):
        self.capacity, self.linear, self.quadratic = capacity, linear, quadratic
        self.next = task << 33
        self.rests: list[tuple] = []  # doc_id, ids, start, doc_tokens
        self.rows: list[tuple] = []

    def piece(self, doc, ids: np.ndarray, start: int, total: int, sequence: int, offset: int) -> None:
        n = len(ids)
        self.rows.append((doc, start, n, zlib.crc32(ids.tobytes()), total, sequence, offset, self.linear * n + self.quadratic * n * n))

    def add(self, doc, ids: np.ndarray) -> None:
        whole = len(ids) - len(ids) % self.capacity
        for start in range(0, whole, self.capacity):
            self.piece(doc, ids[start : start + self.capacity], start, len(ids), self.next, 0)
            self.next += 1
        if whole < len(ids):
            self.rests.append((doc, ids[whole:].copy(), whole, len(ids)))

    def flush(self, last: bool) -> None:
        """Pack the rests; what does not fill a sequence waits for the next block."""
        over = sum(len(r[1]) for r in self.rests) % self.capacity
        wait: list[tuple] = []
        while over:
            doc, ids, start, total = self.rests.pop()
            if len(ids) > over:
                self.rests.append((doc, ids[: len(ids) - over], start, total))
                doc, ids, start = doc, ids[len(ids) - over :], start + len(ids) - over
            wait.append((doc, ids, start, total))
            over -= len(ids)
        base = self.next
        for i, at, n, s, offset in assign(np.array([len(r[1]) for r in self.rests], dtype=np.int64), self.capacity, self.linear, self.quadratic):
            doc, ids, start, total = self.rests[i]
            self.piece(doc, ids[at : at + n], start + at, total, base + s, offset)
            self.next = max(self.next, base + s + 1)
        self.rests = wait
        if last:
            self.end()

    def end(self) -> None:
        """The last tokens, in sequences of falling powers of two."""
        left, room, offset = sum(len(r[1]) for r in self.rests), 0, 0
        for doc, ids, start, total in self.rests:
            at = 0
            while at < len(ids):
                if not room:
                    room, offset = 1 << (left.bit_length() - 1), 0
                    sequence, self.next = self.next, self.next + 1
                n = min(room, len(ids) - at)
                self.piece(doc, ids[at : at + n], start + at, total, sequence, offset)
                at, room, offset, left = at + n, room - n, offset + n, left - n
        self.rests = []

    def take(self) -> Iterator[list[tuple]]:
        if self.rows:
            rows, self.rows = self.rows, []
            yield rows


def pack(
    docs: DataFrame,
    ranks_path: str,
    *,
    doc_id: str = "doc_id",
    text: str = "text",
    capacity: int = 1024,
    linear: float = 1.0,
    quadratic: float = 1.0 / 1024,
    end_id: int = 0,
    block_rests: int = 2048,
) -> DataFrame:
    """A row for each piece; `cost` is the piece's estimate. `capacity`: a power of two."""
    names = [x.strip().split()[0] for x in PIECES.split(",")]
    types = [pa.int64()] * 7 + [pa.float64()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(ranks_path)
        packer = _Packer(capacity, linear, quadratic, TaskContext.get().partitionId())

        def out() -> Iterator[pa.RecordBatch]:
            for rows in packer.take():
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)

        for b in batches:
            for doc, words in zip(b.column(0), b.column(1), strict=True):
                packer.add(doc.as_py(), encoder.ids(words.as_py() or "", end_id))
                if len(packer.rests) >= block_rests:
                    packer.flush(last=False)
                if len(packer.rows) >= 20_000:
                    yield from out()
        packer.flush(last=True)
        yield from out()

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, PIECES)


def sequence_costs(pieces: DataFrame, capacity: int = 1024) -> DataFrame:
    """Of each sequence: tokens, padding and cost."""
    tokens = F.sum("length")
    exact = F.pow(F.lit(2.0), F.floor(F.log2(tokens)))
    return pieces.groupBy("sequence_id").agg(tokens.alias("tokens"), F.when(exact == tokens, 0).otherwise(capacity - tokens).cast("long").alias("padding"), F.sum("cost").alias("cost"))


def default_ranks() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents (last stage)."""
    short_batches(spark)
    return pack(docs, default_ranks())
