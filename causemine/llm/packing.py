"""Operator 2: best-fit decreasing packing of documents into windows of a fixed length.

Documents are cut into full windows first; what remains of each is placed, longest first, into the
open window with the least room that still holds it, found by a segment tree over the capacities.
Packing is done in blocks: a block is a run of documents of one input partition with a bounded
number of remaining ids, so a task holds no more than that and nothing is shuffled. A lost task
makes the same pieces again.

Defined cases: a null or empty text has the end id alone; rows with an equal doc_id are documents
of their own; an empty table gives no pieces; other columns are left out.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import table
from .tokens import by_bytes, pre_tokenizer

_PIECES = "doc_id bigint, start bigint, length bigint, ids binary, doc_tokens bigint, sequence_id bigint, offset bigint"


class Capacities:
    """Open windows by the room they have left; finds the least room that is enough.

    Leaf r holds the windows with r ids of room; an inner node tells whether a leaf below it has any.
    """

    def __init__(self, window: int) -> None:
        self.width = 1 << window.bit_length()
        self.some = bytearray(2 * self.width)
        self.open: list[list[int]] = [[] for _ in range(window + 1)]

    def put(self, room: int, window: int) -> None:
        self.open[room].append(window)
        i = room + self.width
        while i and not self.some[i]:
            self.some[i] = 1
            i >>= 1

    def take(self, need: int) -> tuple[int, int] | None:
        """The room and the number of the tightest window with at least `need` ids of room."""
        i = need + self.width
        if not self.some[i]:
            while i > 1 and (i & 1 or not self.some[i + 1]):  # up until a right neighbour has some
                i >>= 1
            if i <= 1:
                return None
            i += 1
            while i < self.width:  # down to its least leaf
                i = 2 * i if self.some[2 * i] else 2 * i + 1
        room = i - self.width
        window = self.open[room].pop()
        if not self.open[room]:
            self.some[i] = 0
            i >>= 1
            while i and not (self.some[2 * i] or self.some[2 * i + 1]):
                self.some[i] = 0
                i >>= 1
        return room, window


def best_fit_decreasing(lengths: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Window number and offset of each length (1 to window), and how many windows there are."""
    number, offset = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    free, used = Capacities(window), 0
    for i in np.argsort(-np.asarray(lengths), kind="stable").tolist():
        n = int(lengths[i])
        room, w = free.take(n) or (window, used)
        used = max(used, w + 1)
        number[i], offset[i] = w, window - room
        if room > n:
            free.put(room - n, w)
    return number, offset, used


def pack(docs: DataFrame, path: str, end: int, window: int = 4096, block_ids: int = 1 << 20) -> DataFrame:
    """Pieces of docs (doc_id, text): which ids (little-endian unsigned 32-bit) go to which place
    of which sequence.

    sequence_id is the number of the input partition times 2**32 plus the number of the sequence
    there. block_ids bounds the remaining ids that a task holds at once.
    """
    names = [x.split()[0] for x in _PIECES.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer, sequence = pre_tokenizer(path), TaskContext.get().partitionId() << 32
        stop = np.array([end], "<u4")
        rest: list[tuple] = []
        held = 0

        def out(pieces: list[tuple]) -> pa.RecordBatch:
            columns = list(zip(*pieces, strict=True))
            kinds = [pa.binary() if n == "ids" else pa.int64() for n in names]
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)

        def packed() -> list[tuple]:
            nonlocal sequence
            number, offset, used = best_fit_decreasing(np.array([p[2] for p in rest]), window)
            placed = [(*p, sequence + w, o) for p, w, o in zip(rest, number.tolist(), offset.tolist(), strict=True)]
            sequence += used
            return placed

        for batch in by_bytes(batches, most=4_000_000):
            full: list[tuple] = []
            for doc, ids in zip(batch.column("doc_id").to_pylist(), tokenizer.ids_of(batch.column("text")), strict=True):
                ids = np.concatenate((ids.astype("<u4"), stop))
                whole = len(ids) // window * window
                for start in range(0, whole, window):
                    full.append((doc, start, window, ids[start : start + window].tobytes(), len(ids), sequence, 0))
                    sequence += 1
                if whole < len(ids):
                    rest.append((doc, whole, len(ids) - whole, ids[whole:].tobytes(), len(ids)))
                    held += len(ids) - whole
            if full:
                yield out(full)
            if held >= block_ids:
                yield out(packed())
                rest, held = [], 0
        if rest:
            yield out(packed())

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, _PIECES)


def padded(length: Column, window: int = 4096) -> Column:
    """What a sequence of so many ids takes up: the window, but for a power of two."""
    return F.when(F.bit_count(length) == 1, length).otherwise(F.lit(window))


def digest(pieces: DataFrame) -> DataFrame:
    return pieces.select("doc_id", "start", "length", F.crc32("ids").cast("long").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(pack(table(spark, sf_dir, "documents"), "word_bpe_49k.json", end=2))
