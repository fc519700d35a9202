"""Operator 9: token ids in binary files, coded by a static range asymmetric numeral system.

A folder holds three Parquet tables: `table` (the shared frequencies, one row for each id),
`blocks` (file, block, the documents with their sizes, the coded payload) and `manifest` (file,
block, how many ids lie before it). Files follow in ascending doc_id order, blocks within a file
too. A block is a whole row, coded on its own, so readers decode blocks in parallel; it carries
checkpoints and a checksum.

Defined cases: a null text is empty and has only the end id; rows with an equal doc_id are written
one after the other, in the order of a hash of their texts; a null doc_id comes first; an empty table gives
an empty folder of the same form; other columns are left out.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import rans
from .shared import partitions, scratch, staged, table
from .tokens import by_bytes, pre_tokenizer

_IDS = "file int, block int, docs array<bigint>, sizes array<bigint>, n bigint, ids binary"
_BLOCKS = "file int, block int, docs array<bigint>, sizes array<bigint>, payload binary"


def tokenised(docs: DataFrame, path: str, end: int, block_ids: int = 1 << 18) -> DataFrame:
    """Blocks of plain ids: one range partition is one file, one block is about block_ids ids of
    whole documents."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer, file, block = pre_tokenizer(path), TaskContext.get().partitionId(), 0
        stop = np.array([end], tokenizer.dtype)
        docs: list = []
        held: list = []
        sizes: list[int] = []
        waiting = 0

        def row():
            ids = np.concatenate(held)
            return pa.RecordBatch.from_pylist([{"file": file, "block": block, "docs": docs, "sizes": sizes, "n": len(ids), "ids": ids.tobytes()}], schema=schema)

        for batch in by_bytes(batches):
            for doc, ids in zip(batch.column("doc_id").to_pylist(), tokenizer.ids_of(batch.column("text")), strict=True):
                docs.append(doc)
                sizes.append(len(ids) + 1)
                held += [ids, stop]
                waiting += len(ids) + 1
                if waiting >= block_ids:
                    yield row()
                    docs, held, sizes, waiting, block = [], [], [], 0, block + 1
        if docs:
            yield row()

    schema = pa.schema([("file", pa.int32()), ("block", pa.int32()), ("docs", pa.list_(pa.int64())), ("sizes", pa.list_(pa.int64())), ("n", pa.int64()), ("ids", pa.binary())])
    text = docs.select(F.col("doc_id").cast("long"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    # Rows with an equal doc_id, or none, may fall into several files: a hash of the text parts them.
    dealt = text.withColumn("tie", F.xxhash64("text")).repartitionByRange(partitions(docs.sparkSession), "doc_id", "tie")
    return dealt.sortWithinPartitions("doc_id", "tie", "text").select("doc_id", "text").mapInArrow(cut, _IDS)


def write(docs: DataFrame, folder: str, path: str, end: int, block_ids: int = 1 << 18) -> None:
    """Tokenise docs (doc_id, text) with the vocabulary file at path and write the folder.

    Both passes after the first read the staged ids, not the texts. Only the vocabulary's table of
    counts comes to the driver and is broadcast: its size is that of the vocabulary.
    """
    spark = docs.sparkSession
    tokenizer = pre_tokenizer(path)
    dtype, size = tokenizer.dtype, max(tokenizer.library.get_vocab_size(with_added_tokens=True), end + 1)
    ids = staged(tokenised(docs, path, end, block_ids), codec="none")  # ids hardly compress

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size, np.int64)
        for batch in batches:
            for value in batch.column("ids"):
                total += np.bincount(np.frombuffer(value.as_buffer(), dtype), minlength=size)
        found = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(found, pa.int32()), pa.array(total[found])], ["id", "n"])

    counts = np.zeros(size, np.int64)
    for row in ids.select("ids").mapInArrow(count, "id int, n bigint").groupBy("id").agg(F.sum("n").alias("n")).toLocalIterator():
        counts[row["id"]] = row["n"]
    frequencies = rans.normalised(counts)
    shared = spark.sparkContext.broadcast(frequencies)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = _table(shared)
        for batch in batches:
            for i in range(batch.num_rows):
                own = batch.slice(i, 1)
                payload = rans.encode(np.frombuffer(own.column("ids")[0].as_buffer(), dtype), coder)
                yield pa.RecordBatch.from_arrays([own.column(c) for c in ("file", "block", "docs", "sizes")] + [pa.array([payload], pa.binary())], ["file", "block", "docs", "sizes", "payload"])

    plain = lambda df: df.write.option("compression", "none")  # noqa: E731  the payload is compressed already
    plain(ids.select("file", "block", "docs", "sizes", "ids").mapInArrow(encode, _BLOCKS)).parquet(f"{folder}/blocks")
    spark.createDataFrame([(i, int(f)) for i, f in enumerate(frequencies)], "id int, f bigint").coalesce(1).write.parquet(f"{folder}/table")
    # A file has few blocks, and there are as many files as partitions: both windows are small.
    of_file = ids.groupBy("file").agg(F.sum("n").alias("n"))
    before = of_file.select("file", (F.sum("n").over(W.orderBy("file")) - F.col("n")).alias("before"))
    within = ids.select("file", "block", "n", (F.sum("n").over(W.partitionBy("file").orderBy("block")) - F.col("n")).alias("own"))
    within.join(before, "file").select("file", "block", (F.col("before") + F.col("own")).alias("start"), "n").write.parquet(f"{folder}/manifest")
    shared.unpersist()


_tables: dict[int, rans.Table] = {}


def _table(shared) -> rans.Table:
    """A worker keeps the last table it made."""
    if (key := zlib.crc32(np.asarray(shared.value, "<u8").tobytes())) not in _tables:
        _tables.clear()
        _tables[key] = rans.Table(shared.value)
    return _tables[key]


def read(spark: SparkSession, folder: str) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens, ids (little-endian unsigned 32-bit)."""
    f = {r["id"]: r["f"] for r in spark.read.parquet(f"{folder}/table").toLocalIterator()}
    shared = spark.sparkContext.broadcast(np.array([f[i] for i in range(len(f))], np.int64))
    names = ["file", "block", "doc_id", "own", "n_tokens", "ids"]

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = _table(shared)
        for batch in batches:
            for file, block, docs, sizes, payload in zip(*(batch.column(c) for c in ("file", "block", "docs", "sizes", "payload")), strict=True):
                ids, sizes = rans.decode(payload.as_buffer().to_pybytes(), coder).astype("<u4"), np.array(sizes.as_py(), np.int64)
                ends = np.cumsum(sizes)
                if ends[-1] != len(ids):
                    raise ValueError("a block's documents do not add up to its ids")
                data = pa.BinaryArray.from_buffers(pa.large_binary(), len(sizes), [None, pa.py_buffer(np.concatenate(([0], 4 * ends)).astype(np.int64).tobytes()), pa.py_buffer(ids.tobytes())]).cast(pa.binary())
                n = len(sizes)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(n, file.as_py(), np.int32)), pa.array(np.full(n, block.as_py(), np.int32)), docs.values, pa.array(ends - sizes), pa.array(sizes), data], names)

    found = spark.read.parquet(f"{folder}/blocks").mapInArrow(decode, "file int, block int, doc_id bigint, own bigint, n_tokens bigint, ids binary")
    manifest = spark.read.parquet(f"{folder}/manifest").select("file", "block", "start")
    return found.join(manifest, ["file", "block"]).select("doc_id", (F.col("start") + F.col("own")).alias("start"), "n_tokens", "ids")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = scratch(spark)
    write(table(spark, sf_dir, "documents"), folder, "byte_bpe_50k.json", end=2)
    return read(spark, folder).select("doc_id", "start", "n_tokens", F.crc32("ids").cast("long").alias("ids_crc32"))
