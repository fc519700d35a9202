"""Operator 4: token counts without ids.

The pieces of a pre-token are counted once for each distinct pre-token of the corpus. Documents
give their pre-token frequencies, which are joined to these counts and summed. The join has two
parts by a bound that holds for any corpus: of N pre-tokens, at most `head` distinct ones can occur
N / head times or more; these are broadcast and joined where the documents are read. Rarer ones go
through a shuffle, in which no key has more rows than that quotient.

Defined cases: a null text counts as empty (0 tokens, 0 bytes); rows with an equal doc_id are
counted each on its own; an empty table gives an empty result; other columns are left out.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import staged, table
from .tokens import by_bytes, pre_tokenizer

_SEEN = "pre_token string, freq bigint"


def pre_token_counts(docs: DataFrame, path: str, flush: int = 400_000) -> DataFrame:
    """Each distinct pre-token of the texts, how often it occurs, and how many pieces it has."""

    def seen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer = pre_tokenizer(path)
        total: dict[str, int] = {}
        out = lambda: pa.RecordBatch.from_arrays([pa.array(list(total), pa.string()), pa.array(list(total.values()), pa.int64())], ["pre_token", "freq"])
        for batch in by_bytes(batches):
            _, found, names = tokenizer.frequencies(batch.column("text"))
            for name, n in zip(names, np.bincount(found, minlength=len(names)).tolist(), strict=True):
                total[name] = total.get(name, 0) + n
            if len(total) >= flush:
                yield out()
                total = {}
        if total:
            yield out()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer = pre_tokenizer(path)
        for batch in batches:
            pieces = tokenizer.counts(batch.column("pre_token"))
            yield pa.RecordBatch.from_arrays([batch.column("pre_token"), batch.column("freq"), pa.array(pieces, pa.int64())], ["pre_token", "freq", "pieces"])

    text = docs.select(F.col("text").cast("string"))
    return text.mapInArrow(seen, _SEEN).groupBy("pre_token").agg(F.sum("freq").alias("freq")).mapInArrow(count, f"{_SEEN}, pieces bigint")


def count_tokens(docs: DataFrame, path: str, head: int = 1_000_000) -> DataFrame:
    """doc_id, n_bytes, n_tokens of docs (doc_id, text), a row for each row."""
    spark = docs.sparkSession
    counts = staged(pre_token_counts(docs, path))
    n = counts.agg(F.sum("freq")).first()[0] or 0
    often = -(-n // head)
    known = {r["pre_token"]: r["pieces"] for r in counts.where(F.col("freq") >= often).toLocalIterator()}
    shared = spark.sparkContext.broadcast(known)  # at most `head` entries
    names = ["row", "doc_id", "n_bytes", "base", "pre_token", "freq"]

    def join_head(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer, pieces, row = pre_tokenizer(path), shared.value, TaskContext.get().partitionId() << 40
        for batch in by_bytes(batches):
            n = batch.num_rows
            docs, found, words = tokenizer.frequencies(batch.column("text"))
            own = list(map(pieces.get, words))
            value = np.array([0 if x is None else x for x in own], np.int64)[found] if words else np.empty(0, np.int64)
            base = np.bincount(docs, weights=value, minlength=n).astype(np.int64)
            # A text's rare pre-tokens; its first row carries what is summed already, its id and size.
            rare = np.flatnonzero(np.fromiter((x is None for x in own), bool, len(own))[found]) if words else np.empty(0, np.int64)
            pairs, freq = np.unique(docs[rare] * max(1, len(words)) + found[rare], return_counts=True)
            doc, word = np.divmod(pairs, max(1, len(words)))
            alone = np.setdiff1d(np.arange(n), doc)  # texts without any
            first = np.concatenate((np.diff(doc, prepend=-1) != 0, np.ones(len(alone), bool)))
            doc = np.concatenate((doc, alone))
            keys = pa.concat_arrays([pa.array(words, pa.string()).take(pa.array(word)), pa.nulls(len(alone), pa.string())])
            size = pc.fill_null(pc.binary_length(batch.column("text")), 0).to_numpy()
            yield pa.RecordBatch.from_arrays(
                [pa.array(row + doc), batch.column("doc_id").take(pa.array(doc, mask=~first)), pa.array(size[doc].astype(np.int64), mask=~first), pa.array(np.where(first, base[doc], 0)), keys, pa.array(np.concatenate((freq, np.zeros(len(alone), np.int64))))], names)
            row += n

    # `row` tells rows with an equal doc_id apart.
    pairs = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(join_head, "row bigint, doc_id bigint, n_bytes bigint, base bigint, pre_token string, freq bigint")
    # A text without rare pre-tokens gets a key that no pre-token has, so that such rows spread.
    key = F.coalesce("pre_token", F.concat(F.lit("\u0000 \u0000"), F.col("row").cast("string")))
    rare = counts.where(F.col("freq") < often).select("pre_token", "pieces")
    joined = pairs.withColumn("pre_token", key).join(rare, "pre_token", "left")
    total = F.sum(F.col("base") + F.col("freq") * F.coalesce("pieces", F.lit(0)))
    return joined.groupBy("row").agg(F.max("doc_id").alias("doc_id"), F.max("n_bytes").alias("n_bytes"), total.alias("n_tokens")).drop("row")


def query(spark: SparkSession, sf_dir: str, limit: int = 512) -> DataFrame:
    counted = count_tokens(table(spark, sf_dir, "documents"), "byte_bpe_50k.json")
    return counted.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
