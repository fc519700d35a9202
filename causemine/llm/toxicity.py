"""Operator 3: toxicity by a classifier chain.

The categories are those that `labels` has: first low quality (quality = 0), then toxic; any list of
0/1 label expressions can be given. The chain is fitted on the driver over a bounded sample of
labelled documents (`sample` in expectation, chosen by a hash of the id, of at most `longest`
characters each) and broadcast; its size is that of its vocabulary. Every whole text is scored where
it is read, however long it is.

Defined cases: a null or wordless text gets the probabilities of a text without telling words; without any labelled
document, or any toxic one, nothing is rejected; labels with nulls or without a document are not
used; of several labels of a document each category takes the greatest; repeated rows get the same result; an empty table gives an empty result; other columns are
left out of `score`, and pass through `clean` unchanged.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .classifier_chain import Chain, train
from .shared import table
from .tokens import by_bytes

CATEGORIES = {"low_quality": "1 - quality", "toxic": "toxic"}
SAMPLE, LONGEST = 5000, 50_000


def fit(docs: DataFrame, labels: DataFrame, categories: dict[str, str] = CATEGORIES, sample: int = SAMPLE, longest: int = LONGEST) -> Chain:
    """Learn from docs (doc_id, text) and labels (doc_id and what the categories' expressions need)."""
    names = list(categories)
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), *[F.expr(e).cast("int").alias(n) for n, e in categories.items()]).dropna().groupBy("doc_id").agg(*[F.max(n).alias(n) for n in names])
    n = known.count()
    draw = F.pmod(F.xxhash64(F.lit("sample"), "doc_id"), F.lit(1 << 30))
    chosen = known.where(draw <= int((1 << 30) * min(1.0, sample / max(1, n))))
    text = docs.where(F.col("doc_id").isNotNull() & (F.length("text") <= longest)).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string"))
    # The sample has a bound, so its side of the join does.
    found = text.join(F.broadcast(chosen), "doc_id").toPandas().sort_values(["doc_id", "text"]).drop_duplicates("text")
    return train(found["text"].tolist(), found[names].to_numpy(np.int64).reshape(len(found), len(names)), names)


def score(docs: DataFrame, chain: Chain) -> DataFrame:
    """doc_id, <category>_score for each category, toxic and kept (the last category decides)."""
    shared, names = docs.sparkSession.sparkContext.broadcast(chain), [f"{c}_score" for c in chain.categories]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in by_bytes(batches, most=2_000_000):
            p = own.predict(batch.column("text").to_pylist())
            out = p[:, -1] >= own.thresholds[-1]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(p[:, i]) for i in range(p.shape[1])], pa.array(out), pa.array(~out)], ["doc_id", *names, "toxic", "kept"])

    text = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return text.mapInArrow(run, ", ".join(["doc_id bigint", *[f"{n} double" for n in names], "toxic boolean", "kept boolean"]))


def clean(docs: DataFrame, chain: Chain) -> DataFrame:
    """The rows of docs that are not toxic, with all columns."""
    shared, at = docs.sparkSession.sparkContext.broadcast(chain), docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in by_bytes(batches, most=2_000_000):
            yield batch.filter(pa.array(own.predict(batch.column(at).to_pylist())[:, -1] < own.thresholds[-1]))

    return docs.mapInArrow(run, docs.schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return score(docs, fit(docs, table(spark, sf_dir, "labels")))
