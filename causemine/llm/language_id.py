"""Operator 5: language identification.

The model is fitted on the driver over a bounded sample of labelled texts (`per_label` for each of
the `languages` most frequent languages in expectation, chosen by a hash of the id, of at most
`longest` characters each; of these a bounded number of runs of words, spread over the text) and
broadcast: its size is that of the hashed table. Every whole text is then predicted where it is read,
however long it is.

Defined cases: a null text, or one without a letter, is `und` with score 0; without any labelled
text everything is `und`; repeated rows get the same result; an empty table gives an empty result;
other columns are left out.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .language_model import LanguageModel, train
from .shared import table
from .tokens import by_bytes

PER_LABEL, LANGUAGES, LONGEST = 500, 1000, 50_000


def held_out(doc_id: Column) -> Column:
    """The third of the documents that nothing is learned from."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % 3 == 1, F.lit(False))


def fit(docs: DataFrame, per_label: int = PER_LABEL, languages: int = LANGUAGES, longest: int = LONGEST) -> LanguageModel:
    """Learn from text and lang of docs (doc_id, text, lang)."""
    usable = docs.where(F.col("lang").isNotNull() & (F.length("text") <= longest)).select(F.col("doc_id").cast("long"), F.col("lang").cast("string"), F.col("text").cast("string"))
    counts = usable.groupBy("lang").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "lang").limit(languages)
    draw = F.pmod(F.xxhash64(F.lit("sample"), "doc_id"), F.lit(1 << 30))
    # As many rows as languages, which have a bound.
    chosen = usable.join(F.broadcast(counts), "lang").where(draw <= (1 << 30) * F.least(F.lit(1.0), per_label / F.col("n")))
    sample = chosen.toPandas().sort_values(["doc_id", "text", "lang"])
    return train(sample["text"].tolist(), sample["lang"].tolist())


def identify(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """doc_id, lang_pred, score, accepted (score at or above the calibrated rejection bound)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in by_bytes(batches, most=1_500_000):
            names, score = own.predict([t or "" for t in batch.column("text").to_pylist()])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(names, pa.string()), pa.array(score), pa.array((score >= own.least) & (score > 0))], ["doc_id", "lang_pred", "score", "accepted"])

    text = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return text.mapInArrow(run, "doc_id bigint, lang_pred string, score double, accepted boolean")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = fit(docs.where(~held_out(F.col("doc_id"))))
    return identify(docs, model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score", "accepted")
