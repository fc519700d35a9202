"""From raw documents to packed training sequences, in five stages.

Each stage takes (spark, docs, sf_dir) and works on all that the one before it kept; all but the
last return the columns of documents. A stage's result is written as Parquet and read again.

In every stage an empty table gives an empty result of the same columns, whole texts are looked at
however long they are, and columns beside doc_id, text, lang, source and n_chars, whatever their
names, pass through unchanged.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from causemine.llm import decontamination, near_dedup, packing, quality_rules, toxicity
from causemine.llm.shared import scratch, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier chain rejects go. It learns from a bounded sample of all labelled
    documents. A null or empty text has nothing that tells and stays; rows that repeat a document go
    or stay together, as do those with an equal text; a probability at the threshold rejects."""
    chain = toxicity.fit(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return toxicity.clean(docs, chain)


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base rules or their group's fences go: so a null or empty text, which
    has no words. A null lang or source is a group of its own; rows that repeat a document go or stay
    together; a measure on its fence stays."""
    return quality_rules.keep(docs)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays, the one with the least id: five words a shingle, similarity 0.8
    or more. Of rows that repeat a doc_id one stays, with the least text; texts without words, and
    rows without a doc_id, are in no group and stay."""
    return near_dedup.deduplicated(docs)


def remove_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Contaminated documents lose the passages, or go where more than half of their words are hit.
    A null or empty text is not contaminated; repeated rows are treated alike."""
    return decontamination.cleaned(docs, table(spark, sf_dir, "benchmark"))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of the packed sequences. A null or empty text is its end id; repeated rows are
    documents of their own."""
    return packing.digest(packing.pack(docs, "word_bpe_49k.json", end=2))


STAGES = [
    ("toxicity", drop_toxic),
    ("quality rules", keep_quality),
    ("near-duplicates", drop_near_duplicates),
    ("benchmark decontamination", remove_benchmark),
    ("packing", pack_sequences),
]

#: Classifiers, MinHash and tokenizers are beyond SQL; tests/llm/test_pipeline.py holds the stages
#: against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        path = scratch(spark)
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
