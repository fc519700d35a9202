"""Operator 8: the main text of web pages by tree scoring.

Pages are parsed one at a time where they are read; nothing is shuffled.

Defined cases: a null or empty page, and one without text, has an empty text; broken, unclosed and
cut-off markup is read as far as it goes; repeated rows give repeated results; an empty table gives
an empty result; other columns are left out.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .html_tree import main_text
from .shared import table
from .tokens import by_bytes


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url and the main text of pages (page_id, url, html)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in by_bytes(batches, "html"):
            texts = pa.array(list(map(main_text, batch.column("html").to_pylist())), pa.string())
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), texts], ["page_id", "url", "text"])

    kept = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.col("html").cast("string"))
    return kept.mapInArrow(run, "page_id bigint, url string, text string")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages")).withColumn("n_chars", F.length("text").cast("long"))
