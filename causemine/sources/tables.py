"""Reading and writing tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.prepare import merge_compact


def load(spark: SparkSession, folder: str, name: str, columns: list[str] | None = None, fmt: str = "parquet", **options) -> DataFrame:
    """A table of the folder, with the wanted columns only (the scan is pruned to them)."""
    df = spark.read.options(**options).format(fmt).load(f"{folder}/{name}.{fmt}")
    return df.select(*columns) if columns else df


def jdbc(spark: SparkSession, url: str, table: str, **options) -> DataFrame:
    """An operational store; its driver must be on the class path."""
    return spark.read.format("jdbc").options(url=url, dbtable=table, **options).load()


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None, mode: str = "overwrite") -> None:
    writer = df.write.format(fmt).mode(mode).option("partitionOverwriteMode", "dynamic")
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, key: str) -> None:
    """A table whose joins on the key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def put_day(compact: DataFrame, hot: str, day: str) -> None:
    """A day's compact table into the hot store, where it replaces what the day had."""
    compact.withColumn("day", F.lit(day)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("day").parquet(hot)


def archive_days(spark: SparkSession, hot: str, archive: str, before: str) -> None:
    """Copy the days before the given one from the hot store to the archive; the hot store may then drop them."""
    spark.read.parquet(hot).where(F.col("day").cast("string") < before).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("day").parquet(archive)


def compact_days(spark: SparkSession, hot: str, archive: str, first: str, last: str, kept_from: str) -> DataFrame:
    """The compact tables of the days from first to last, added up: days from kept_from on come from the
    hot store, older ones from the archive. Only the folders of these days are read, and a store
    that has none of them is not opened."""
    day = F.col("day").cast("string")
    parts = []
    if last >= kept_from:
        parts.append(spark.read.parquet(hot).where(day.between(max(first, kept_from), last)))
    if first < kept_from:
        parts.append(spark.read.parquet(archive).where(day.between(first, last) & (day < kept_from)))
    return merge_compact(*[p.drop("day") for p in parts])


def sampled(df: DataFrame, label: str, share: float, seed: int = 7) -> DataFrame:
    """All rows with the label and a share of the others, with `weight` so that sums estimate the whole."""
    found = df.sampleBy(F.col(label).cast("int"), {0: share, 1: 1.0}, seed)
    return found.withColumn("weight", F.when(F.col(label).cast("int") == 1, 1.0).otherwise(1.0 / share))
