"""What the operators of this subpackage share: staged tables, hashing, reading of inputs."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_GOLDEN = np.uint64(0x9E3779B97F4A7C15)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark: SparkSession) -> str:
    """A new folder under spark.checkpoint.dir, which every executor sees.

    Only a local session without that setting (a test) falls back to a temporary folder of this
    machine; a cluster without it is refused, as its executors would not share the folder.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.gettempdir() + "/causemine-scratch"
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


def staged(df: DataFrame, codec: str = "zstd", rows: int | None = None) -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: it cuts the lineage, survives
    lost executors, prunes columns, and gives the planner true sizes. rows: how many there are at
    most, of a narrow table; few rows then make few files."""
    spark = df.sparkSession
    df = df if rows is None else df.coalesce(1 + rows // FEW)
    path = scratch(spark)
    df.write.option("compression", codec).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: So many keys, those with the most rows, are joined by broadcast; any other has less than one in
#: HOT of the rows. Fewer rows than FEW are no burden to a task, even if one key has them all.
HOT, FEW = 1024, 1_000_000


def hot_join(left: DataFrame, right: DataFrame, key: list[str], how: str = "inner", n: int | None = None, few: int = FEW, sizes: str | None = None) -> DataFrame:
    """left, a table of n rows, joined to right, which has one row for each key at most: rows of hot
    keys meet right's rows by broadcast and stay where they are; the others are shuffled. sizes: a
    column of right, a table, that already tells how many rows of left a key has."""
    if sizes:
        counts = right.select(*key, F.col(sizes).alias("__c"))
    elif (left.count() if n is None else n) < few:
        return left.join(right, key, how)
    else:
        counts = left.groupBy(*key).agg(F.count("*").alias("__c"))
    top = counts.where(F.col("__c") >= few // 10).orderBy(F.desc("__c"), *key).limit(HOT).select(*key).collect()
    if not top:
        return left.join(right, key, how)
    hot = F.broadcast(left.sparkSession.createDataFrame(top, left.select(*key).schema))
    marked = left.join(hot.withColumn("__hot", F.lit(True)), key, "left")
    own = F.broadcast(right.join(hot, key, "left_semi"))
    return marked.where("__hot").drop("__hot").join(own, key, how).unionByName(marked.where("__hot is null").drop("__hot").join(right, key, how))


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def all_of(*conditions: Column) -> Column:
    return reduce(lambda a, b: a & b, conditions)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (splitmix64), over uint64 arrays."""
    with np.errstate(over="ignore"):
        x = x + _GOLDEN
        x = (x ^ (x >> np.uint64(30))) * _M1
        x = (x ^ (x >> np.uint64(27))) * _M2
        return x ^ (x >> np.uint64(31))


def rows(batches: Iterator[pa.RecordBatch], chunk: int = 512) -> Iterator[pa.RecordBatch]:
    """Batches of at most chunk rows, whatever Arrow's batch size is set to."""
    for batch in batches:
        for i in range(0, batch.num_rows, chunk):
            yield batch.slice(i, chunk)


def unsigned_crc32(column: Column | str) -> Column:
    return F.crc32(column).cast("long")
