"""The stream front end: events flow into windowed weights, closed windows into the miner.

Every flow reads a folder of Parquet files as a stream. The registered queries run to the end of
what is there (available-now) and read the sink back as a batch.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import Config
from ..operators import monitor, prepare
from ..plans import planner
from ..plans.staging import folder, staged
from ..sources.tables import load

_TIME = "yyyy-MM-dd HH:mm:ss.SSSSSS"


def events(spark: SparkSession, d: str, per_trigger: int = 16) -> DataFrame:
    """The events as a stream with an event time that a watermark can use. The table may be one file
    or a folder of part files; the pattern, which matches its name alone, lets a stream read either."""
    schema = load(spark, d, "events").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(f"{d}/event[s].parquet")
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def finished(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run the stream over what is there, and what its sink then holds. Each batch is written under
    its number, so a batch that runs again after a failure replaces its own output."""
    spark, at = df.sparkSession, folder(df.sparkSession)

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out/{'last' if mode == 'complete' else number}")

    query = df.writeStream.outputMode(mode).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).foreachBatch(put).start()
    query.awaitTermination()
    return spark.read.schema(df.schema).option("recursiveFileLookup", "true").parquet(f"{at}/out")


def windowed(stream: DataFrame, dims: list[str], width: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Weights of each tuple of dims in tumbling or sliding windows; later rows than the watermark
    are not counted once their window is closed."""
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width, slide or width), *dims).agg(F.count("*").alias("n"))


def sessions(stream: DataFrame, key: str, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), key).agg(F.count("*").alias("n"))


def unique(stream: DataFrame, key: str) -> DataFrame:
    """The first row of each key, in whatever order and however late rows come; the state holds every
    key (a narrow row each), as nothing bounds how far apart two copies may be."""
    return stream.dropDuplicates([key])


def preceded(errors: DataFrame, clicks: DataFrame, key: str, within: str = "10 minutes", late: str = "1 hour") -> DataFrame:
    """Errors with the clicks of the same user shortly before (a stream-stream interval join)."""
    a = errors.withWatermark("ts", late).alias("a")
    b = clicks.withWatermark("ts", late).alias("b")
    return a.join(b, F.expr(f"a.{key} = b.{key} and b.ts <= a.ts and b.ts >= a.ts - interval {within}"))


def tumbling(spark: SparkSession, d: str) -> DataFrame:
    found = finished(windowed(events(spark, d), ["event_type"], "1 day"), "complete")
    return found.select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n")


def dedup(spark: SparkSession, d: str) -> DataFrame:
    return finished(unique(events(spark, d), "event_id").select("event_id")).agg(F.count("*").alias("n"))


def enriched(spark: SparkSession, d: str) -> DataFrame:
    """Stream rows get a dimension's attributes; the dimension is read once for each batch."""
    own = events(spark, d).join(load(spark, d, "customer", ["c_custkey", "c_mktsegment"]), F.expr("user_id = c_custkey"))
    return finished(own.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count("*").alias("n")), "complete")


def sliding(spark: SparkSession, d: str) -> DataFrame:
    found = finished(windowed(events(spark, d), ["event_type"], "6 hours", "1 hour"), "complete")
    return found.select(F.date_format("window.start", _TIME).alias("start"), "event_type", "n")


def by_session(spark: SparkSession, d: str) -> DataFrame:
    found = finished(sessions(events(spark, d), "user_id"), "complete")
    return found.select("user_id", F.date_format("session_window.start", _TIME).alias("start"), "n")


def before_errors(spark: SparkSession, d: str) -> DataFrame:
    """Errors with the views of the same user in the hour before: two streams, each with a watermark."""
    kind = lambda k: events(spark, d).where(F.col("event_type") == k).select("event_id", "user_id", "ts")
    both = preceded(kind("error"), kind("view"), "user_id", "1 hour", late="40 days")
    return finished(both.select(F.col("a.event_id").alias("error_id"), F.col("b.event_id").alias("view_id")))


def late_rows(batches: DataFrame, key: str = "event_id", late: str = "1 hour") -> DataFrame:
    """Which rows of a stream come later than its watermark, in a table beside the stream: key, ts, late.

    A batch is held against the greatest event time of the batches before it, which the batches have
    written under their numbers; so a batch that runs again after a failure finds the same.
    """
    spark, at = batches.sparkSession, folder(batches.sparkSession)
    times = "number long, top timestamp"

    def put(batch: DataFrame, number: int) -> None:
        known = spark.createDataFrame([], times) if number == 0 else spark.read.schema(times).option("recursiveFileLookup", "true").parquet(f"{at}/times")
        limit = known.where(F.col("number") < number).agg((F.max("top") - F.expr(f"INTERVAL {late}")).alias("limit"))  # one row
        marked = batch.select(key, "ts").crossJoin(F.broadcast(limit))
        marked.select(key, "ts", F.coalesce(F.col("ts") < F.col("limit"), F.lit(False)).alias("late")).write.mode("overwrite").parquet(f"{at}/out/{number}")
        batch.agg(F.lit(number).cast("long").alias("number"), F.max("ts").alias("top")).write.mode("overwrite").parquet(f"{at}/times/{number}")

    batches.writeStream.option("checkpointLocation", f"{at}/state").trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    return spark.read.option("recursiveFileLookup", "true").parquet(f"{at}/out")


def arriving(spark: SparkSession, d: str) -> DataFrame:
    """The events as they might arrive: in four lots of eight days, every fifth event one lot late."""
    lot = F.least(F.lit(3), F.floor((F.dayofmonth("ts") - 1) / 8) + F.when(F.col("event_id") % 5 == 0, 1).otherwise(0)).cast("int")
    rows = load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).withColumn("lot", lot)
    at = folder(spark)
    for k in range(4):  # files are read in the order of their times
        rows.where(F.col("lot") == k).drop("lot").coalesce(1).write.mode("append").parquet(at)
    return spark.readStream.schema(rows.drop("lot").schema).option("maxFilesPerTrigger", 1).parquet(at)


def counted_late(spark: SparkSession, d: str) -> DataFrame:
    found = late_rows(arriving(spark, d))
    return found.groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("n"), F.count_if("late").alias("n_late"))


def running_weights(stream: DataFrame, dims: list[str], idle: str = "2 hours") -> DataFrame:
    """Weights of each tuple of dims (and y) as state of our own, for rules that windows cannot say: a
    tuple that is not seen for `idle` of event time starts again at zero. dims, n_all, n_pos, last,
    a row for each tuple of each batch."""
    names, limit = ", ".join(f"{c} string" for c in dims), round(pd.Timedelta(idle).total_seconds() * 1000)

    def step(key, parts, state):
        n_all, n_pos, last = state.get if state.exists else (0, 0, None)
        rows = pd.concat(list(parts)).sort_values("at")
        for y, at in zip(rows["y"].tolist(), rows["at"].tolist(), strict=True):
            if last is not None and at - last > limit:
                n_all = n_pos = 0
            n_all, n_pos, last = n_all + 1, n_pos + y, max(at, last or at)
        state.update((n_all, n_pos, last))
        yield pd.DataFrame([[*key, n_all, n_pos, last]], columns=[*dims, "n_all", "n_pos", "last"])

    counts = "n_all long, n_pos long, last long"
    own = stream.select(*[F.col(c).cast("string").alias(c) for c in dims], F.col("y").cast("long").alias("y"), F.unix_millis("ts").alias("at"))
    return own.groupBy(*dims).applyInPandasWithState(step, f"{names}, {counts}", counts, "update", "NoTimeout")


def stateful(spark: SparkSession, d: str) -> DataFrame:
    marked = events(spark, d).withColumn("y", (F.col("value") > 150).cast("int"))
    found = finished(running_weights(marked, ["event_type"], "20 minutes"), "update")
    return found.groupBy("event_type").agg(F.max_by("n_all", "last").alias("n_all"), F.max_by("n_pos", "last").alias("n_pos"))


def _daily(spark: SparkSession, d: str) -> DataFrame:
    """The compact table by day, from the stream's windows."""
    marked = events(spark, d).withColumn("hour_band", F.floor(F.hour("ts") / 6).cast("string")).withColumn("y", (F.col("value") > 150).cast("string"))
    found = finished(windowed(marked, ["event_type", "hour_band", "y"], "1 day"), "complete")
    positive = F.coalesce(F.sum(F.when(F.col("y") == "true", F.col("n"))), F.lit(0))
    return found.groupBy(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "hour_band").agg(F.sum("n").alias("n_all"), positive.alias("n_pos"))


def final_rules(spark: SparkSession, d: str) -> DataFrame:
    """Windows of weights from the stream, summed into a compact table, mined at the end."""
    compact = staged(prepare.merge_compact(_daily(spark, d).drop("day")))
    return planner.mined_rules(compact, Config(max_length=2, algorithm="cuboids")).select("key", "n_x", "n_xy", F.round("lift", 6).alias("lift"))


def final_alerts(spark: SparkSession, d: str) -> DataFrame:
    """Rules of the month's second half that are new or stronger against its first half."""
    daily, own = staged(_daily(spark, d)), Config(max_length=2, algorithm="cuboids")
    halves = [staged(prepare.merge_compact(daily.where(x).drop("day"))) for x in ("day < '2024-01-16'", "day >= '2024-01-16'")]
    found = monitor.alerts(*[planner.mined_rules(c, own) for c in halves], min_lift=1.0, factor=1.05)
    return found.select("key", "alert", "n_xy", F.round("lift", 6).alias("lift"))


def merged_batches(compact: DataFrame, batch: DataFrame) -> DataFrame:
    """A batch's weights added to the compact table so far (for foreachBatch)."""
    return prepare.merge_compact(compact, batch)
