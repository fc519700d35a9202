"""From raw logs to the compact weighted table: structure, enrich, label, bucket, prune, group."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


#: Patterns of a vocabulary, each a condition of one projection.
VOCABULARY_MOST = 500


def parse_lines(lines: DataFrame, column: str = "value") -> DataFrame:
    """time and message of text lines that begin with a time; others are dropped."""
    time = F.regexp_extract(column, r"^\s*(\d+:\d\d)\s+", 1)
    message = F.trim(F.regexp_extract(column, r"^\s*\d+:\d\d\s+(.*)$", 1))
    return lines.select(time.alias("time"), message.alias("message")).where("time <> '' and message <> ''")


def structure_log(lines: DataFrame, vocabulary: DataFrame, kinds: list[str], layout: str = "wide") -> DataFrame:
    """A row for each time (wide: a counter for each kind; narrow: a row for each kind).

    vocabulary (pattern, kind, tool) maps messages, which may be worded in several ways, to
    canonical kinds; a message may match several kinds, and one that matches none is dropped. The
    vocabulary is fixed by whoever designs the log's schema, and refused beyond VOCABULARY_MOST
    patterns; they are conditions of one projection, so lines are matched where they are read.
    """
    known = vocabulary.select("pattern", "kind", "tool").limit(VOCABULARY_MOST + 1).collect()
    if len(known) > VOCABULARY_MOST:
        raise ValueError(f"a vocabulary has at most {VOCABULARY_MOST} patterns")
    hits = [F.when(F.col("message").rlike(r["pattern"]), F.struct(F.lit(r["kind"]).alias("kind"), F.lit(r["tool"]).cast("string").alias("tool"))) for r in known]
    none = F.array().cast("array<struct<kind:string,tool:string>>")
    found = lines.select("time", F.explode(F.array_compact(F.array(*hits)) if hits else none).alias("hit")).select("time", "hit.kind", "hit.tool")
    per = found.groupBy("time", "kind").agg(F.count("*").alias("n"), F.max("tool").alias("tool"))
    if layout == "narrow":
        return per.select("time", "kind", "n", "tool")
    wide = per.groupBy("time").pivot("kind", kinds).agg(F.sum("n"))
    tools = per.groupBy("time").agg(F.max("tool").alias("tool"))
    return wide.fillna(0, subset=kinds).join(tools, "time").select("time", *kinds, "tool")


def enrich(fact: DataFrame, dims: list[tuple[DataFrame, Column | str]], how: str = "left") -> DataFrame:
    """Add the attributes of entities to the label rows, one equi-join for each dimension."""
    return reduce(lambda df, d: df.join(d[0], d[1], how), dims, fact)


def enrich_asof(events: DataFrame, configs: DataFrame, key: str, time: str, values: list[str], tolerance: str | None = None) -> DataFrame:
    """Each event with its entity's last configuration before or at it.

    Both sides go into one sorted stream by entity, in which the last configuration is carried on:
    one shuffle, no range join. A configuration counts before an event of the same time.
    """
    held = F.struct(F.col(time).alias("__at"), *values)
    a = events.withColumn("__held", F.lit(None).cast(configs.select(held.alias("h")).schema["h"].dataType)).withColumn("__event", F.lit(1))
    b = configs.select(key, time, held.alias("__held")).withColumn("__event", F.lit(0))
    stream = a.unionByName(b, allowMissingColumns=True)
    window = W.partitionBy(key).orderBy(time, "__event").rowsBetween(W.unboundedPreceding, 0)
    last = stream.withColumn("__last", F.last("__held", ignorenulls=True).over(window)).where("__event = 1")
    near = F.lit(True) if tolerance is None else F.col("__last.__at") >= F.col(time) - F.expr(f"INTERVAL {tolerance}")
    return last.select(*events.columns, *[F.when(near, F.col(f"__last.{v}")).alias(v) for v in values])


def within(a: DataFrame, b: DataFrame, key: str, time_a: str, time_b: str, seconds: int) -> DataFrame:
    """Pairs in which b is at most so many seconds before a. A range join by equal time buckets:
    b enters the bucket of its time and the next one."""
    bucket = lambda c: F.floor(F.unix_timestamp(F.col(c).cast("timestamp")) / seconds)
    left = a.withColumn("__bucket", bucket(time_a))
    right = b.withColumn("__bucket", F.explode(F.array(bucket(time_b), bucket(time_b) + 1)))
    gap = F.unix_timestamp(F.col(time_a).cast("timestamp")) - F.unix_timestamp(F.col(time_b).cast("timestamp"))
    return left.join(right, [key, "__bucket"]).where(gap.between(0, seconds)).drop("__bucket")


def label(df: DataFrame, condition: str, name: str = "y") -> DataFrame:
    return df.withColumn(name, F.coalesce(F.expr(condition).cast("long"), F.lit(0)))


def bucketize(df: DataFrame, column: str, edges: list[float], name: str | None = None) -> DataFrame:
    """A continuous column as intervals: (-inf, e0], (e0, e1], ... as text. Null stays null."""
    c, out = F.col(column), F.when(F.col(column).isNull(), F.lit(None).cast("string"))
    low = "-inf"
    for e in edges:
        out = out.when(c <= e, F.lit(f"({low},{e:g}]"))
        low = f"{e:g}"
    return df.withColumn(name or column, out.otherwise(F.lit(f"({low},inf)")))


def quantile_edges(df: DataFrame, column: str, parts: int, accuracy: int = 10_000) -> list[float]:
    """Edges of intervals with about equal weights; a few numbers come to the driver."""
    at = [i / parts for i in range(1, parts)]
    found = df.agg(F.percentile_approx(column, at, accuracy).alias("q")).first()["q"]
    return sorted(set(found or []))


def sweep_threshold(df: DataFrame, column: str, thresholds: list[float]) -> DataFrame:
    """How many rows each threshold calls unacceptable, in one pass."""
    counts = df.agg(F.count("*").alias("n"), *[F.count_if(F.col(column) > t).alias(f"t{i}") for i, t in enumerate(thresholds)])
    rows = F.explode(F.array(*[F.struct(F.lit(float(t)).alias("threshold"), F.col(f"t{i}").alias("n_pos")) for i, t in enumerate(thresholds)]))
    return counts.select("n", rows.alias("r")).select("r.threshold", "r.n_pos", "n")


def exclude_columns(df: DataFrame, columns: list[str]) -> DataFrame:
    return df.drop(*columns)


def profile_columns(df: DataFrame, columns: list[str] | None = None, exact: bool = False) -> DataFrame:
    """column, n, n_distinct, n_null of each column, from one pass over the data."""
    columns = columns or df.columns
    count = F.count_distinct if exact else F.approx_count_distinct
    row = df.agg(F.count("*").alias("__n"), *[x for i, c in enumerate(columns) for x in (count(F.col(c)).alias(f"d{i}"), F.count_if(F.col(c).isNull()).alias(f"z{i}"))])
    out = F.explode(F.array(*[F.struct(F.lit(c).alias("column"), F.col(f"d{i}").alias("n_distinct"), F.col(f"z{i}").alias("n_null")) for i, c in enumerate(columns)]))
    return row.select("__n", out.alias("r")).select("r.column", F.col("__n").alias("n"), "r.n_distinct", "r.n_null")


def auto_exclude(df: DataFrame, ratio: float = 0.02, columns: list[str] | None = None, exact: bool = False, rsd: float = 0.05) -> list[str]:
    """The columns to keep: those with at most ratio * n distinct values.

    Counts are estimated first; only columns near the limit are counted again exactly.
    """
    found = {r["column"]: r for r in profile_columns(df, columns, exact).collect()}
    near = [c for c, r in found.items() if not exact and abs(r["n_distinct"] - ratio * r["n"]) <= 3 * rsd * max(1.0, ratio * r["n"])]
    if near:
        found |= {r["column"]: r for r in profile_columns(df.select(*near), near, exact=True).collect()}
    return [c for c, r in found.items() if r["n_distinct"] <= ratio * r["n"]]


def support_exclude(compact: DataFrame, least: int) -> list[str]:
    """The columns to keep: those with some value of the least weight in the target. No rule can have
    an item of another column."""
    from .items import Items

    return Items.of(compact, least).supported()


def preaggregate(df: DataFrame, dims: list[str], target: str = "y", enabled: bool = True) -> DataFrame:
    """dims, n_all and n_pos: equal rows become one with a weight. The only step that shuffles what
    comes from raw data, after each task has summed its own. enabled=False keeps every row."""
    if not enabled:
        return df.select(*dims, F.lit(1).cast("long").alias("n_all"), F.col(target).cast("long").alias("n_pos"))
    return df.groupBy(*dims).agg(F.count("*").alias("n_all"), F.sum(F.col(target).cast("long")).alias("n_pos"))


def merge_compact(*parts: DataFrame) -> DataFrame:
    """Compact tables of several days or sources as one: weights add up."""
    whole = reduce(lambda a, b: a.unionByName(b), parts)
    dims = [c for c in whole.columns if c not in ("n_all", "n_pos")]
    return whole.groupBy(*dims).agg(F.sum("n_all").alias("n_all"), F.sum("n_pos").alias("n_pos"))


def rows_behind(df: DataFrame, itemset: dict[str, str], n: int) -> DataFrame:
    """A few raw rows that a rule speaks of; its conditions reach the scan."""
    return df.where(reduce(lambda a, b: a & b, [F.col(c) == v for c, v in itemset.items()])).limit(n)
