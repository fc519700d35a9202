"""Measures of a rule X => Y from four counts: n_x, n_xy, n_y and n (sums of weights)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _d(c: Column | str) -> Column:
    return (F.col(c) if isinstance(c, str) else c).cast("double")


def supp_all(n_x, n) -> Column:
    """Share of all rows with X."""
    return F.try_divide(_d(n_x), _d(n))


def supp(n_xy, n_y) -> Column:
    """Share of the target's rows with X."""
    return F.try_divide(_d(n_xy), _d(n_y))


def confidence(n_xy, n_x) -> Column:
    return F.try_divide(_d(n_xy), _d(n_x))


def lift(n_xy, n_x, n_y, n) -> Column:
    """A rounded quotient times a constant: equal ratios give equal doubles, so ties are stable."""
    return F.try_divide(_d(n_xy), _d(n_x)) * F.try_divide(_d(n), _d(n_y))


def conviction(n_xy, n_x, n_y, n) -> Column:
    """Null where X never occurs without Y."""
    return F.when(_d(n_xy) < _d(n_x), (1 - F.try_divide(_d(n_y), _d(n))) / (1 - F.try_divide(_d(n_xy), _d(n_x))))


def chi2(n_xy, n_x, n_y, n) -> Column:
    """Of the 2 x 2 table of X and Y; null where a margin is empty."""
    a = _d(n_xy)
    b, c = _d(n_x) - a, _d(n_y) - a
    d = _d(n) - a - b - c
    cross = a * d - b * c
    return F.try_divide(_d(n) * cross * cross, (a + b) * (c + d) * (a + c) * (b + d))


def error_rate(df: DataFrame, cols: list[str], target: str) -> DataFrame:
    """Groups of column values by their share of target rows."""
    return df.groupBy(*cols).agg(F.count("*").alias("n"), F.sum(F.col(target).cast("long")).alias("n_pos"), F.avg(F.col(target).cast("double")).alias("rate"))


def reduction(raw: int, compact: int) -> float:
    return raw / max(1, compact)


def register(spark: SparkSession) -> None:
    """The measures as SQL functions, which the analyzer inlines."""
    four = "n_xy BIGINT, n_x BIGINT, n_y BIGINT, n BIGINT"
    for text in (
        "rule_support(n_xy BIGINT, n_y BIGINT) RETURNS DOUBLE RETURN try_divide(CAST(n_xy AS DOUBLE), n_y)",
        "rule_confidence(n_xy BIGINT, n_x BIGINT) RETURNS DOUBLE RETURN try_divide(CAST(n_xy AS DOUBLE), n_x)",
        f"rule_lift({four}) RETURNS DOUBLE RETURN try_divide(CAST(n_xy AS DOUBLE), n_x) * try_divide(CAST(n AS DOUBLE), n_y)",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
