"""Conditions on items, sub-sets and signatures for users of SQL and of the DataFrame API."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from itertools import combinations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Words of a condition after the column's name, as in where(df, "segment in A, B", "value between 5 and 9").
_FORMS = {
    "=": lambda c, v: c.eqNullSafe(v),
    "!=": lambda c, v: ~c.eqNullSafe(v),
    "in": lambda c, v: c.isin([x.strip() for x in v.split(",")]),
    "between": lambda c, v: c.cast("double").between(*[float(x) for x in v.split(" and ")]),
    "like": lambda c, v: c.like(v),
    "matches": lambda c, v: c.rlike(v),
    ">=": lambda c, v: c.cast("double") >= float(v),
    "<=": lambda c, v: c.cast("double") <= float(v),
}


def condition(text: str) -> Column:
    """One condition, `column form value`; `column = null` holds for a missing value."""
    name, form, value = (text.strip().split(None, 2) + ["", ""])[:3]
    if form not in _FORMS:
        raise ValueError(f"a condition reads: column {' | '.join(_FORMS)} value")
    if value == "null" and form in ("=", "!="):
        return F.col(name).isNull() if form == "=" else F.col(name).isNotNull()
    return _FORMS[form](F.col(name), value)


def where(df: DataFrame, *conditions: str) -> DataFrame:
    """Rows that meet all conditions; they reach the scan as far as it can take them."""
    return df.where(reduce(lambda a, b: a & b, map(condition, conditions)))


def signature(items: Column) -> Column:
    """A number for a set of items whatever their order; equal numbers are held against the sets themselves."""
    return F.xxhash64(F.array_sort(items))


@F.pandas_udf(T.LongType())
def mask_sum(bit: pd.Series) -> int:
    """Which bits occur in a group (an aggregate; bit_or is the same in SQL)."""
    out = 0
    for b in bit:
        out |= 1 << int(b)
    return out


@F.udtf(returnType=T.StructType([T.StructField("subset", T.ArrayType(T.StringType())), T.StructField("len", T.IntegerType())]))
class Subsets:
    """subsets(items, longest): the non-empty parts of a set, for LATERAL joins."""

    def eval(self, items: list, longest: int) -> Iterator[tuple]:
        for k in range(1, min(longest, len(items)) + 1):
            for part in combinations(items, k):
                yield list(part), k


def register(spark: SparkSession) -> None:
    spark.udtf.register("subsets", Subsets)
    spark.udf.register("mask_sum", mask_sum)
