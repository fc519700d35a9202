"""Counts of all combinations of at most `max_length` columns by grouping sets: exact, and the
yardstick of the miners. Good where the columns are few."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .items import dims_of, escape


def cuboids(compact: DataFrame, max_length: int) -> DataFrame:
    """itemset, len, n_x, n_xy of every cell."""
    dims = dims_of(compact)
    sets = [s for k in range(1, min(max_length, len(dims)) + 1) for s in combinations(dims, k)]
    quoted = lambda c: "`" + c.replace("`", "``") + "`"
    groups = ", ".join("(" + ", ".join(map(quoted, s)) + ")" for s in sets)
    name = lambda c: escape(c).replace("\\", "\\\\").replace("'", "\\'")
    escaped = lambda c: f"replace(replace(replace(cast({quoted(c)} as string), '\\\\', '\\\\\\\\'), '=', '\\\\='), '|', '\\\\|')"
    part = ", ".join(f"case when grouping({quoted(c)}) = 0 then concat('{name(c)}=', {escaped(c)}) end" for c in dims)
    whole = " and ".join(f"(grouping({quoted(c)}) = 1 or {quoted(c)} is not null)" for c in dims)
    text = f"select array_compact(array({part})) as itemset, sum(n_all) as n_x, sum(n_pos) as n_xy, {whole} as whole from {{compact}} group by grouping sets ({groups})"
    return compact.sparkSession.sql(text, compact=compact).where("whole").select("itemset", F.size("itemset").alias("len"), "n_x", "n_xy")


def mine_cuboids(compact: DataFrame, least: int, max_length: int) -> DataFrame:
    return cuboids(compact, max_length).where(F.col("n_xy") >= least)


def drill(compact: DataFrame, dims: list[str]) -> DataFrame:
    """Subtotals from the coarsest to the finest of the columns."""
    return compact.rollup(*dims).agg(F.sum("n_all").alias("n_all"), F.sum("n_pos").alias("n_pos"))
