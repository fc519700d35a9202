"""Level-wise mining: sets of k items are joined to candidates of k + 1, pruned by downward closure,
and counted in one scan for each level."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.staging import staged
from .counting import count_sets
from .items import Items, itemize


def next_candidates(level: DataFrame, columns: list[int]) -> DataFrame:
    """items of k + 1 from sets that share all but their last item, of different columns."""
    of = F.array(*[F.lit(c) for c in columns])
    head = lambda x: F.slice(x, 1, F.size(x) - 1)
    a = level.select(head(F.col("items")).alias("head"), F.col("items").alias("a"), F.element_at("items", -1).alias("last_a"))
    b = level.select(head(F.col("items")).alias("head"), F.element_at("items", -1).alias("last_b"))
    differs = F.element_at(of, F.col("last_a") + 1) != F.element_at(of, F.col("last_b") + 1)
    return a.join(b, "head").where((F.col("last_a") < F.col("last_b")) & differs).select(F.concat("a", F.array("last_b")).alias("items"))


def prune_candidates(candidates: DataFrame, level: DataFrame) -> DataFrame:
    """Candidates all of whose subsets with one item less are frequent."""
    places = F.sequence(F.lit(0), F.size("items") - 1)
    less = candidates.select("items", F.explode(F.transform(places, lambda k: F.filter("items", lambda _, i: i != k))).alias("subset"))
    known = level.select(F.col("items").alias("subset"))
    return less.join(known, "subset", "left_semi").groupBy("items").agg(F.count("*").alias("c")).where(F.col("c") == F.size("items")).select("items")


def first_level(items: Items, spark) -> DataFrame:
    """The frequent items, whose counts the dictionary has."""
    return spark.createDataFrame([([i], n_x, n_xy) for i, (_, _, n_x, n_xy) in enumerate(items.entries)], "items array<int>, n_x bigint, n_xy bigint")


def mine_levelwise(compact: DataFrame, least: int, max_length: int, parallelism: int | None = None, items: Items | None = None, keep: Callable[[int, int], Column] | None = None, reference: bool = True) -> DataFrame:
    """itemset, len, n_x, n_xy of all sets with the least weight in the target.

    parallelism: how many tasks share a level's candidates, each over all rows (1: one after the
    other); None lets tasks share the rows instead. keep(k, n): a further condition on the counts (n_x,
    n_xy) of level k, which has n candidates; used by baselines alone, as it loses sets.
    """
    items = items or Items.of(compact, least)
    rows = staged(itemize(compact, items))
    whole = keep is not None  # the search needs the target's rows alone, unless a condition asks for all
    inside = rows if whole else rows.where("n_pos > 0")
    level, levels, n = first_level(items, compact.sparkSession), [], len(items)
    for k in range(1, max_length + 1):
        level = level if keep is None else level.where(keep(k, n))
        level = staged(level.where(F.col("n_xy") >= least))
        if level.isEmpty():
            break
        levels.append(level)
        if k == max_length or k == len(items.dims):
            break
        candidates = next_candidates(level, items.columns)
        if k > 1:
            candidates = prune_candidates(candidates, level)
        if whole:
            n = candidates.count()
        level = count_sets(inside, candidates, parallelism)
    found = _union(levels) if levels else compact.sparkSession.createDataFrame([], "items array<int>, n_x bigint, n_xy bigint")
    if reference and not whole and levels:
        found = count_reference(found, rows, items)
    return named(found, items)


def _union(parts: list[DataFrame]) -> DataFrame:
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    return whole


def count_reference(found: DataFrame, rows: DataFrame, items: Items) -> DataFrame:
    """items, n_x, n_xy over all rows for found sets, a table; the dictionary has those of single items."""
    longer = found.where("size(items) > 1").select("items")
    singles = first_level(items, rows.sparkSession).join(found.select("items"), "items", "left_semi")
    return singles.unionByName(count_sets(rows, longer))


def named(found: DataFrame, items: Items) -> DataFrame:
    return found.select(items.named(F.col("items")).alias("itemset"), F.size("items").alias("len"), "n_x", "n_xy")
