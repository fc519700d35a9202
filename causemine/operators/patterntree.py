"""Pattern-tree mining without candidates, over weighted rows.

The rank order of items splits the search: every set belongs to its last-ranked item, whose base is
the prefixes of the rows up to it. Spark makes the bases, one unit of work for each item, and sums
equal prefixes. A unit that is too costly is split by the next item before it, and again, until it
fits or its suffix is as long as a set may be. Units are dealt to tasks; a task grows the tree of
one unit at a time from sorted prefixes.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.staging import staged
from .items import Items, itemize
from .levelwise import count_reference, named

#: Items of distinct prefixes that one unit may have, which bounds the tree that a task holds.
UNIT_MOST = 500_000


class PatternTree:
    """Prefixes of rank-sorted rows with two weights: of the target's rows, and of all rows."""

    __slots__ = ("by_item", "child", "item", "parent", "pos", "whole")

    def __init__(self) -> None:
        self.item, self.parent, self.pos, self.whole = [-1], [-1], [0], [0]
        self.child: dict[tuple[int, int], int] = {}
        self.by_item: dict[int, list[int]] = {}  # all nodes of an item

    def add(self, row, pos: int, whole: int) -> None:
        at = 0
        for i in row:
            key = (at, i)
            if key not in self.child:
                self.child[key] = len(self.item)
                self.by_item.setdefault(i, []).append(len(self.item))
                self.item.append(i)
                self.parent.append(at)
                self.pos.append(0)
                self.whole.append(0)
            at = self.child[key]
            self.pos[at] += pos
            self.whole[at] += whole

    def path(self) -> list[int] | None:
        """The nodes if the tree is one path, else None."""
        if len(self.child) == len(self.item) - 1 and all(p == n for n, p in enumerate(self.parent[1:])):
            return list(range(1, len(self.item)))
        return None

    def conditional(self, i: int, least: int) -> PatternTree:
        """What stands before item i, without what is rare there."""
        base = []
        total: dict[int, int] = {}
        for node in self.by_item[i]:
            row, at = [], self.parent[node]
            while at > 0:
                row.append(self.item[at])
                total[self.item[at]] = total.get(self.item[at], 0) + self.pos[node]
                at = self.parent[at]
            base.append((row[::-1], self.pos[node], self.whole[node]))
        tree = PatternTree()
        for row, pos, whole in base:
            tree.add([x for x in row if total[x] >= least], pos, whole)
        return tree

    def mine(self, least: int, longest: int, suffix: tuple[int, ...] = ()):
        """(items, weight in the target, weight) of each frequent set that ends in suffix."""
        if longest <= len(suffix):
            return
        line = self.path()
        if line is not None:  # every combination, as heavy as its deepest node
            for k in range(1, longest - len(suffix) + 1):
                for some in combinations(line, k):
                    if self.pos[some[-1]] >= least:
                        yield (*[self.item[n] for n in some], *suffix), self.pos[some[-1]], self.whole[some[-1]]
            return
        for i in self.by_item:
            pos = sum(self.pos[n] for n in self.by_item[i])
            if pos < least:
                continue
            yield (i, *suffix), pos, sum(self.whole[n] for n in self.by_item[i])
            if longest > len(suffix) + 1:
                yield from self.conditional(i, least).mine(least, longest, (i, *suffix))


def _summed(base: DataFrame) -> DataFrame:
    keys = [c for c in base.columns if c not in ("n_pos", "n_all")]
    return base.groupBy(*keys).agg(F.sum("n_pos").alias("n_pos"), F.sum("n_all").alias("n_all"))


def emit_prefixes(rows: DataFrame) -> DataFrame:
    """unit (a suffix of one item), prefix, n_pos, n_all and what else rows have: for each item of a
    row what stands before it, equal ones summed."""
    rest = [c for c in rows.columns if c not in ("items", "n_pos", "n_all")]
    each = rows.select(*rest, "items", "n_pos", "n_all", F.posexplode("items").alias("at", "item"))
    return _summed(each.select(*rest, F.array("item").alias("unit"), F.slice("items", 1, F.col("at")).alias("prefix"), "n_pos", "n_all"))


def split_unit(base: DataFrame) -> DataFrame:
    """The same for units with one item more in their suffix."""
    rest = [c for c in base.columns if c not in ("unit", "prefix", "n_pos", "n_all")]
    each = base.select(*rest, "unit", "prefix", "n_pos", "n_all", F.posexplode("prefix").alias("at", "item"))
    return _summed(each.select(*rest, F.concat(F.array("item"), "unit").alias("unit"), F.slice("prefix", 1, F.col("at")).alias("prefix"), "n_pos", "n_all"))


def _grown(key: tuple, rows: list, longest: int) -> Iterator[tuple]:
    """The unit's own set and the sets found in the tree of its prefixes."""
    by, unit, least = key
    pos, whole = sum(r[1] for r in rows), sum(r[2] for r in rows)
    if pos < least:
        return
    yield by, unit, whole, pos
    total: dict[int, int] = {}
    for prefix, n, _ in rows:
        for i in prefix:
            total[i] = total.get(i, 0) + n
    tree = PatternTree()
    for prefix, n, m in rows:
        tree.add([i for i in prefix if total[i] >= least], n, m)
    for items, n, m in tree.mine(least, longest, tuple(unit)):
        yield by, sorted(items), m, n


def mine_units(rows: DataFrame, max_length: int, shards: int, unit_most: int = UNIT_MOST) -> DataFrame:
    """by, items, n_x, n_xy of the frequent sets of each group, for rows (by, least, items, n_pos,
    n_all): groups have their own search, and each its least weight."""
    small, heavy = [], staged(emit_prefixes(rows))
    for depth in range(1, max_length):
        size = heavy.groupBy("by", "unit").agg(F.sum(F.size("prefix")).alias("cost"), F.sum("n_pos").alias("pos"), F.first("least").alias("least"))
        costly = size.where((F.col("cost") > unit_most) & (F.col("pos") >= F.col("least"))).select("by", "unit")
        if costly.isEmpty():
            break
        costly = staged(costly)
        # A unit that is split still has the set of its suffix alone.
        alone = heavy.join(costly, ["by", "unit"], "left_semi").select("by", "least", "unit", F.array().cast("array<int>").alias("prefix"), "n_pos", "n_all")
        small += [heavy.join(costly, ["by", "unit"], "left_anti"), _summed(alone)]
        heavy = staged(split_unit(heavy.join(costly, ["by", "unit"], "left_semi")))
    whole = heavy
    for part in small:
        whole = whole.unionByName(part)

    def grow(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held, out = None, [], []

        def batch() -> pa.RecordBatch:
            by, items, n_x, n_xy = zip(*out, strict=True)
            return pa.RecordBatch.from_arrays([pa.array(by, pa.string()), pa.array(items, pa.list_(pa.int32())), pa.array(n_x, pa.int64()), pa.array(n_xy, pa.int64())], ["by", "items", "n_x", "n_xy"])

        for part in batches:
            columns = [part.column(c).to_pylist() for c in ("by", "unit", "least", "prefix", "n_pos", "n_all")]
            for by, unit, least, prefix, n_pos, n_all in zip(*columns, strict=True):
                if (by, unit, least) != key:
                    if key:
                        out.extend(_grown(key, held, max_length))
                    key, held = (by, unit, least), []
                    if len(out) >= 10_000:
                        yield batch()
                        out.clear()
                held.append((prefix, n_pos, n_all))
        if key:
            out.extend(_grown(key, held, max_length))
        if out:
            yield batch()

    dealt = whole.repartition(shards, "by", "unit").sortWithinPartitions("by", "unit")
    return dealt.mapInArrow(grow, "by string, items array<int>, n_x bigint, n_xy bigint")


def mine_patterntree(compact: DataFrame, least: int, max_length: int, shards: int | None = None, items: Items | None = None, reference: str = "second_pass", unit_most: int = UNIT_MOST) -> DataFrame:
    """itemset, len, n_x, n_xy of all sets with the least weight in the target.

    reference: second_pass grows trees from the target's rows and counts the found sets over all
    rows after; joint grows them from all rows with both weights.
    """
    if reference not in ("second_pass", "joint"):
        raise ValueError("reference must be second_pass or joint")
    spark = compact.sparkSession
    items = items or Items.of(compact, least)
    if not len(items):
        return named(spark.createDataFrame([], "items array<int>, n_x bigint, n_xy bigint"), items)
    rows = staged(itemize(compact, items))
    inside = rows.where("n_pos > 0") if reference == "second_pass" else rows
    found = mine_units(inside.withColumn("by", F.lit("")).withColumn("least", F.lit(least).cast("long")), max_length, shards or 2 * spark.sparkContext.defaultParallelism, unit_most).drop("by")
    if reference == "second_pass":
        found = count_reference(staged(found), rows, items)
    return named(found, items)
