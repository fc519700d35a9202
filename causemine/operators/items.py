"""Items, their dictionary, and rows as sets of items."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

COUNTS = ("n_all", "n_pos")


def dims_of(compact: DataFrame) -> list[str]:
    return [c for c in compact.columns if c not in COUNTS]


def totals(compact: DataFrame) -> tuple[int, int]:
    """N and P: the weight of all rows and of the target's rows."""
    row = compact.agg(F.sum("n_all").alias("n"), F.sum("n_pos").alias("p")).first()
    return row["n"] or 0, row["p"] or 0


def item_counts(compact: DataFrame, null_items: str = "drop") -> DataFrame:
    """col, val, n_x, n_xy of every item: one unpivot and one aggregate."""
    dims = dims_of(compact)
    whole = compact.select(*COUNTS, *[F.col(c).cast("string").alias(c) for c in dims]).unpivot(list(COUNTS), dims, "col", "val")
    kept = whole.where("val is not null") if null_items == "drop" else whole.fillna("∅", subset=["val"])
    return kept.groupBy("col", "val").agg(F.sum("n_all").alias("n_x"), F.sum("n_pos").alias("n_xy"))


def item_dictionary(compact: DataFrame, least: int, null_items: str = "drop") -> DataFrame:
    """item (rank from 0, most frequent in the target first), col, val, n_x, n_xy of the items that
    reach the least weight. At most columns / min_support items, whatever the input."""
    order = W.orderBy(F.desc("n_xy"), "col", "val")
    return item_counts(compact, null_items).where(F.col("n_xy") >= least).select((F.row_number().over(order) - 1).alias("item"), "col", "val", "n_x", "n_xy")


@dataclass(frozen=True)
class Items:
    """The dictionary on the driver."""

    dims: list[str]
    entries: list[tuple[str, str, int, int]]  # col, val, n_x, n_xy by rank

    @classmethod
    def of(cls, compact: DataFrame, least: int, null_items: str = "drop") -> Items:
        rows = item_counts(compact, null_items).where(F.col("n_xy") >= least).collect()  # bounded
        found = sorted(((r["col"], r["val"], r["n_x"], r["n_xy"]) for r in rows), key=lambda e: (-e[3], e[0], e[1]))
        return cls(dims_of(compact), found)

    def __len__(self) -> int:
        return len(self.entries)

    @classmethod
    def of_some(cls, compact: DataFrame, by: str, least: DataFrame) -> Items:
        """The items that are frequent in some group. least: by, least. Bounded by groups times
        columns / min_support, and by the values there are."""
        dims = [c for c in dims_of(compact) if c != by]
        whole = compact.select(by, *COUNTS, *[F.col(c).cast("string").alias(c) for c in dims]).unpivot([by, *COUNTS], dims, "col", "val").where("val is not null")
        per = whole.groupBy(by, "col", "val").agg(F.sum("n_all").alias("n_x"), F.sum("n_pos").alias("n_xy")).join(least, by)
        some = per.groupBy("col", "val").agg(F.sum("n_x").alias("n_x"), F.sum("n_xy").alias("n_xy"), F.max(F.col("n_xy") >= F.col("least")).alias("frequent"))
        found = [(r["col"], r["val"], r["n_x"], r["n_xy"]) for r in some.where("frequent").collect()]
        return cls(dims, sorted(found, key=lambda e: (-e[3], e[0], e[1])))

    def supported(self) -> list[str]:
        """The columns with some frequent value; the others cannot be part of any rule."""
        return [d for d in self.dims if any(e[0] == d for e in self.entries)]

    @property
    def columns(self) -> list[int]:
        """The number of each item's column: two items of one column never occur together."""
        return [self.dims.index(e[0]) for e in self.entries]

    def name(self, i: int) -> str:
        col, val, *_ = self.entries[i]
        return f"{escape(col)}={escape(val)}"

    def named(self, items: Column) -> Column:
        """An array of item numbers as `col=val` texts in the order of the columns."""
        if not self.entries:
            return F.array().cast("array<string>")
        known = F.array(*[F.struct(F.lit(c).alias("c"), F.lit(self.name(i)).alias("name")) for i, c in enumerate(self.columns)])
        return F.transform(F.array_sort(F.transform(items, lambda i: F.element_at(known, i + 1))), lambda s: s["name"])


def escape(value: str) -> str:
    for c in "\\=|":
        value = value.replace(c, "\\" + c)
    return value


def itemize(compact: DataFrame, items: Items, null_items: str = "drop", extra: tuple[str, ...] = ()) -> DataFrame:
    """items (numbers, sorted by rank), n_all, n_pos and extra columns. Infrequent values are left out
    and rows that then are equal become one, which is a second compaction."""
    found = []
    for d in items.dims:
        value = F.col(d).cast("string") if null_items == "drop" else F.coalesce(F.col(d).cast("string"), F.lit("∅"))
        own = [(v, i) for i, (c, v, *_) in enumerate(items.entries) if c == d]
        if own:
            found.append(F.element_at(F.create_map(*[F.lit(x) for pair in own for x in pair]), value))
    row = F.array_sort(F.array_compact(F.array(*found))) if found else F.array().cast("array<int>")
    return compact.select(row.alias("items"), *COUNTS, *extra).groupBy("items", *extra).agg(*[F.sum(c).alias(c) for c in COUNTS])


def compact_again(compact: DataFrame, items: Items) -> DataFrame:
    """The compact table with infrequent values as null, grouped again."""
    dims = items.dims
    kept = {d: [v for c, v, *_ in items.entries if c == d] for d in dims}
    own = [F.when(F.col(d).isin(kept[d]), F.col(d)).alias(d) if kept[d] else F.lit(None).cast("string").alias(d) for d in dims]
    return compact.select(*own, *COUNTS).groupBy(*dims).agg(*[F.sum(c).alias(c) for c in COUNTS])


def one_hot_wide(compact: DataFrame, items: Items) -> DataFrame:
    """A Boolean column for each item."""
    return compact.select(*[(F.col(c).cast("string").eqNullSafe(v)).alias(items.name(i)) for i, (c, v, *_) in enumerate(items.entries)], *COUNTS)
