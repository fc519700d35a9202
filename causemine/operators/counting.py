"""Weights of given item-sets: a prefix tree of the sets goes to every task, and only sums come back."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Sets in one broadcast tree (about 100 bytes each); more are counted in several passes.
SETS_MOST = 200_000

_COUNTED = "items array<int>, n_x bigint, n_xy bigint"


def tree_of(sets: list[list[int]]) -> dict:
    """item -> [number of the set that ends here or -1, children]."""
    root: dict = {}
    for number, items in enumerate(sets):
        level, node = root, None
        for i in items:
            node = level.setdefault(i, [-1, {}])
            level = node[1]
        if node is not None:
            node[0] = number
    return root


def _add(tree: dict, rows: np.ndarray, has: dict[int, np.ndarray], weights: np.ndarray, total: np.ndarray) -> None:
    """Walk the tree with the rows that hold the way to each node."""
    stack = [(tree, rows)]
    while stack:
        level, rows = stack.pop()
        for item, (number, below) in level.items():
            flags = has.get(item)
            if flags is None:
                continue
            own = rows[flags[rows]]
            if not len(own):
                continue
            if number >= 0:
                total[number] += weights[own].sum(axis=0)
            if below:
                stack.append((below, own))


def counted_in(batches: Iterator[pa.RecordBatch], sets: list[list[int]]) -> pa.RecordBatch:
    """The sums over batches of rows (items, n_all, n_pos) for the sets that occur."""
    tree, total = tree_of(sets), np.zeros((len(sets), 2), np.int64)
    for batch in batches:
        lists = batch.column("items")
        flat, offsets = lists.flatten().to_numpy(), lists.offsets.to_numpy().astype(np.int64)
        if not len(flat):  # no row of the batch has a frequent item
            continue
        of = np.repeat(np.arange(batch.num_rows), np.diff(offsets))
        has = {}
        order = np.argsort(flat, kind="stable")
        found, first = np.unique(flat[order], return_index=True)
        for item, rows in zip(found.tolist(), np.split(of[order], first[1:]), strict=True):
            has[item] = np.zeros(batch.num_rows, bool)
            has[item][rows] = True
        weights = np.stack([batch.column("n_all").to_numpy(), batch.column("n_pos").to_numpy()], axis=1)
        _add(tree, np.arange(batch.num_rows), has, weights, total)
    seen = np.flatnonzero(total[:, 0])
    return pa.RecordBatch.from_arrays([pa.array([sets[k] for k in seen.tolist()], pa.list_(pa.int32())), pa.array(total[seen, 0]), pa.array(total[seen, 1])], ["items", "n_x", "n_xy"])


def _pass(rows: DataFrame, own: list[list[int]], parallelism: int | None) -> DataFrame:
    spark = rows.sparkSession
    if parallelism is None:  # tasks share the rows; each has all sets
        shared = spark.sparkContext.broadcast(own)
        return rows.select("items", "n_all", "n_pos").mapInArrow(lambda b: iter([counted_in(b, shared.value)]), _COUNTED)
    # Tasks share the sets, a group each, and every task sees all rows.
    shared = spark.sparkContext.broadcast([own[g::parallelism] for g in range(parallelism)])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = next(batches, None)
        if first is not None and first.num_rows:
            group = first.column("group")[0].as_py()

            def rest() -> Iterator[pa.RecordBatch]:
                yield first
                yield from batches

            yield counted_in(rest(), shared.value[group])

    copies = rows.select(F.explode(F.sequence(F.lit(0), F.lit(parallelism - 1))).alias("group"), "items", "n_all", "n_pos")
    return copies.repartitionById(parallelism, "group").mapInArrow(count, _COUNTED)


def count_sets(rows: DataFrame, sets: DataFrame, parallelism: int | None = None, most: int = SETS_MOST) -> DataFrame:
    """items, n_x, n_xy of sets (items) over rows (items, n_all, n_pos); sets that no row holds are left out.

    A set's items have one order throughout. Sets come to the driver in groups of about `most` at most,
    which bounds what is broadcast; beyond that the rows are read once for each group. sets should be
    a table, as it may be read several times.

    parallelism None: tasks share the rows. n: n tasks share the sets, and each reads all rows.
    """
    gathered = lambda part: sorted(r["items"] for r in part.select("items").collect())
    own = gathered(sets.limit(most + 1))
    if len(own) <= most:
        out = _pass(rows, own, parallelism)
    else:
        out, groups = None, 1 + sets.count() * 5 // (most * 4)  # a group may be a little larger than the mean
        for g in range(groups):
            found = _pass(rows, gathered(sets.where(F.pmod(F.xxhash64("items"), F.lit(groups)) == g)), parallelism)
            out = found if out is None else out.unionByName(found)
    return out.groupBy("items").agg(F.sum("n_x").alias("n_x"), F.sum("n_xy").alias("n_xy"))
