"""The whole analysis, and the choice of the miner."""

from __future__ import annotations

import time
from collections.abc import Callable
from itertools import combinations
from math import comb

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Config, least_count
from .staging import staged
from ..operators import cuboids, items, levelwise, patterntree, prepare, rules


def candidate_bound(n_items: int, max_length: int) -> int:
    """How many sets of at most so many items there can be."""
    return sum(comb(n_items, k) for k in range(1, max_length + 1))


def exclusive_bound(cardinalities: list[int], max_length: int) -> int:
    """The same, when items of one column exclude each other: sums of products of cardinalities."""
    sums = [1] + [0] * max_length
    for c in cardinalities:
        for k in range(max_length, 0, -1):
            sums[k] += sums[k - 1] * c
    return sum(sums[1:])


#: Below so many possible sets the level-wise search is taken (the published crossover).
LEVELWISE_MOST = 2_000


def choose_miner(known: items.Items, n_rows: int, max_length: int) -> str:
    """By what each would touch: cuboids read every row once for each combination of columns;
    level-wise suits few sets; the tree suits many."""
    columns = known.columns
    per = [columns.count(c) for c in set(columns)]
    groupings = sum(1 for k in range(1, min(max_length, len(known.dims)) + 1) for _ in combinations(known.dims, k))
    if groupings * n_rows <= 200_000:
        return "cuboids"
    return "levelwise" if exclusive_bound(per, max_length) <= LEVELWISE_MOST else "patterntree"


def mine(compact: DataFrame, config: Config, least: int, known: items.Items | None = None) -> DataFrame:
    name = config.algorithm
    if name == "auto":
        known = known or items.Items.of(compact, least)
        name = choose_miner(known, compact.count(), config.max_length)
    if name == "cuboids":
        return cuboids.mine_cuboids(compact, least, config.max_length)
    if name == "levelwise":
        return levelwise.mine_levelwise(compact, least, config.max_length, config.parallelism, known)
    return patterntree.mine_patterntree(compact, least, config.max_length, config.shards, known)


def mined_rules(compact: DataFrame, config: Config, label: str = "y") -> DataFrame:
    """Scored rules with the least support, before any filter. Without a failure there are none."""
    n, n_y = items.totals(compact)
    return rules.score_rules(mine(compact, config, least_count(config.min_support, max(1, n_y), config.min_count)), n, n_y, label)


def explain_failures(df: DataFrame, target: str, config: Config = Config(), columns: list[str] | None = None) -> DataFrame:  # noqa: B008
    """From labelled rows to the condensed rules: prune columns, group, mine, score, filter."""
    kept = [c for c in columns or df.columns if c != target and c not in config.exclude]
    kept = prepare.auto_exclude(df, config.distinct_ratio, kept)
    compact = staged(prepare.preaggregate(df, kept, target))
    found = rules.filter_lift(mined_rules(compact, config), config.min_lift)
    return rules.condense(found, config.h_supp, config.h_lift_long, config.h_lift_short, config.mode)


def measure(name: str, action: Callable[[], int]) -> tuple[str, float, int]:
    began = time.perf_counter()
    n = action()
    return name, time.perf_counter() - began, n


def advise(compact: DataFrame, supports: list[float], lengths: list[int], algorithms: tuple[str, ...] = ("levelwise", "patterntree", "cuboids")) -> DataFrame:
    """Times of the algorithms over a small grid; the fastest of each point is marked."""
    found = []
    _, n_y = items.totals(compact)
    for s in supports:
        for k in lengths:
            own = [(a, *measure(a, lambda a=a, s=s, k=k: mine(compact, Config(min_support=s, max_length=k, algorithm=a), least_count(s, n_y)).count())[1:]) for a in algorithms]
            best = min(own, key=lambda r: r[1])[0]
            found += [(a, s, k, t, n, a == best) for a, t, n in own]
    return compact.sparkSession.createDataFrame(found, "algorithm string, min_support double, max_length int, seconds double, n_itemsets bigint, best boolean")


def thread_sweep(compact: DataFrame, config: Config, degrees: list[int]) -> DataFrame:
    _, n_y = items.totals(compact)
    least = least_count(config.min_support, n_y)
    found = [(d, *measure("", lambda d=d: levelwise.mine_levelwise(compact, least, config.max_length, d).count())[1:]) for d in degrees]
    return compact.sparkSession.createDataFrame(found, "parallelism int, seconds double, n_itemsets bigint")


def plan_metrics(df: DataFrame) -> dict[str, int]:
    """Run df and read what its final plan counted: rows and bytes that scans gave, bytes shuffled and spilled."""
    plan = df._jdf.queryExecution().executedPlan()
    df._jdf.queryExecution().toRdd().count()  # the very plan whose counters are read
    wanted = {"numOutputRows": "rows_scanned", "filesSize": "bytes_scanned", "shuffleBytesWritten": "bytes_shuffled", "spillSize": "bytes_spilled"}
    total = dict.fromkeys(wanted.values(), 0)
    stack = [plan]
    while stack:
        node = stack.pop()
        name = node.nodeName()
        if name == "AdaptiveSparkPlan":
            stack.append(node.executedPlan())
            continue
        if "QueryStage" in name:
            stack.append(node.plan())
            continue
        metrics = node.metrics()
        for key, out in wanted.items():
            if metrics.contains(key) and (key not in ("numOutputRows", "filesSize") or name.startswith("Scan")):
                total[out] += metrics.apply(key).value()
        children = node.children()
        stack += [children.apply(i) for i in range(children.size())]
    return total


def time_to_cause(df: DataFrame, target: str, known: str, config: Config = Config(), columns: list[str] | None = None) -> DataFrame:  # noqa: B008
    """From labelled rows to the known rule: seconds, its place by lift among the condensed rules, how many there are."""
    began = time.perf_counter()
    found = [(r["key"], r["lift"]) for r in explain_failures(df, target, config, columns).select("key", "lift").collect()]  # condensed rules are few
    seconds = time.perf_counter() - began
    lift = dict(found).get(known)
    place = None if lift is None else 1 + sum(x > lift for _, x in found)
    return df.sparkSession.createDataFrame([(known, seconds, place, len(found))], "key string, seconds double, place int, n_rules int")


def plan_text(df: DataFrame) -> str:
    """The formatted physical plan, for checks of pushed filters, pruned columns and joins."""
    return df._sc._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), "formatted")


def itemset_curve(sets: DataFrame, n_y: int, supports: list[float], lengths: list[int]) -> DataFrame:
    """How many sets each support and length gives, from one mining run at the least support and
    the greatest length. The grid is small and known."""
    grid = sets.sparkSession.createDataFrame([(s, k, least_count(s, max(1, n_y))) for s in supports for k in lengths], "min_support double, max_length int, least bigint")
    own = sets.groupBy("len", "n_xy").agg(F.count("*").alias("c"))
    joined = F.broadcast(grid).join(own, (own["n_xy"] >= grid["least"]) & (own["len"] <= grid["max_length"]), "left")
    return joined.groupBy("min_support", "max_length").agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n_itemsets"))


def convergence_point(curve: DataFrame, factor: float = 10.0) -> DataFrame:
    """The least support at which the counts over all lengths lie within the factor."""
    per = curve.groupBy("min_support").agg(F.max("n_itemsets").alias("most"), F.min("n_itemsets").alias("fewest"))
    return per.where((F.col("fewest") > 0) & (F.col("most") <= F.col("fewest") * factor)).agg(F.min("min_support").alias("min_support"))
