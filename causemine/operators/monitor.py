"""Many labels, slices, time and feedback: rules as something that is watched."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..config import MICRO
from ..plans.staging import staged
from .counting import count_sets
from .items import Items, dims_of, itemize
from .items import totals as items_totals
from .patterntree import mine_units
from .rules import measured


def mine_each_label(df: DataFrame, dims: list[str], label: str, min_support: float, max_length: int) -> DataFrame:
    """Rules for each label value in turn, the others being its reference, from one search.

    The label is a column of the compact table; a set's reference count is its sum over labels.
    """
    compact = df.groupBy(*dims, F.col(label).alias("label")).agg(F.count("*").alias("n_all")).withColumn("n_pos", F.col("n_all"))
    return _by(compact, "label", dims, min_support, max_length, within=False)


def mine_by_slice(compact: DataFrame, by: str, min_support: float, max_length: int) -> DataFrame:
    """Rules inside each value of a column, with totals of its own: a small service's failures are
    not lost in the support over all."""
    return _by(compact, by, [d for d in dims_of(compact) if d != by], min_support, max_length, within=True)


def _by(compact: DataFrame, by: str, dims: list[str], min_support: float, max_length: int, within: bool) -> DataFrame:
    """One search by pattern trees whose units carry the value of `by`; rows without one are left out."""
    spark = compact.sparkSession
    own = staged(compact.select(F.col(by).cast("string").alias("by"), *dims, "n_all", "n_pos").where("by is not null"))
    total = staged(own.groupBy("by").agg(F.sum("n_all").alias("n"), F.sum("n_pos").alias("n_y")))
    least = total.select("by", F.greatest(F.expr(f"(n_y * {round(min_support * MICRO)} + {MICRO - 1}) div {MICRO}"), F.lit(1)).cast("long").alias("least"))
    known = Items.of_some(own, "by", least)
    rows = staged(itemize(own, known, extra=("by",)))
    found = mine_units(rows.join(least, "by"), max_length, 2 * spark.sparkContext.defaultParallelism)
    if not within:
        found = staged(found)
        together = rows.groupBy("items").agg(F.sum("n_all").alias("n_all"), F.sum("n_pos").alias("n_pos"))
        found = found.drop("n_x").join(count_sets(staged(together), found.select("items").distinct()).select("items", "n_x"), "items")
        total = total.withColumn("n", F.lit(items_totals(compact)[0]).cast("long"))
    sets = found.select("by", known.named(F.col("items")).alias("itemset"), "n_x", "n_xy").join(total, "by")
    return measured(sets.select(F.col("by").alias("label"), "itemset", F.array_join("itemset", "|").alias("key"), F.size("itemset").alias("len"), "n", "n_y", "n_x", "n_xy"))


def new_rules(before: DataFrame, now: DataFrame) -> DataFrame:
    """Rules of this run that the last one did not have."""
    return now.join(before.select("label", "key"), ["label", "key"], "left_anti")


def changed_rules(before: DataFrame, now: DataFrame, factor: float = 1.5) -> DataFrame:
    """Rules whose lift moved by the factor or more, or that came or went."""
    a = before.select("label", "key", F.col("lift").alias("lift_before"))
    b = now.select("label", "key", F.col("lift").alias("lift_now"))
    moved = F.greatest("lift_before", "lift_now") >= factor * F.least("lift_before", "lift_now")
    return a.join(b, ["label", "key"], "full").where(F.col("lift_before").isNull() | F.col("lift_now").isNull() | moved)


def rule_trend(df: DataFrame, dims: list[str], target: str, period: Column, min_support: float, max_length: int, season: int = 7) -> DataFrame:
    """Each rule's lift in each period, its change from the period before, and from one season ago.

    period: the number of a row's period (of days, months, ...). A change is null where the rule was
    not found in the period that it is compared with, or that period has no rows.
    """
    compact = df.withColumn("period", period.cast("long")).groupBy(*dims, "period").agg(F.count("*").alias("n_all"), F.sum(F.col(target).cast("long")).alias("n_pos"))
    found = staged(mine_by_slice(compact, "period", min_support, max_length).select(F.col("label").cast("long").alias("period"), "key", "n_xy", "supp", "lift"))
    ago = lambda n, name: found.select((F.col("period") + n).alias("period"), "key", F.col("lift").alias(name))
    both = found.join(ago(1, "before"), ["period", "key"], "left").join(ago(season, "season"), ["period", "key"], "left")
    return both.select("period", "key", "n_xy", "supp", "lift", (F.col("lift") - F.col("before")).alias("change"), (F.col("lift") - F.col("season")).alias("season_change"))


def alerts(before: DataFrame, now: DataFrame, min_lift: float, factor: float = 1.5) -> DataFrame:
    """What a watcher is told after a run: rules at or above the lift that are new, and those whose
    lift rose by the factor or more."""
    old = before.select("label", "key", F.col("lift").alias("lift_before"))
    both = now.where(F.col("lift") >= min_lift).select("label", "key", "n_xy", "lift").join(old, ["label", "key"], "left")
    kind = F.when(F.col("lift_before").isNull(), "new").when(F.col("lift") >= factor * F.col("lift_before"), "stronger")
    return both.withColumn("alert", kind).where("alert is not null")


def apply_feedback(rules: DataFrame, feedback: DataFrame) -> DataFrame:
    """Rules without those that analysts hid; promoted ones rank first. feedback: key, verdict."""
    own = rules.join(feedback.where("verdict = 'hide'").select("key"), "key", "left_anti").join(feedback.where("verdict = 'promote'").select("key", F.lit(1).alias("promoted")), "key", "left")
    return own.withColumn("promoted", F.coalesce("promoted", F.lit(0))).withColumn("rank", F.row_number().over(W.partitionBy("label").orderBy(F.desc("promoted"), F.desc("lift"), F.desc("supp"), "key")))


def lift_curve(rules: DataFrame, thresholds: list[float]) -> DataFrame:
    """How many rules reach each threshold of lift."""
    grid = F.broadcast(rules.sparkSession.createDataFrame([(float(t),) for t in thresholds], "min_lift double"))
    own = rules.groupBy("lift").agg(F.count("*").alias("c"))
    return grid.join(own, F.col("lift") >= F.col("min_lift"), "left").groupBy("min_lift").agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n_rules"))


def stable_band(curve: DataFrame) -> DataFrame:
    """The widest run of thresholds with one count, not zero. The curve has a few points."""
    order = W.partitionBy(F.lit(1)).orderBy("min_lift")
    step = F.sum(F.coalesce((F.col("n_rules") != F.lag("n_rules").over(order)).cast("int"), F.lit(0))).over(order)
    runs = curve.withColumn("run", step).where("n_rules > 0").groupBy("run", "n_rules").agg(F.min("min_lift").alias("low"), F.max("min_lift").alias("high"))
    return runs.orderBy(F.desc(F.col("high") - F.col("low")), "low").limit(1).select("n_rules", "low", "high")


def appears_at(rules: DataFrame, key: str) -> DataFrame:
    """The highest threshold of lift at which a known rule is still there, and its rank by lift."""
    own = rules.where(F.col("key") == key).select("key", "supp", "lift")
    above = rules.select(F.col("lift").alias("other")).join(F.broadcast(own), F.col("other") > F.col("lift")).agg(F.count("*").alias("higher"))
    return own.crossJoin(above)


def retention(before: DataFrame, after: DataFrame) -> DataFrame:
    a, b = before.agg(F.count("*").alias("n_before")), after.agg(F.count("*").alias("n_after"))
    return a.crossJoin(b).withColumn("retained", F.try_divide(F.col("n_after").cast("double"), F.col("n_before").cast("double")))
