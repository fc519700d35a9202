"""Rules from counted item-sets, and the two filters that condense them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import metrics as m


def score_rules(sets: DataFrame, n: int, n_y: int, label: str = "y") -> DataFrame:
    """All measures of the rules itemset => label."""
    key = F.array_join("itemset", "|")
    own = sets.select(F.lit(label).alias("label"), "itemset", key.alias("key"), "len", F.lit(n).cast("long").alias("n"), F.lit(n_y).cast("long").alias("n_y"), "n_x", "n_xy")
    return measured(own)


def measured(own: DataFrame) -> DataFrame:
    four = ("n_xy", "n_x", "n_y", "n")
    return own.select(
        "*",
        m.supp_all("n_x", "n").alias("supp_all"),
        m.supp("n_xy", "n_y").alias("supp"),
        m.confidence("n_xy", "n_x").alias("confidence"),
        m.lift(*four).alias("lift"),
        m.conviction(*four).alias("conviction"),
        m.chi2(*four).alias("chi2"),
    )


def filter_lift(rules: DataFrame, min_lift: float) -> DataFrame:
    return rules.where(F.col("lift") >= min_lift)


def filter_confidence(rules: DataFrame, gamma: float) -> DataFrame:
    return rules.where(F.col("confidence") >= gamma)


def subset_pairs(rules: DataFrame) -> DataFrame:
    """Each rule with each rule on a proper part of its items: the longer one explodes into its
    parts (2**len - 2 of them), which meet the shorter ones in an equi-join."""
    parts = F.transform(
        F.sequence(F.lit(1), F.pow(F.lit(2), F.size("itemset")).cast("int") - 2),
        lambda bits: F.array_join(F.filter("itemset", lambda _, i: F.getbit(bits, i) == 1), "|"),
    )
    long = rules.where("len > 1").select("label", F.col("key").alias("long_key"), F.col("n_xy").alias("long_n"), F.col("lift").alias("long_lift"), F.explode(parts).alias("key"))
    short = rules.select("label", "key", F.col("n_xy").alias("short_n"), F.col("lift").alias("short_lift"))
    return long.join(short, ["label", "key"]).withColumnRenamed("key", "short_key")


def _redundant_long(pairs: DataFrame, h_lift: float) -> DataFrame:
    return pairs.groupBy("label", F.col("long_key").alias("key")).agg(F.max("short_lift").alias("top"), F.max("long_lift").alias("own")).where(F.col("top") * h_lift >= F.col("own")).select("label", "key")


def _subsumed_short(pairs: DataFrame, h_supp: float, h_lift: float) -> DataFrame:
    better = (F.col("long_n") * F.lit(float(h_supp)) >= F.col("short_n")) & (F.col("long_lift") > F.col("short_lift") * h_lift)
    return pairs.where(better).select("label", F.col("short_key").alias("key")).distinct()


def drop_redundant_long(rules: DataFrame, h_lift: float = 1.0) -> DataFrame:
    """Filter 1: a rule goes if a part of it reaches its lift, up to the multiplier."""
    return rules.join(_redundant_long(subset_pairs(rules), h_lift), ["label", "key"], "left_anti").select(rules.columns)


def drop_subsumed_short(rules: DataFrame, h_supp: float = 1.05, h_lift: float = 1.0) -> DataFrame:
    """Filter 2: a rule goes if a longer one has about its support and a higher lift."""
    return rules.join(_subsumed_short(subset_pairs(rules), h_supp, h_lift), ["label", "key"], "left_anti").select(rules.columns)


def condense(rules: DataFrame, h_supp: float = 1.05, h_lift_long: float = 1.0, h_lift_short: float = 1.0, mode: str = "simultaneous") -> DataFrame:
    """Both filters. simultaneous: both look at all rules, and may drop a whole chain when a
    multiplier of lift is above 1; sequential: Filter 2 sees what Filter 1 leaves, and never
    empties a set of rules."""
    if mode == "sequential":
        return drop_subsumed_short(drop_redundant_long(rules, h_lift_long), h_supp, h_lift_short)
    pairs = subset_pairs(rules)
    gone = _redundant_long(pairs, h_lift_long).unionByName(_subsumed_short(pairs, h_supp, h_lift_short)).distinct()
    return rules.join(gone, ["label", "key"], "left_anti").select(rules.columns)


def evidence_groups(rules: DataFrame) -> DataFrame:
    """Rules with the same counts, which rest on the same evidence as far as counts tell, as one."""
    keys = F.array_join(F.array_sort(F.collect_list("key")), " ; ")
    return rules.groupBy("label", "n_x", "n_xy").agg(F.count("*").alias("n_rules"), keys.alias("keys"), F.max("lift").alias("lift"))


def coverage(compact: DataFrame, rules: DataFrame) -> DataFrame:
    """rules with a signature of the compact rows that each covers: rules with the same signature
    rest on the very same rows. A row enters by two hashes of its values."""
    dims = [c for c in compact.columns if c not in ("n_all", "n_pos")]
    part = lambda c: F.concat(F.lit(f"{c}="), F.regexp_replace(F.col(c).cast("string"), r"([\\=|])", r"\\$1"))
    held = F.array_compact(F.array(*[F.when(F.col(c).isNotNull(), part(c)) for c in dims]))
    row = compact.select(held.alias("held"), F.xxhash64(*dims).alias("a"), F.xxhash64(F.lit(1), *dims).alias("b"))
    # Rows meet the rules of one of their items; a rule waits at its first.
    at = rules.select("label", "key", "itemset", F.element_at("itemset", 1).alias("item"))
    met = row.withColumn("item", F.explode("held")).join(at, "item").where(F.size(F.array_except("itemset", "held")) == 0)
    signed = met.groupBy("label", "key").agg(F.hex(F.bit_xor("a")).alias("xa"), F.hex(F.bit_xor("b")).alias("xb"), F.count("*").alias("n_rows"))
    return rules.join(signed.select("label", "key", F.concat_ws(":", "xa", "xb", F.col("n_rows").cast("string")).alias("signature")), ["label", "key"])


def same_evidence(compact: DataFrame, rules: DataFrame) -> DataFrame:
    """Groups of rules that are proven to rest on the same rows."""
    keys = F.array_join(F.array_sort(F.collect_list("key")), " ; ")
    return coverage(compact, rules).groupBy("label", "n_x", "n_xy", "signature").agg(F.count("*").alias("n_rules"), keys.alias("keys"), F.max("lift").alias("lift"))


def exclusive_rules(rules: DataFrame) -> DataFrame:
    """Rules whose items never occur without the label."""
    return rules.where("n_xy = n_x")


def top_rules(rules: DataFrame, k: int, by: str = "lift") -> DataFrame:
    return rules.orderBy(F.desc(by), F.desc("supp"), "len", "key").limit(k)
