"""What the miner is compared with."""

from __future__ import annotations

import re
from statistics import NormalDist

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import metrics as m
from .items import Items, itemize, totals
from .levelwise import mine_levelwise


def naive_groupby(df: DataFrame, cols: list[str], target: str = "y") -> DataFrame:
    """Every combination of values with its error rate."""
    return m.error_rate(df, cols, target)


def mllib_patterns(df: DataFrame, dims: list[str], target: str, min_support: float) -> DataFrame:
    """Spark's own pattern growth over the target's raw rows, without weights: items, freq."""
    from pyspark.ml.fpm import FPGrowth

    rows = df.where(F.col(target) == 1).select(F.array(*[F.concat(F.lit(f"{d}="), F.col(d).cast("string")) for d in dims]).alias("items"))
    return FPGrowth(itemsCol="items", minSupport=min_support, minConfidence=1.0).fit(rows).freqItemsets


def chi2_critical(alpha: float) -> float:
    """The value that a chi-square of one degree exceeds with chance alpha."""
    return NormalDist().inv_cdf(1 - alpha / 2) ** 2


def contrast_sets(compact: DataFrame, alpha: float = 0.05, min_dev: float = 0.01, max_length: int = 3, least: int = 1) -> DataFrame:
    """A contrast-set search: a set is extended only if the target and the rest differ on it, by
    chi-square at the level's share of alpha, and by min_dev in support. It cannot find a pair of
    items none of which differs alone. Half of what is left of alpha goes to each level, dealt over
    its candidates, and no level has more for one test than the level before."""
    n, p = totals(compact)
    four = ("n_xy", "n_x", F.lit(p), F.lit(n))
    deviation = F.abs(F.try_divide(F.col("n_xy").cast("double"), F.lit(float(p))) - F.try_divide((F.col("n_x") - F.col("n_xy")).cast("double"), F.lit(float(n - p))))
    shares: dict[int, float] = {}

    def keep(k: int, candidates: int):
        shares[k] = min(alpha / 2**k / max(1, candidates), shares.get(k - 1, alpha))
        return (m.chi2(*four) > chi2_critical(shares[k])) & (deviation > min_dev)

    found = mine_levelwise(compact, least, max_length, keep=keep)
    return found.select("*", m.chi2(*four).alias("chi2"), deviation.alias("deviation"))


def prune_by_lift(compact: DataFrame, least: int, max_length: int, min_lift: float) -> DataFrame:
    """Lift as a condition inside the search: it loses what only shows jointly."""
    n, p = totals(compact)
    return mine_levelwise(compact, least, max_length, keep=lambda k, c: m.lift("n_xy", "n_x", F.lit(p), F.lit(n)) >= min_lift)


def item_vectors(compact: DataFrame, items: Items) -> DataFrame:
    """features (a sparse 0/1 vector over items), label and weight: two rows for each compact row."""
    from pyspark.ml.functions import array_to_vector

    rows = itemize(compact, items)
    dense = F.array(*[F.array_contains("items", F.lit(i)).cast("double") for i in range(len(items))])
    both = F.explode(F.array(F.struct(F.lit(1.0).alias("label"), F.col("n_pos").alias("w")), F.struct(F.lit(0.0).alias("label"), (F.col("n_all") - F.col("n_pos")).alias("w"))))
    return rows.select(array_to_vector(dense).alias("features"), both.alias("b")).select("features", "b.label", F.col("b.w").cast("double").alias("weight")).where("weight > 0")


def tree_paths(debug: str, names: list[str]) -> list[tuple[str, float]]:
    """The ways from the root to the leaves of a tree's printed form, as (rule, predicted label)."""
    found, way = [], []
    for line in debug.split("\n"):
        text = line.strip()
        depth = len(line) - len(line.lstrip())
        if test := re.match(r"(If|Else) \(feature (\d+) (<=|>|in|not in) (.*)\)", text):
            way = [w for w in way if w[0] < depth]
            name = names[int(test[2])]
            way.append((depth, name if test[3] == ">" or (test[3] == "in" and "1.0" in test[4]) else f"not {name}"))
        elif text.startswith("Predict"):
            found.append((" and ".join(w[1] for w in way if w[0] < depth), float(text.rpartition(" ")[2])))
    return found


def tree_baseline(compact: DataFrame, items: Items, depth: int = 4) -> DataFrame:
    """A decision tree over items, its ways to the leaves read as rules, with their lengths."""
    from pyspark.ml.classification import DecisionTreeClassifier

    model = DecisionTreeClassifier(maxDepth=depth, weightCol="weight").fit(item_vectors(compact, items))
    paths = tree_paths(model.toDebugString, [items.name(i) for i in range(len(items))])
    return compact.sparkSession.createDataFrame([(r, r.count(" and ") + 1, p) for r, p in paths], "rule string, len int, prediction double")


def forest_baseline(compact: DataFrame, items: Items, trees: int = 10, depth: int = 4) -> DataFrame:
    """A random forest: the importance of each item, as its many ways are beyond reading."""
    from pyspark.ml.classification import RandomForestClassifier

    model = RandomForestClassifier(numTrees=trees, maxDepth=depth, weightCol="weight", seed=1).fit(item_vectors(compact, items))
    found = [(items.name(i), float(v)) for i, v in enumerate(model.featureImportances.toArray())]
    return compact.sparkSession.createDataFrame(found, "item string, importance double").where("importance > 0")


def logit_baseline(compact: DataFrame, items: Items) -> DataFrame:
    """Logistic regression: a coefficient for each item, none for combinations."""
    from pyspark.ml.classification import LogisticRegression

    model = LogisticRegression(weightCol="weight", regParam=0.001, maxIter=20).fit(item_vectors(compact, items))
    return compact.sparkSession.createDataFrame([(items.name(i), float(v)) for i, v in enumerate(model.coefficients.toArray())], "item string, coefficient double")


def bayes_baseline(compact: DataFrame, items: Items, mined: DataFrame, top: int = 20) -> DataFrame:
    """Naive Bayes on which mined patterns (the rules of the greatest lift) a row holds: it predicts,
    and explains nothing."""
    from pyspark.ml.classification import NaiveBayes
    from pyspark.ml.functions import array_to_vector

    place = {items.name(i): i for i in range(len(items))}
    best = mined.orderBy(F.desc("lift"), F.desc("supp"), "key").select("itemset").limit(top).collect()
    patterns = [[place[x] for x in r["itemset"]] for r in best]
    rows = itemize(compact, items)
    holds = F.array(*[(F.size(F.array_intersect("items", F.array(*map(F.lit, p)))) == len(p)).cast("double") for p in patterns])
    both = F.explode(F.array(F.struct(F.lit(1.0).alias("label"), F.col("n_pos").alias("w")), F.struct(F.lit(0.0).alias("label"), (F.col("n_all") - F.col("n_pos")).alias("w"))))
    data = rows.select(array_to_vector(holds).alias("features"), both.alias("b")).select("features", "b.label", F.col("b.w").cast("double").alias("weight")).where("weight > 0").persist()
    predicted = NaiveBayes(modelType="bernoulli", weightCol="weight").fit(data).transform(data)
    return predicted.groupBy("label", "prediction").agg(F.sum("weight").cast("long").alias("n"))


def cooccurrence(compact: DataFrame) -> DataFrame:
    """How often two items occur together, over all rows and the target's."""
    dims = [c for c in compact.columns if c not in ("n_all", "n_pos")]
    own = F.array(*[F.when(F.col(d).isNotNull(), F.concat(F.lit(f"{d}="), F.col(d).cast("string"))) for d in dims])
    rows = compact.select(F.array_compact(own).alias("i"), "n_all", "n_pos")
    pairs = F.flatten(F.transform("i", lambda a, x: F.transform(F.slice("i", x + 2, F.greatest(F.size("i") - x - 1, F.lit(0))), lambda b: F.struct(a.alias("a"), b.alias("b")))))
    return rows.select(F.explode(pairs).alias("p"), "n_all", "n_pos").groupBy("p.a", "p.b").agg(F.sum("n_all").alias("n_x"), F.sum("n_pos").alias("n_xy"))


def negative_rules(rules: DataFrame) -> DataFrame:
    """X without item z => Y, from the counts of X and of X with z: no further scan."""
    longer = rules.where("len > 1").select("label", F.col("n_x").alias("x2"), F.col("n_xy").alias("xy2"), F.posexplode("itemset").alias("at", "z"), "itemset")
    longer = longer.select("label", "x2", "xy2", "z", F.array_join(F.filter("itemset", lambda _, i: i != F.col("at")), "|").alias("key"))
    own = rules.select("label", "key", "n", "n_y", "n_x", "n_xy").join(longer, ["label", "key"])
    out = own.select("label", "key", F.col("z").alias("without"), "n", "n_y", (F.col("n_x") - F.col("x2")).alias("n_x"), (F.col("n_xy") - F.col("xy2")).alias("n_xy"))
    return out.where("n_x > 0").select("label", "key", "without", "n_x", "n_xy", m.lift("n_xy", "n_x", "n_y", "n").alias("lift"))


def ubiquitous(rules: DataFrame, eps: float = 0.02) -> DataFrame:
    """Items as frequent with the target as without: lift about 1."""
    return rules.where((F.col("len") == 1) & (F.abs(F.col("lift") - 1) <= eps)).select(F.element_at("itemset", 1).alias("item"), "lift")


def drop_ubiquitous(rules: DataFrame, eps: float = 0.02) -> DataFrame:
    """Rules without such items; there are as many as items, so they are broadcast."""
    found = F.broadcast(ubiquitous(rules, eps).agg(F.collect_list("item").alias("all")))
    return rules.crossJoin(found).where(~F.arrays_overlap("itemset", "all")).drop("all")
