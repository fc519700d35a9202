"""Operator 6: quality rules whose thresholds adapt to each language and source.

Everything is DataFrame functions. Measures of each text come from arrays inside its row; the
fences of a (lang, source) group come from mergeable quantile sketches, built by partition and
merged by group, and are joined back. Texts under MIN_WORDS fail anyway and have no say in them.

* mean_word: the group's median plus or minus SPREAD interquartile ranges, wider for a short text,
  whose mean wavers more.
* symbol_share, dup_line_share: zero in most texts, so their quartiles say nothing and the positive
  values are sketched alone. Where symbols are rare a text with many is odd, where they are common
  it is not: the fence is the lower quartile of the positive shares times RARE times the share of
  texts that have any. Repeated lines are found in good texts too: the fence is the upper quartile
  of the positive shares plus TAIL interquartile ranges.

The group's own value is mixed with a default that weighs as PRIOR texts, so it decides where there
are many values and the default where there are few. Far bounds remain, so that a group made of junk
cannot talk itself out of being junk.

Defined cases: a null or empty text has no words, so base_failed; a null lang or source is a group
of its own; a group with no measurable text gets the defaults; an empty table gives an empty
result; other columns pass through `keep` unchanged; repeated rows are judged alike.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import staged, table

WINDOW = 5
MIN_WORDS = 10
REPEATED_PERCENT = 20
SKETCH_K = 200
SPREAD = 6.0
RARE, TAIL, PRIOR = 4.0, 3.0, 10
#: measure: (default, least, greatest) of its upper fence
UPPER = {"symbol_share": (0.1, 0.02, 0.25), "dup_line_share": (0.6, 0.3, 0.95), "mean_word": (20.0, 3.0, 40.0)}
#: the same of its lower fence
LOWER = {"mean_word": (2.0, 0.5, 4.5)}
#: Measures that are zero in most texts.
MOSTLY_ZERO = {"symbol_share", "dup_line_share"}
_SPACE = "[\\x20\\x09-\\x0D]"
_BASE = ["n_words", "word_chars", "n_symbols", "n_dup_lines"]


def _with_words(docs: DataFrame, text: str) -> DataFrame:
    whole = F.coalesce(F.col(text).cast("string"), F.lit(""))
    lines = F.filter(F.split(whole, "\n"), lambda x: x.rlike("[^\\x20\\x09-\\x0D]"))
    return (
        docs.withColumn("__words", F.array_remove(F.split(whole, f"{_SPACE}+"), ""))
        .withColumn("__lines", lines)
        .withColumn("n_words", F.size("__words").cast("long"))
        .withColumn("word_chars", F.length(F.array_join("__words", "")).cast("long"))
        .withColumn("n_symbols", F.regexp_count(whole, F.lit("[#*$%&|<>]")).cast("long"))
        .withColumn("__n_lines", F.size("__lines").cast("long"))
        .withColumn("n_dup_lines", F.col("__n_lines") - F.size(F.array_distinct("__lines")))
        .drop("__lines")
    )


def _with_repeats(df: DataFrame) -> DataFrame:
    """n_repeat_words: words under a window of words that occurs at least twice in the text.

    Each step is a column that the next reads more than once, so none is worked out again inside
    a lambda. Only texts with an equal pair of windows go beyond the distinct count.
    """
    at = lambda i: F.get("__hashes", i)
    starts = F.when(F.col("n_words") >= WINDOW, F.sequence(F.lit(0), F.col("n_words").cast("int") - WINDOW)).otherwise(F.array().cast("array<int>"))
    df = df.withColumn("__hashes", F.transform("__words", lambda w: F.xxhash64(w)))
    df = df.withColumn("__windows", F.transform(starts, lambda i: F.xxhash64(*[at(i + k) for k in range(WINDOW)])))
    df = df.withColumn("__twice", F.size(F.array_distinct("__windows")) < F.size("__windows"))
    pairs = F.sort_array(F.transform("__windows", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    df = df.withColumn("__sorted", F.when(F.col("__twice"), pairs))
    hash_at = lambda i: F.get("__sorted", i)["h"]
    found = F.filter("__sorted", lambda s, i: F.coalesce(s["h"] == hash_at(i - 1), F.lit(False)) | F.coalesce(s["h"] == hash_at(i + 1), F.lit(False)))
    df = df.withColumn("__at", F.when(F.col("__twice"), F.sort_array(F.transform(found, lambda s: s["i"]))))
    covered = F.aggregate(
        F.sequence(F.lit(1), F.size("__at") - 1),
        F.lit(WINDOW),
        lambda n, k: n + F.least(F.lit(WINDOW), F.get("__at", k) - F.get("__at", k - 1)),
    )
    df = df.withColumn("n_repeat_words", F.when(F.col("__twice"), covered).otherwise(0).cast("long"))
    return df.drop("__words", "__hashes", "__windows", "__twice", "__sorted", "__at")


def _measures() -> dict[str, Column]:
    per = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b))
    return {"symbol_share": per("n_symbols", "word_chars"), "dup_line_share": per("n_dup_lines", "__n_lines"), "mean_word": per("word_chars", "n_words")}


def sketches(measured: DataFrame, by: list[str]) -> DataFrame:
    """A row for each group with one quantile sketch for each measure; rows of several tables (days,
    shards) can be merged by `merged`."""
    says = F.col("n_words") >= MIN_WORDS
    counted = {name: F.when(says & (m > 0) if name in MOSTLY_ZERO else says, m) for name, m in _measures().items()}
    found = [F.kll_sketch_agg_double(m, F.lit(SKETCH_K)).alias(name) for name, m in counted.items()]
    return measured.groupBy(*by).agg(*found)


def merged(parts: DataFrame, by: list[str]) -> DataFrame:
    return parts.groupBy(*by).agg(*[F.kll_merge_agg_double(m, F.lit(SKETCH_K)).alias(m) for m in _measures()])


def fences(groups: DataFrame, by: list[str]) -> DataFrame:
    """Each group's fences from its sketches."""

    def quantile(m: str, q: float) -> Column:
        return F.when(F.kll_sketch_get_n_double(m) > 0, F.kll_sketch_get_quantile_double(m, F.lit(q)))

    def own(m: str, sign: int) -> Column:
        if m == "symbol_share":
            texts = F.kll_sketch_get_n_double("mean_word")
            return RARE * quantile(m, 0.25) * F.kll_sketch_get_n_double(m) / F.when(texts > 0, texts)
        range_ = quantile(m, 0.75) - quantile(m, 0.25)
        return quantile(m, 0.75) + TAIL * range_ if m == "dup_line_share" else quantile(m, 0.5) + sign * SPREAD * range_

    def fence(m: str, sign: int, default: float, least: float, most: float) -> Column:
        n = F.kll_sketch_get_n_double(m)
        mixed = F.coalesce((n * own(m, sign) + F.lit(PRIOR * default)) / (n + PRIOR), F.lit(default))
        return F.least(F.lit(most), F.greatest(F.lit(least), mixed))

    upper = [fence(m, 1, *UPPER[m]).alias(f"__max_{m}") for m in UPPER]
    lower = [fence(m, -1, *LOWER[m]).alias(f"__min_{m}") for m in LOWER]
    return groups.select(*by, *upper, *lower)


def judged(measured: DataFrame, limits: DataFrame) -> DataFrame:
    """base_failed and kept for measured rows with __lang and __source."""
    limits = limits.withColumnsRenamed({"__lang": "__of_lang", "__source": "__of_source"})
    on = F.col("__lang").eqNullSafe(F.col("__of_lang")) & F.col("__source").eqNullSafe(F.col("__of_source"))
    base = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > REPEATED_PERCENT * F.col("n_words"))
    m = _measures()
    out = F.lit(False)
    wavers = F.when(F.col("n_words") > 0, 1 / F.sqrt(F.col("n_words")))
    for name in UPPER:
        room = F.lit(1.0) if name in MOSTLY_ZERO else 1 + wavers
        out = out | F.coalesce(m[name] > F.col(f"__max_{name}") * room, F.lit(False))
    for name in LOWER:
        out = out | F.coalesce(m[name] < F.col(f"__min_{name}") * (1 - wavers), F.lit(False))
    return measured.join(limits, on, "left").withColumn("base_failed", base).withColumn("kept", ~base & ~out)


def _grouped(docs: DataFrame) -> DataFrame:
    return docs.withColumn("__lang", F.col("lang").cast("string")).withColumn("__source", F.col("source").cast("string"))


def score(docs: DataFrame) -> DataFrame:
    """doc_id, the base counts, base_failed and kept for docs (doc_id, text, lang, source).

    The counts are staged, so the texts are read once; the fences are as many as groups.
    """
    own = _grouped(docs.select("doc_id", "text", "lang", "source")).select("doc_id", "text", "__lang", "__source")
    measured = staged(_with_repeats(_with_words(own, "text")).drop("text"))
    limits = staged(fences(merged(sketches(measured, ["__lang", "__source"]), ["__lang", "__source"]), ["__lang", "__source"]))
    return judged(measured, limits).select(F.col("doc_id").cast("long"), *_BASE, "n_repeat_words", "base_failed", "kept")


def keep(docs: DataFrame) -> DataFrame:
    """The rows of docs that are kept, with all their columns. Texts are read twice: once for the
    fences, which need the cheap counts alone, and once to judge."""
    names = docs.columns
    numbered = docs.select(*[F.col(f"`{c}`").alias(f"__in_{i}") for i, c in enumerate(names)], F.col("text").alias("__text"), F.col("lang").cast("string").alias("__lang"), F.col("source").cast("string").alias("__source"))
    by = ["__lang", "__source"]
    limits = staged(fences(sketches(_with_words(numbered.select("__text", *by), "__text"), by), by))
    # A filter on `kept` would be pushed below the arrays of each text and work them out again in
    # every lambda; it is not pushed past a column that is not deterministic.
    measured = _with_repeats(_with_words(numbered, "__text")).withColumn("__row", F.monotonically_increasing_id())
    found = judged(measured, limits).where(F.col("kept") & (F.col("__row") >= 0))
    return found.select(*[F.col(f"__in_{i}").alias(c) for i, c in enumerate(names)])


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(table(spark, sf_dir, "documents"))
