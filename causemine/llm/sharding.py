"""Operator 10: shards of even size that keep linked documents together, by balanced label
propagation.

Law `rows`: the counts of two shards differ by one at most. Documents with equal texts are linked.
Every linked document starts with a shard by its hash. In each round the documents of a link look
at where their neighbours are, and the link proposes the fullest of these shards that still has
room; a shard accepts the proposals that save the most cut edges, up to its quota. Documents
without a link have no say and fill what room is left, so the law holds exactly at the end.

A text with more copies than half a shard is cut into links by the hash of the document's id, so no
link is large. Everything is DataFrame functions; the driver sees one row for each shard.

Defined cases: a null text has size 16 and is linked with empty texts; rows with an equal doc_id
are placed each on its own; with fewer rows than shards some shards are empty; an empty table gives
an empty result; other columns are left out.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .shared import hot_join, staged, table, unsigned_crc32

OVERHEAD = 16
#: Rows that a ranking window holds, and how many such windows there are at most.
RANKED, MOST_WINDOWS = 256, 1 << 16


def _bucket(salt: str, *of: str) -> Column:
    return F.xxhash64(F.lit(salt), *[F.col(c) for c in of])


def _links(rows: DataFrame, limit: int) -> DataFrame:
    """Add link (null where no other document has the text)."""
    groups = rows.groupBy("__text").agg(F.count("*").alias("__n")).where("__n > 1")
    groups = staged(groups.withColumn("__parts", F.ceil(F.col("__n") / limit)))
    joined = hot_join(rows, groups, ["__text"], "left", sizes="__n")
    part = F.pmod(_bucket("part", "doc_id", "__salt"), F.col("__parts"))
    return joined.withColumn("link", F.when(F.col("__n").isNotNull(), F.xxhash64("__text", part))).drop("__n", "__parts")


def _large(asked: DataFrame, parts: int) -> DataFrame:
    """The proposals too large for one of the parts that a shard's room is dealt over, largest first
    as far as the whole room goes. At most `parts` of a shard fit, so a few of each window are enough
    to look at; the others ask again in the next round."""
    first = W.partitionBy("target", "window").orderBy(F.desc("need"), "link")
    few = asked.where(F.col("need") > F.floor(F.col("room") / parts)).withColumn("at", F.row_number().over(first)).where("at <= 64")
    order = W.partitionBy("target").orderBy(F.desc("need"), "link").rowsBetween(W.unboundedPreceding, 0)
    return few.withColumn("sum", F.sum("need").over(order)).where("sum <= room")


def propagate(held: DataFrame, quota: list[int], rounds: int = 6) -> DataFrame:
    """held (link, shard, n): how many documents of a link are in a shard. Returns it after the
    moves: an accepted link is in one shard."""
    spark = held.sparkSession
    shards = len(quota)
    room_of = F.array(*[F.lit(q).cast("long") for q in quota])
    done = None
    held = staged(held)
    for _ in range(rounds):
        loads = {r["shard"]: r["n"] for r in (held if done is None else held.unionByName(done)).groupBy("shard").agg(F.sum("n").alias("n")).collect()}
        room = spark.createDataFrame([(s, quota[s] - loads.get(s, 0)) for s in range(shards)], "shard int, room long")
        total = W.partitionBy("link")
        seen = held.withColumn("total", F.sum("n").over(total)).join(F.broadcast(room), "shard")
        fits = seen.where(F.col("room") + F.col("n") >= F.col("total"))
        best = fits.groupBy("link", "total").agg(F.max(F.struct("n", F.xxhash64("link", "shard").alias("tie"), "shard", "room")).alias("best"))
        asked = best.select("link", "total", F.col("best.shard").alias("target"), F.col("best.room").alias("room"), F.col("best.n").alias("there"))
        asked = staged(asked.withColumn("need", F.col("total") - F.col("there")))
        n = asked.count()
        if not n:
            break
        # A shard's room is dealt over as many windows as keep each of them small.
        parts = max(1, min(MOST_WINDOWS, n // (shards * 64 * RANKED)))
        window = F.pmod(F.xxhash64(F.lit("window"), F.col("link")), F.lit(parts))
        asked, large = asked.withColumn("window", window), None
        if parts > 1:
            large = staged(_large(asked, parts))
            used = F.broadcast(large.groupBy("target").agg(F.sum("need").alias("used")))
            asked = asked.where(F.col("need") <= F.floor(F.col("room") / parts)).join(used, "target", "left")
            asked = asked.withColumn("room", F.col("room") - F.coalesce("used", F.lit(0))).where(F.col("need") <= F.floor(F.col("room") / parts))
        order = W.partitionBy("target", "window").orderBy(F.desc("need"), "link").rowsBetween(W.unboundedPreceding, 0)
        taken = asked.withColumn("sum", F.sum("need").over(order)).where(F.col("sum") <= F.floor(F.col("room") / parts)).select("link", "target", "total")
        taken = taken if large is None else taken.unionByName(large.select("link", "target", "total"))
        accepted = staged(taken.select("link", F.col("target").cast("int").alias("shard"), F.col("total").alias("n")))
        done = accepted if done is None else done.unionByName(accepted)
        before, held = held, staged(held.join(accepted.select("link"), "link", "left_anti"))
        if held.isEmpty() or accepted.isEmpty():
            break
        del before
    return held if done is None else held.unionByName(done)


def _ranked(rows: DataFrame, n: int, shards: int) -> DataFrame:
    """Add rank: a gapless number from 0 within each `__to` (null: -1), without a window over all
    of its rows: numbers inside small buckets, plus how many rows lie in the buckets before."""
    of_shard, of_rest = (max(1, min(MOST_WINDOWS, n // (k * RANKED))) for k in (shards, 1))
    rows = rows.withColumn("__key", F.coalesce("__to", F.lit(-1)))
    rows = rows.withColumn("__bucket", F.pmod(_bucket("rank", "doc_id", "__salt"), F.when(F.col("__key") < 0, F.lit(of_rest)).otherwise(F.lit(of_shard))))
    sizes = rows.groupBy("__key", "__bucket").agg(F.count("*").alias("__n"))
    before = sizes.withColumn("__before", F.sum("__n").over(W.partitionBy("__key").orderBy("__bucket")) - F.col("__n")).drop("__n")
    inside = F.row_number().over(W.partitionBy("__key", "__bucket").orderBy("doc_id", "text_crc32", "size")) - 1
    # At most MOST_WINDOWS * (shards + 1) narrow rows, whatever the input.
    found = rows.withColumn("__inside", inside).join(F.broadcast(before), ["__key", "__bucket"])
    return found.withColumn("rank", F.col("__before") + F.col("__inside")).drop("__key", "__bucket", "__before", "__inside")


def shard(docs: DataFrame, shards: int = 40) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of docs (doc_id, text)."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    size = (F.octet_length(text) + OVERHEAD).cast("long")
    # __salt tells rows of a repeated doc_id apart, where their texts differ.
    rows = staged(docs.select(F.col("doc_id").cast("long"), size.alias("size"), unsigned_crc32(text).alias("text_crc32"), F.xxhash64(text).alias("__text")).withColumn("__salt", F.col("__text")))
    n = rows.count()
    quota = [n // shards + (s < n % shards) for s in range(shards)]
    linked = staged(_links(rows, max(1, n // shards // 2)))
    start = F.pmod(_bucket("start", "doc_id", "__salt"), F.lit(shards)).cast("int")
    of_link = linked.where("link is not null").withColumn("shard", start).groupBy("link", "shard").agg(F.count("*").alias("n"))
    final = propagate(of_link, quota)
    one = staged(final.groupBy("link").agg(F.count("*").alias("__parts"), F.max("shard").alias("__shard")).where("__parts = 1").select(F.col("link").alias("__link"), "__shard"))
    placed = linked.join(one, F.col("link") == F.col("__link"), "left")
    to = F.when(F.col("link").isNotNull(), F.coalesce("__shard", start)).cast("int")
    ranked = staged(_ranked(placed.withColumn("__to", to).drop("__text", "__link", "__shard", "link"), n, shards))
    # Rows beyond a shard's quota join those without a link; they fill the shards in order.
    most = F.element_at(F.array(*[F.lit(q).cast("long") for q in quota]), F.col("__to") + 1)
    stays = F.col("__to").isNotNull() & (F.col("rank") < most)
    kept = {r["__to"]: r["n"] for r in ranked.where(stays).groupBy("__to").agg(F.count("*").alias("n")).collect()}
    over = ranked.where(~F.coalesce(stays, F.lit(False))).where("__to is not null").withColumn("__to", F.lit(None).cast("int"))
    n_free = ranked.where("__to is null").count()
    free = ranked.where("__to is null").select("doc_id", "size", "text_crc32", "rank")
    if not over.isEmpty():
        again = _ranked(over.drop("rank"), n, shards)
        free = free.unionByName(again.select("doc_id", "size", "text_crc32", (F.col("rank") + n_free).alias("rank")))
    shard_of, slot, at = F.lit(None).cast("int"), F.lit(None).cast("long"), 0
    bounds = []
    for s in range(shards):
        held = kept.get(s, 0)
        bounds.append((s, at, at + quota[s] - held, held))
        at += quota[s] - held
    for s, first, end, held in reversed(bounds):
        inside = F.col("rank") < end
        shard_of = F.when(inside, F.lit(s)).otherwise(shard_of)
        slot = F.when(inside, F.col("rank") - first + held).otherwise(slot)
    columns = ["doc_id", "size", "text_crc32", "shard", "slot"]
    filled = free.withColumn("shard", shard_of).withColumn("slot", slot).select(columns)
    staying = ranked.where(stays).withColumn("shard", F.col("__to")).withColumn("slot", F.col("rank")).select(columns)
    return staying.unionByName(filled).select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), F.col("shard").cast("int"), F.col("slot").cast("long"), F.lit(None).cast("int").alias("grown_shard"))


def cut_links(placed: DataFrame, docs: DataFrame) -> DataFrame:
    """How many texts have their copies in more than one shard."""
    texts = docs.select("doc_id", F.xxhash64(F.coalesce("text", F.lit(""))).alias("__text")).join(placed.select("doc_id", "shard"), "doc_id")
    return texts.groupBy("__text").agg(F.count("*").alias("n"), F.countDistinct("shard").alias("shards")).where("n > 1").agg(F.count("*").alias("texts"), F.count_if(F.col("shards") > 1).alias("cut"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard(table(spark, sf_dir, "documents"))
