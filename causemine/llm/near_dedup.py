"""Operator 1: near-duplicates by one-permutation MinHash, banded buckets and star-shaped edges.

Equal shingle sets are collapsed first, so copies cost one row each. The distinct sets share
buckets by the bands of their signatures; a bucket gives star edges, from each member to one
centre, never all pairs. Every edge is confirmed on the full sets. As a star alone can miss a link
between two members that both fail against the centre, buckets that still hold several components
get a second star, and what is then left is compared in blocks of bounded size, whose output is
links between components alone. No link between sets that share a bucket is lost; two sets at the
least similarity miss every bucket with a chance of about 5e-8.

The driver sees counts, a Bloom filter of fixed size and hot keys, of which there is a bounded number.
Components are found by repeated joins.

Defined cases: a text without words has an empty set and links with nothing; a text with fewer
words than a shingle has its whole sequence as one; rows that repeat a doc_id are one document, which
has the links of all its texts (n_shingles is each row's own); a null doc_id is linked with nothing;
an empty table gives an empty result; other columns are left out, or pass through `deduplicated`
unchanged, which leaves one row of each document that stays, the one with the least text.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .minhash import Signer, shingle_sets
from .shared import hot_join, staged, table
from .tokens import by_bytes

#: Members of a block in the last comparison, and bits of the Bloom filter.
BLOCK, BLOOM_BITS = 256, 1 << 24


@lru_cache(maxsize=1)
def _signer() -> Signer:
    """A worker keeps its own."""
    return Signer()


def _similar(a: Column, b: Column, shared: Column, percent: int) -> Column:
    return 100 * shared >= percent * (a + b - shared)


def _sizes_fit(a: Column, b: Column, percent: int) -> Column:
    """Sets of such different sizes cannot be similar."""
    return 100 * F.least(a, b) >= percent * F.greatest(a, b)


def signatures(docs: DataFrame, shingle: int) -> DataFrame:
    """doc_id, n (set size), h1 and h2 (a hash of the set), bands (a key for each; null if empty)."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        signer = _signer()
        for batch in by_bytes(batches, most=2_000_000):
            n, h1, h2, bands = [], [], [], []
            for own in shingle_sets(batch.column("text").to_pylist(), shingle):
                digest = _digest(own)
                n.append(len(own))
                h1.append(digest[0])
                h2.append(digest[1])
                bands.append(signer.band_keys(own).astype(np.int64) if len(own) else None)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(h1, pa.int64()), pa.array(h2, pa.int64()), pa.array(bands, pa.list_(pa.int64()))], ["doc_id", "n", "h1", "h2", "bands"])

    text = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return text.mapInArrow(sign, "doc_id bigint, n bigint, h1 bigint, h2 bigint, bands array<bigint>")


def _digest(own: np.ndarray) -> tuple[int, int]:
    h1, h2 = np.frombuffer(xxhash.xxh3_128_digest(own.tobytes()), ">i8")
    return int(h1), int(h2)


def _sets_of(docs: DataFrame, wanted: DataFrame, shingle: int) -> DataFrame:
    """rep, hashes for the sets in wanted (rep, doc_id, h1, h2), made again from the documents that
    have them. A Bloom filter of fixed size spares most other texts the shuffle; those it lets
    through go at the join."""
    place = F.pmod(F.xxhash64("doc_id"), F.lit(BLOOM_BITS))
    words = wanted.select(F.shiftright(place, 6).cast("int").alias("word"), F.expr("shiftleft(1L, cast(pmod(xxhash64(doc_id), 64) as int))").alias("bit"))
    bits = np.zeros(BLOOM_BITS // 64, np.uint64)
    found = words.groupBy("word").agg(F.bit_or("bit").alias("bits")).toPandas()  # BLOOM_BITS / 64 rows at most
    bits[found["word"].to_numpy(np.int64)] = found["bits"].to_numpy(np.int64).astype(np.uint64)
    shared = docs.sparkSession.sparkContext.broadcast(bits)

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = shared.value
        for batch in batches:
            place = batch.column("place").to_numpy().astype(np.int64)
            maybe = (held[place >> 6] >> (place & 63).astype(np.uint64)) & np.uint64(1) == 1
            for part in by_bytes(iter([batch.filter(pa.array(maybe))]), most=2_000_000):
                own = list(shingle_sets(part.column("text").to_pylist(), shingle))
                both = np.array([_digest(h) for h in own], np.int64).reshape(len(own), 2)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(both[:, 0]), pa.array(both[:, 1]), pa.array([h.view(np.int64) for h in own], pa.list_(pa.int64()))], ["doc_id", "h1", "h2", "hashes"])

    doc = F.col("doc_id").cast("long")
    text = docs.where("doc_id is not null").select(doc.alias("doc_id"), F.pmod(F.xxhash64(doc), F.lit(BLOOM_BITS)).alias("place"), F.col("text").cast("string").alias("text"))
    found = text.mapInArrow(sets, "doc_id bigint, h1 bigint, h2 bigint, hashes array<bigint>")
    # Rows that repeat a document and its text have the same set.
    return found.join(wanted, ["doc_id", "h1", "h2"]).select("rep", "hashes").dropDuplicates(["rep"])


def _confirmed(edges: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The edges (a, b) whose full sets are similar."""
    side = lambda x: sets.select(F.col("rep").alias(x), F.col("hashes").alias(f"of_{x}"))
    both = edges.select("a", "b").join(side("a"), "a").join(side("b"), "b")
    shared = F.size(F.array_intersect("of_a", "of_b"))
    return both.where(_similar(F.size("of_a"), F.size("of_b"), shared, percent)).select("a", "b")


def components(edges: DataFrame) -> DataFrame:
    """node, label (the least node reachable) for the nodes of edges (a, b).

    Every round takes the least label among the neighbours and then the label of that label, so
    the number of rounds grows with the logarithm of a component's width.
    """
    both = staged(edges.select("a", "b").union(edges.select("b", "a")).distinct())
    n = both.count()
    labels = staged(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.col("node")).alias("label")), rows=n)
    while True:
        near = hot_join(both, labels.withColumnRenamed("node", "a"), ["a"], n=n).groupBy(F.col("b").alias("node")).agg(F.min("label").alias("near"))
        step = staged(labels.join(near, "node").select("node", F.col("label").alias("old"), F.least("label", "near").alias("label")), rows=n)
        jump = step.select(F.col("node").alias("label"), F.col("label").alias("next"))
        new = staged(hot_join(step, jump, ["label"], n=n).select("node", "old", F.least("label", "next").alias("label")), rows=n)
        if new.where("label < old").isEmpty():
            return new.select("node", "label")
        labels = new.select("node", "label")


def _relabelled(members: DataFrame, links: DataFrame) -> DataFrame:
    """members with comp replaced by what links (a, b) between components make of it."""
    if links.isEmpty():
        return members
    label = components(links).select(F.col("node").alias("comp"), "label")
    return staged(members.join(label, "comp", "left").withColumn("comp", F.coalesce("label", "comp")).drop("label"))


def _mixed(members: DataFrame) -> DataFrame:
    """The members of buckets that still hold several components."""
    several = staged(members.groupBy("key").agg(F.min("comp").alias("low"), F.max("comp").alias("high")).where("low < high").select("key"))
    return members.join(several, "key", "left_semi")


def _star(members: DataFrame, centre: Column, percent: int) -> tuple[DataFrame, DataFrame]:
    """The members but for each bucket's centre, which is then compared with all of them, and the
    edges to it from members of other components."""
    of = staged(members.groupBy("key").agg(centre.alias("centre"), F.count("*").alias("size")).select("key", "size", "centre.*").withColumnsRenamed({"rep": "b", "n": "n_b", "comp": "comp_b"}))
    joined = hot_join(members, of, ["key"], sizes="size")
    fit = (F.col("rep") != F.col("b")) & (F.col("comp") != F.col("comp_b")) & _sizes_fit(F.col("n"), F.col("n_b"), percent)
    edges = joined.where(fit).select(F.col("rep").alias("a"), "b", "comp", "comp_b").distinct()
    return joined.where("rep <> b").select("key", "rep", "n", "comp"), edges


def _block_links(members: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) between components of a bucket, from comparing all members outside its largest
    component with all members, in blocks of bounded size."""
    sizes = members.groupBy("key", "comp").agg(F.count("*").alias("c"))
    of = sizes.groupBy("key").agg(F.max_by("comp", F.struct("c", "comp")).alias("main"), F.max("c").alias("most"), F.sum("c").alias("all"))
    # Buckets with the same members, from other bands, are compared once.
    same = members.groupBy("key").agg(F.sum(F.xxhash64("rep").cast("decimal(38,0)")).alias("sum"), F.count("*").alias("k"))
    once = same.groupBy("sum", "k").agg(F.min("key").alias("key")).select("key")
    of = staged(of.join(once, "key").select("key", "main", F.ceil(F.col("all") / BLOCK).cast("int").alias("blocks"), F.ceil((F.col("all") - F.col("most")) / BLOCK).cast("int").alias("others")))
    held = members.join(of, "key")
    numbers = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    other = F.pmod(F.xxhash64("rep"), F.col("others")).cast("int")
    block = F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int")
    first = held.where("comp <> main").select("key", other.alias("i"), numbers("blocks").alias("j"), "rep", "comp", F.lit(True).alias("other"))
    second = held.select("key", numbers("others").alias("i"), block.alias("j"), "rep", "comp", F.lit(False).alias("other"))

    def compare(group: pd.DataFrame) -> pd.DataFrame:
        links = set()
        others = group[group["other"]]
        rest = group[~group["other"]]
        if len(others) and len(rest):
            flat = np.concatenate(rest["hashes"].to_numpy())
            count = rest["hashes"].map(len).to_numpy()
            starts = np.cumsum(count) - count
            known, place = np.unique(flat, return_inverse=True)
            comps = rest["comp"].to_numpy()
            for comp, own in zip(others["comp"], others["hashes"], strict=True):
                at = np.searchsorted(known, own)
                at[at == len(known)] = 0
                flag = np.zeros(len(known), np.int64)
                flag[at[known[at] == own]] = 1
                shared = np.add.reduceat(flag[place], starts)
                near = (100 * shared >= percent * (len(own) + count - shared)) & (comps != comp)
                links |= {(comp, c) for c in comps[near].tolist()}
        return pd.DataFrame(list(links), columns=["a", "b"], dtype="int64")

    pairs = first.unionByName(second).join(sets, "rep")
    return pairs.groupBy("key", "i", "j").applyInPandas(compare, "a bigint, b bigint").distinct()


def near_duplicates(docs: DataFrame, shingle: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for docs (doc_id, text)."""
    signed = staged(signatures(docs, shingle))
    own = signed.where("n > 0 and doc_id is not null")
    key = ["h1", "h2"]
    several = _several(own)
    # A distinct set is named, as rep, by the least document that has it, which makes the first of
    # several copies the centre of its bucket; by a number where documents have several sets.
    reps = own.groupBy(*key).agg(F.min("doc_id").alias("doc"), F.min("n").alias("n"), F.count("*").alias("copies"))
    reps = reps.withColumn("rep", F.col("doc") if several is None else F.monotonically_increasing_id())
    reps = staged(reps)
    first = own.select(F.col("doc_id").alias("doc"), *key, "bands").join(reps.select(*key, "doc", "rep", "n"), [*key, "doc"])
    rows = staged(first.select("rep", "n", F.explode("bands").alias("key")).dropDuplicates(["rep", "key"]))
    shared = staged(rows.groupBy("key").agg(F.count("*").alias("k")).where("k > 1").select("key"))
    members = staged(rows.join(shared, "key", "left_semi").withColumn("comp", F.col("rep")))
    wanted = reps.join(members.select("rep").distinct(), "rep", "left_semi").select("rep", F.col("doc").alias("doc_id"), *key)
    sets = staged(_sets_of(docs, staged(wanted), shingle))

    low, high = F.min(F.struct("rep", "n", "comp")), F.max(F.struct(F.xxhash64("rep", "n"), "rep", "n", "comp"))
    comps = members.select("rep", "comp").distinct()
    for centre in (low, F.struct(high["rep"].alias("rep"), high["n"].alias("n"), high["comp"].alias("comp"))):
        rest, edges = _star(members, centre, percent)
        edges = staged(edges)
        found = staged(_confirmed(edges, sets, percent))
        links = staged(found.join(edges, ["a", "b"]).select(F.col("comp").alias("a"), F.col("comp_b").alias("b")).distinct())
        comps = _relabelled(comps, links)
        # What is left of a bucket once its centre has been compared with all of it.
        rest = rest.drop("comp").join(comps, "rep")
        members = staged(_mixed(staged(rest)))
    if not members.isEmpty():
        comps = _relabelled(comps, staged(_block_links(members, sets, percent)))

    placed = reps.join(comps, "rep", "left").withColumn("comp", F.coalesce("comp", "rep"))
    if several is None:
        moved = placed.withColumn("component_id", F.col("comp"))
    else:
        placed = staged(_relabelled(placed, staged(_same_document(own, several, placed))))
        least = staged(placed.groupBy("comp").agg(F.min("doc").alias("component_id"), F.count("*").alias("sets")))
        moved = hot_join(placed, least, ["comp"], sizes="sets")
    moved = staged(moved.where("copies > 1 or component_id <> doc").select(*key, "component_id", "copies"))
    placed = hot_join(signed.select("doc_id", "n", *key), moved, key, "left", sizes="copies")
    component = F.when(F.col("n") > 0, F.coalesce("component_id", "doc_id")).otherwise(F.col("doc_id"))
    return placed.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), component).alias("component_id")).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def _several(own: DataFrame) -> DataFrame | None:
    """The documents that have several sets, if there are any."""
    one = F.xxhash64("h1", "h2")
    found = staged(own.groupBy("doc_id").agg(F.min(one).alias("low"), F.max(one).alias("high")).where("low <> high").select("doc_id"))
    return None if found.isEmpty() else found


def _same_document(own: DataFrame, several: DataFrame, placed: DataFrame) -> DataFrame:
    """Links (a, b) between the components of a document's sets, where it has several."""
    each = own.select("doc_id", "h1", "h2").join(several, "doc_id", "left_semi").distinct().join(placed.select("h1", "h2", "comp"), ["h1", "h2"])
    centre = each.groupBy("doc_id").agg(F.min("comp").alias("b"))
    return each.join(centre, "doc_id").where("comp <> b").select(F.col("comp").alias("a"), "b").distinct()


def deduplicated(docs: DataFrame, shingle: int = 5, percent: int = 80) -> DataFrame:
    """One row of each document that its component keeps, with all columns, and the rows without a doc_id."""
    found = staged(near_duplicates(docs, shingle, percent).where("doc_id is not null").select("doc_id", "kept"))
    doc = docs["doc_id"].cast("long")
    gone = found.where("not kept").select(F.col("doc_id").alias("__id")).distinct()
    again = found.where("kept").groupBy(F.col("doc_id").alias("__id")).agg(F.count("*").alias("c")).where("c > 1").select("__id")
    rest = docs.join(gone, doc == F.col("__id"), "left_anti")
    if again.isEmpty():
        return rest
    least = F.min_by(F.struct(*docs.columns), F.struct(F.col("text").cast("string")))
    one = rest.join(again, doc == F.col("__id"), "left_semi").groupBy(doc).agg(least.alias("__row"))
    return rest.join(again, doc == F.col("__id"), "left_anti").unionByName(one.select("__row.*"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), shingle=2)


#: The same by joining all shingles, for tables of a size that SQL can hold.
SQL = r"""
with recursive w as (select doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as ws from documents),
s as (select distinct doc_id, unnest(case when len(ws) = 0 then [] when len(ws) = 1 then [ws[1]] else list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1]) end) as g from w),
n as (select doc_id, count(*) as n from s group by 1),
p as (select a.doc_id as x, b.doc_id as y, count(*) as c from s a join s b on a.g = b.g and a.doc_id <> b.doc_id group by 1, 2),
l as (select x, y from p join n a on a.doc_id = x join n b on b.doc_id = y where 100 * c >= 80 * (a.n + b.n - c)),
r as (select doc_id as x, doc_id as y from w union select r.x, l.y from r join l on r.y = l.x),
m as (select x, min(y) as component_id from r group by 1)
select w.doc_id, coalesce(n.n, 0)::bigint as n_shingles, m.component_id, w.doc_id = m.component_id as kept
from w left join n on n.doc_id = w.doc_id join m on m.x = w.doc_id
"""
