"""Operator 7: benchmark decontamination with a generalised suffix automaton.

The items are normalised and put into an automaton, which is broadcast; documents stream through
it and keep the longest match at each word. Items are read in blocks of about `block_words` words,
one automaton each. Documents pass through one block after the other, and what one block finds is a
written table before the next is built, so the driver and a worker hold one automaton at a time
whatever the benchmark's size. A benchmark of one block, the usual case, needs no such table.

Defined cases: a null or wordless text has no words and no hits; a null or wordless item has no
window; an item with a null id hits, but is not named or counted; items with an equal id count once;
an empty benchmark hits nothing; an empty table gives an empty result; repeated rows are judged each
on its own; other columns are left out of `find`, and pass through `cleaned` unchanged.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import chain

import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .automaton import SuffixAutomaton, _joined, words
from .shared import staged, table
from .tokens import by_bytes

WINDOW = 13
#: A document is contaminated when this many of its words or more, in percent, are hit.
PERCENT = 5
#: Beyond this share of hit words nothing of use is left, and the document goes as a whole.
COVERAGE = 0.5
_FOUND = "n_words bigint, spans array<struct<first:bigint,last:bigint>>, items array<string>"
_SPANS = pa.list_(pa.struct([("first", pa.int64()), ("last", pa.int64())]))
#: The words of a text as it stands, before A-Z is lower-cased.
_WORD = re.compile("[^\x00-\x2f\x3a-\x40\x5b-\x60\x7b-\x7f]+")


def automata(benchmark: DataFrame, window: int = WINDOW, block_words: int = 200_000) -> Iterator[tuple[Broadcast, bool]]:
    """A broadcast automaton for each block of items, made when it is asked for, and whether it is the last."""
    rows = benchmark.select(F.col("item_id").cast("string").alias("item"), F.col("text").cast("string")).toLocalIterator()
    held, n, more = [], 0, True
    while more:
        if row := next(rows, None):
            held.append((row["item"], words(row["text"])))
            n += len(held[-1][1])
        more = row is not None
        if not more or n >= block_words:
            shared = benchmark.sparkSession.sparkContext.broadcast(SuffixAutomaton(held, window))
            if more and (row := next(rows, None)):
                held = [(row["item"], words(row["text"]))]
                n = len(held[0][1])
                yield shared, False
            else:
                yield shared, True
                return


def _through(rows: DataFrame, blocks: Iterator[tuple[Broadcast, bool]]) -> DataFrame:
    """row, n_words, spans, items of rows (row, text), and their text where there are several blocks."""
    found = rows
    for shared, last in blocks:
        first = found is rows
        keeps = ["row"] if first and last else ["row", "text"]
        kinds = ", ".join(f"{c} {found.schema[c].dataType.simpleString()}" for c in keeps)

        def run(batches: Iterator[pa.RecordBatch], shared=shared, first=first, keeps=keeps) -> Iterator[pa.RecordBatch]:
            for batch in by_bytes(batches, most=2_000_000):
                texts = [words(t) for t in batch.column("text").to_pylist()]
                held = [([], set())] * len(texts)
                if not first:
                    held = [([(x["first"], x["last"] + 1) for x in spans], set(items)) for spans, items in zip(batch.column("spans").to_pylist(), batch.column("items").to_pylist(), strict=True)]
                joined = [(_joined(spans + more), items | names) for (spans, items), (more, names) in zip(held, shared.value.matches(texts), strict=True)]
                spans = pa.array([[{"first": a, "last": b - 1} for a, b in spans] for spans, _ in joined], _SPANS)
                items = pa.array([sorted(items - {None}) for _, items in joined], pa.list_(pa.string()))
                yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in keeps], pa.array(list(map(len, texts)), pa.int64()), spans, items], [*keeps, "n_words", "spans", "items"])

        found = found.mapInArrow(run, f"{kinds}, {_FOUND}")
        if not last:
            found = staged(found)
            shared.unpersist()
    return found


def find(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_words: int = 200_000) -> DataFrame:
    """doc_id, n_words, spans (numbers of the hit words, the last included) and items of each text."""
    rows = docs.select(F.col("doc_id").cast("long").alias("row"), F.col("text").cast("string").alias("text"))
    return _through(rows, automata(benchmark, window, block_words)).select(F.col("row").alias("doc_id"), "n_words", "spans", "items")


def without(text: str, spans: list[tuple[int, int]]) -> str:
    """The text without the words in spans and what stands between them."""
    at = [m.span() for m in _WORD.finditer(text)]
    out, end = [], 0
    for a, b in spans:
        out.append(text[end : at[a][0]])
        end = at[b - 1][1]
    return "".join([*out, text[end:]])


def cleaned(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, percent: int = PERCENT, coverage: float = COVERAGE, block_words: int = 200_000) -> DataFrame:
    """docs with all columns, where contaminated texts have lost their hit spans (n_chars follows) and
    those with more than `coverage` of their words hit are gone. Others stay as they are.

    A cut may bring words together that make a window again: texts that were cut are looked at again
    until none is contaminated.
    """
    blocks = automata(benchmark, window, block_words)
    first = next(blocks)
    if first[1]:
        return _cleaned_by_one(docs, first[0], percent, coverage)
    found = _through(docs.select(F.struct(*docs.columns).alias("row"), F.col("text").cast("string").alias("text")), chain([first], blocks))
    done = None
    while True:
        cut = staged(_cut(found, percent, coverage if done is None else 1.0))
        clean = cut.where("not changed")
        done = clean if done is None else done.unionByName(clean)
        todo = cut.where("changed").select("row", "text")
        if todo.isEmpty():
            break
        found = _through(todo, automata(benchmark, window, block_words))
    new = {"text": F.col("text").cast(docs.schema["text"].dataType)}
    if "n_chars" in docs.columns:
        differs = ~F.col("text").eqNullSafe(F.col("row.text").cast("string"))
        new["n_chars"] = F.when(differs, F.length("text")).otherwise(F.col("row.n_chars")).cast(docs.schema["n_chars"].dataType)
    return done.select(*[new.get(c, F.col("row")[c]).alias(c) for c in docs.columns])


def _cut(found: DataFrame, percent: int, coverage: float) -> DataFrame:
    """row, text and whether it was changed, of the rows that stay."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in by_bytes(batches, most=2_000_000):
            texts, keep, changed = batch.column("text").to_pylist(), [], []
            for i, (n, spans) in enumerate(zip(batch.column("n_words").to_pylist(), batch.column("spans").to_pylist(), strict=True)):
                hit = sum(x["last"] - x["first"] + 1 for x in spans)
                if hit and 100 * hit >= percent * n:
                    if hit > coverage * n or hit == n:
                        continue
                    texts[i] = without(texts[i], [(x["first"], x["last"] + 1) for x in spans])
                    changed.append(True)
                else:
                    changed.append(False)
                keep.append(i)
            at = pa.array(keep, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("row").take(at), pa.array(texts, pa.string()).take(at), pa.array(changed, pa.bool_())], ["row", "text", "changed"])

    row = found.schema["row"].dataType.simpleString()
    return found.mapInArrow(run, f"row {row}, text string, changed boolean")


def _cleaned_by_one(docs: DataFrame, shared: Broadcast, percent: int, coverage: float) -> DataFrame:
    names, schema = docs.columns, docs.schema
    at, size = names.index("text"), names.index("n_chars") if "n_chars" in names else None

    def one_text(text: str, spans: list[tuple[int, int]], n: int) -> str | None:
        """None if the document goes."""
        hit = lambda: sum(b - a for a, b in spans)
        if hit() > coverage * n:
            return None
        while 100 * hit() >= percent * n and spans:
            text = without(text, spans)
            own = words(text)
            spans, n = shared.value.matches([own])[0][0], len(own)
        return text if n else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in by_bytes(batches, most=2_000_000):
            texts = batch.column(at).to_pylist()
            own = [words(t) for t in texts]
            keep, new = [], list(texts)
            for i, (spans, _) in enumerate(shared.value.matches(own)):
                if spans and 100 * sum(b - a for a, b in spans) >= percent * len(own[i]):
                    new[i] = one_text(texts[i], spans, len(own[i]))
                    if new[i] is None:
                        continue
                keep.append(i)
            columns = list(batch.columns)
            columns[at] = pa.array(new, batch.schema.field(at).type)
            if size is not None:
                chars = batch.column(size).to_pylist()
                columns[size] = pa.array([len(b) if b != a and b is not None else c for a, b, c in zip(texts, new, chars, strict=True)], batch.schema.field(size).type)
            yield pa.RecordBatch.from_arrays(columns, schema=batch.schema).take(pa.array(keep, pa.int64()))

    return docs.mapInArrow(run, schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    n_hit = F.aggregate("spans", F.lit(0).cast("long"), lambda n, s: n + s["last"] - s["first"] + 1)
    joined = F.array_join(F.array_sort("items"), ",")
    counted = found.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(joined, 256).alias("items_sha256"))
    return counted.withColumn("contaminated", (F.col("n_hit") > 0) & (100 * F.col("n_hit") >= PERCENT * F.col("n_words")))


#: The same by joining windows, for tables of a size that SQL can hold.
SQL = r"""
with d as (select doc_id, row_number() over () as r, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') as w from documents),
b as (select cast(item_id as varchar) as item, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') as w from benchmark),
iw as (select distinct item, least(13, len(w)) as k, array_to_string(list_slice(w, i, i + least(13, len(w)) - 1), ' ') as g from (select item, w, unnest(range(1, len(w) - least(13, len(w)) + 2)) as i from b where len(w) > 0)),
ks as (select distinct k from iw),
dw as (select r, k, i, array_to_string(list_slice(w, i, i + k - 1), ' ') as g from (select r, w, k, unnest(range(1, len(w) - k + 2)) as i from d, ks where len(w) >= k)),
hit as (select dw.r, dw.i, dw.k, iw.item from dw join iw on dw.k = iw.k and dw.g = iw.g),
pos as (select r, count(distinct p) as n_hit from (select r, unnest(range(i, i + k)) as p from (select distinct r, i, k from hit)) group by r),
its as (select r, count(distinct item) as n_items, sha256(string_agg(distinct item, ',' order by item)) as s from hit group by r)
select d.doc_id, len(d.w)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items, coalesce(s, sha256('')) as items_sha256, coalesce(n_hit, 0) > 0 and 20 * coalesce(n_hit, 0) >= len(d.w) as contaminated
from d left join pos on d.r = pos.r left join its on d.r = its.r
"""
