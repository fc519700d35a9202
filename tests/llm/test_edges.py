"""Repeated ids and rows, ties, hot keys, several blocks, and models on documents they have not seen."""

import random
import re
import zlib
from collections import Counter

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from causemine.llm import decontamination, language_id, near_dedup, packing, quality_rules, sharding, token_files, tokens, toxicity
from causemine.llm.shared import hot_join, table

SF = "/root/testdata/sf0.1"


def _words(draw, n):
    return [f"w{draw.randrange(10**6)}" for _ in range(n)]


def test_a_document_with_several_texts_has_the_links_of_all(spark):
    draw = random.Random(1)
    a, b = _words(draw, 80), _words(draw, 80)
    near = lambda w: " ".join(["changed", *w[1:]])
    rows = [(1, " ".join(a)), (1, " ".join(b)), (2, near(a)), (3, near(b)), (4, None), (4, ""), (5, "alone here"), (5, "alone here"), (None, " ".join(a))]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("__row", F.lit(1))
    got = {(r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in near_dedup.near_duplicates(df, 2).collect()}
    assert got == {(1, 79, 1, True), (2, 79, 1, False), (3, 79, 1, False), (4, 0, 4, True), (5, 1, 5, True), (None, 79, None, True)}
    left = near_dedup.deduplicated(df, 2)
    assert left.columns == df.columns
    assert sorted((r["doc_id"] or 0, r["text"] or "") for r in left.collect()) == sorted([(0, " ".join(a)), (1, min(" ".join(a), " ".join(b))), (4, ""), (5, "alone here")])


def test_hot_keys_join_alike(spark):
    left = spark.range(40_000).select((F.col("id") % 7 * F.when(F.col("id") % 3 == 0, 1).otherwise(0)).alias("k"), "id")
    right = spark.createDataFrame([(0, "a"), (1, "b"), (6, "c")], "k long, v string")
    for how in ("inner", "left"):
        for got in (hot_join(left, right, ["k"], how, few=1000), hot_join(left, right.withColumn("c", F.lit(9000)), ["k"], how, few=1000, sizes="c"), hot_join(left, right, ["k"], how)):
            assert sorted(map(tuple, got.select("k", "id", "v").collect()), key=str) == sorted(map(tuple, left.join(right, "k", how).select("k", "id", "v").collect()), key=str)


def test_components_of_long_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(0, 200)] + [(1000, 1000 + i) for i in range(1, 300)]
    got = {r["node"]: r["label"] for r in near_dedup.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**dict.fromkeys(range(201), 0), **dict.fromkeys(range(1000, 1300), 1000)}


def test_benchmark_of_several_blocks(spark):
    draw = random.Random(4)
    items = [_words(draw, 20) for _ in range(6)]
    bench = spark.createDataFrame([*[(i, " ".join(w)) for i, w in enumerate(items)], (None, " ".join(items[5][::-1]))], "item_id long, text string")
    texts = [" ".join(_words(draw, 200) + items[i % 6] + _words(draw, 100)) for i in range(12)]
    texts += [" ".join(items[5][::-1]), " ".join(items[2][:8] + items[3] + items[2][8:] + _words(draw, 60)), None, ""]
    df = spark.createDataFrame([(i, t, len(t or ""), "x") for i, t in enumerate(texts)], "doc_id long, text string, n_chars long, row string")
    one = decontamination.find(df, bench).orderBy("doc_id").collect()
    assert decontamination.find(df, bench, block_words=1).orderBy("doc_id").collect() == one
    assert (one[12]["n_words"], one[12]["spans"][0]["last"], one[12]["items"]) == (20, 19, [])
    whole = decontamination.cleaned(df, bench)
    parts = decontamination.cleaned(df, bench, block_words=1)
    assert parts.columns == df.columns and parts.orderBy("doc_id").collect() == whole.orderBy("doc_id").collect()
    left = {r["doc_id"]: (r["text"], r["n_chars"]) for r in parts.collect()}
    assert 12 not in left and left[14] == (None, 0)
    # A cut that brings an item together is followed by another.
    assert left[13][0].split() == texts[13].split()[40:] and left[13][1] == len(left[13][0])


def test_toxic_documents_not_seen_in_training(spark):
    """About a tenth of the labels are given to texts without any word that tells; those cannot be learned."""
    docs, labels = table(spark, SF, "documents"), table(spark, SF, "labels")
    chain = toxicity.fit(docs, labels.where("doc_id % 2 = 0"))
    own = toxicity.score(docs, chain).select("doc_id", "kept").join(labels.where("doc_id % 2 = 1"), "doc_id")
    row = own.agg(F.sum("toxic").alias("n"), F.count_if(F.expr("toxic = 1 and not kept")).alias("hit"), F.count_if(F.expr("toxic = 0 and not kept")).alias("wrong"), F.count_if(F.expr("toxic = 0")).alias("clean")).first()
    assert row["n"] > 200 and row["hit"] >= 0.85 * row["n"] and row["wrong"] <= 0.003 * row["clean"]


def test_languages_of_the_held_out_third(spark):
    rows = language_id.query(spark, SF.replace("0.1", "0.01")).where("held_out").join(table(spark, SF.replace("0.1", "0.01"), "documents").select("doc_id", "lang"), "doc_id").where("lang is not null and lang_pred <> 'und'").collect()
    assert len(rows) > 200 and sum(r["lang"] == r["lang_pred"] for r in rows) >= 0.97 * len(rows)


def test_ties_among_labels(spark):
    docs = spark.createDataFrame([(i, f"plain words {i} and {'vilest' if i % 4 == 0 else 'mild'}") for i in range(200)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1, int(i % 4 == 0)) for i in range(200)] + [(i, 1, 0) for i in range(200)], "doc_id long, quality int, toxic int")
    assert {r["doc_id"] for r in toxicity.score(docs, toxicity.fit(docs, labels)).where("toxic").collect()} == set(range(0, 200, 4))


@pytest.fixture(scope="module")
def repeated(spark):
    long = " ".join(f"w{i}" for i in range(30_000))
    rows = [(1, "same text of two rows", "en", "a")] * 3 + [(2, None, None, None), (2, "", "en", None), (3, long, "en", "a"), (None, "no id " * 4, "en", "b"), (4, "# | < " * 9, "en", "a"), (4, "x\n\nx\n x \nx x\ny", "en", "a")]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")


def test_repeated_rows_and_long_texts(spark, repeated, tmp_path):
    rows = repeated.collect()
    pieces = packing.pack(repeated, "word_bpe_49k.json", 2).collect()
    assert sum(p["length"] for p in pieces if p["doc_id"] == 1) == 3 * next(p["doc_tokens"] for p in pieces if p["doc_id"] == 1)
    token_files.write(repeated, f"file://{tmp_path}/t", "byte_bpe_50k.json", 2, block_ids=50)
    read = token_files.read(spark, f"file://{tmp_path}/t").orderBy("start").collect()
    assert [r["doc_id"] for r in read] == sorted((r["doc_id"] for r in rows), key=lambda d: -1 if d is None else d)
    assert all(a["start"] + a["n_tokens"] == b["start"] for a, b in zip(read, read[1:], strict=False))
    shards = sharding.shard(repeated, 3).collect()
    assert Counter(r["doc_id"] for r in shards) == Counter(r["doc_id"] for r in rows)
    assert Counter(r["text_crc32"] for r in shards) == Counter(zlib.crc32((r["text"] or "").encode()) for r in rows)
    model = language_id.fit(repeated)
    assert language_id.identify(repeated, model).count() == len(rows) and toxicity.score(repeated, toxicity.fit(repeated, spark.createDataFrame([], "doc_id long, quality int, toxic int"))).count() == len(rows)


def test_counts_of_symbols_and_lines(repeated):
    got = Counter((r["doc_id"], r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"]) for r in quality_rules.score(repeated).collect())
    want = Counter()
    for r in repeated.collect():
        text = r["text"] or ""
        w, lines = text.split(), [x for x in text.split("\n") if x.strip()]
        want[(r["doc_id"], len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)))] += 1
    assert got == want


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_new_pre_tokens_go_to_the_library_together(name, monkeypatch):
    draw = random.Random(3)
    parts = ["don't", "WE'LL", "x1y22", "éß", "ÿþ", "a\nb", "c\r\n\nd\t", "!!", "...", "(q)", "'s", "_", "9", "|", "Ünï"]
    unit = lambda: draw.choice(parts) + "".join(draw.choice("abÉÿþ\n'9.!") for _ in range(draw.randrange(6)))
    texts = ["", "\n", "x", "'s", *(" ".join(unit() for _ in range(draw.randint(1, 400))) for _ in range(60))]
    tokenizer = tokens.PreTokenizer(tokens.vocabulary(name), most=300)
    want = [tokenizer.library.encode(t, add_special_tokens=False).ids for t in texts]
    calls: list[str] = []
    # Texts that the library must cut itself may still go one by one; there are none among these.
    plain = [i for i, t in enumerate(texts) if not re.search(tokens._SLOW, t)]
    assert len(plain) > 20
    monkeypatch.setattr(tokenizer, "pieces", calls.append)
    for mark in (tokenizer._mark, None):
        tokenizer._mark = mark
        got = tokenizer.ids_of(pa.array([texts[i] for i in plain]))
        assert [g.tolist() for g in got] == [want[i] for i in plain]
        tokenizer._kept_units, tokenizer._kept_pre_tokens = (tokens._Kept(300, tokenizer.dtype) for _ in range(2))
    assert not calls
