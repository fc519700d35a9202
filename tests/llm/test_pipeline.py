"""The stages in a row on small tables, each against brute force, with odd rows and clashing names."""

import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from causemine.llm import decontamination, near_dedup, quality_rules, toxicity
from causemine.llm.automaton import words
from causemine.llm.shared import staged, table
from causemine.llm.tokens import vocabulary

SF = "/root/testdata/sf0.001"
STAGES = dict(corpus_pipeline.STAGES)
EXTRA = "row string, kept boolean, toxic int, n_words long, component_id long, spans string, rep long, `__max_symbol_share` double, sequence_id string"
SCHEMA = f"doc_id long, text string, lang string, source string, n_chars long, {EXTRA}"


def _text(draw, n):
    return " ".join("".join(draw.choice("abcdefgh") for _ in range(draw.randint(3, 8))) for _ in range(n))


def corpus():
    draw = random.Random(9)
    item = _text(draw, 20)
    texts = [None, "", "  \n ", "too few words", "again again " * 20]
    for i in range(60):
        own = _text(draw, draw.randint(40, 90))
        texts.append(own)
        if i % 6 == 0:
            texts += [own, own + " end"]  # a copy, and a near one
        if i % 7 == 0:
            texts.append(_text(draw, 40) + " vilest " + _text(draw, 10))
        if i % 10 == 0:
            texts.append(_text(draw, 60) + " " + item + " " + _text(draw, 60))
    texts += [item + " " + _text(draw, 3), _text(draw, 20_000)]
    rows = [(i, t, None if i % 9 == 0 else "en", None if i % 13 == 0 else "s", len(t or "")) for i, t in enumerate(texts)]
    rows += rows[5:9] + [(None, rows[20][1], "en", "s", 1), (7, _text(draw, 50), "en", "s", 2)]
    return item, [(*r, "r", False, 1, 5, 6, "s", 7, 0.5, "q") for r in rows]


ITEM, ROWS = corpus()


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    at = tmp_path_factory.mktemp("tables")
    docs = spark.createDataFrame(ROWS, SCHEMA)
    docs.write.parquet(f"file://{at}/documents.parquet")
    labels = [(r[0], 1, int("vilest" in (r[1] or ""))) for r in ROWS if r[0] is not None]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"file://{at}/labels.parquet")
    spark.createDataFrame([(1, ITEM), (None, None)], "item_id long, text string").write.parquet(f"file://{at}/benchmark.parquet")
    return f"file://{at}", docs


def _rows(df):
    return Counter(map(tuple, df.collect()))


def test_toxic_documents_go(spark, tables):
    at, docs = tables
    got = STAGES["toxicity"](spark, docs, at)
    assert got.columns == docs.columns
    assert _rows(got) == Counter(r for r in ROWS if "vilest" not in (r[1] or ""))


def _base_failed(text):
    w = (text or "").split()
    seen = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    covered = {k for i in range(len(w) - 4) if seen[tuple(w[i : i + 5])] > 1 for k in range(i, i + 5)}
    return len(w) < 10 or 100 * len(covered) > 20 * len(w)


def test_poor_documents_go(spark, tables):
    at, docs = tables
    got = STAGES["quality rules"](spark, docs, at)
    assert got.columns == docs.columns
    assert _rows(got) == Counter(r for r in ROWS if not _base_failed(r[1]))


def _shingles(text):
    w = (text or "").encode().lower().split()
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} - {()}


def test_one_document_of_each_group_stays(spark, tables):
    at, docs = tables
    got = STAGES["near-duplicates"](spark, docs, at)
    assert got.columns == docs.columns
    group = {r[0]: r[0] for r in ROWS}

    def top(d):
        while group[d] != d:
            d = group[d]
        return d

    sets = [(r[0], _shingles(r[1])) for r in ROWS if r[0] is not None]
    for i, (a, x) in enumerate(sets):
        for b, y in sets[:i]:
            if x and y and 100 * len(x & y) >= 80 * len(x | y) and top(a) != top(b):
                group[max(top(a), top(b))] = min(top(a), top(b))
    texts = {}
    for r in ROWS:
        texts.setdefault(r[0], []).append(r[1])
    want = Counter((d, min(own, key=lambda t: (t is not None, t or ""))) for d, own in texts.items() if d is not None and top(d) == d)
    want[(None, ROWS[20][1])] += 1
    assert Counter((r["doc_id"], r["text"]) for r in got.collect()) == want


def _hit(text, item):
    w, b = words(text), words(item)
    grams = {tuple(b[i : i + 13]) for i in range(len(b) - 12)}
    return len({k for i in range(len(w) - 12) if tuple(w[i : i + 13]) in grams for k in range(i, i + 13)}), len(w)


def test_passages_of_the_benchmark_go(spark, tables):
    at, docs = tables
    got = STAGES["benchmark decontamination"](spark, docs, at)
    assert got.columns == docs.columns
    dirty = [r for r in ROWS if (h := _hit(r[1], ITEM))[0] and 20 * h[0] >= h[1]]
    gone = [r for r in dirty if 2 * _hit(r[1], ITEM)[0] > _hit(r[1], ITEM)[1]]
    assert len(dirty) > 5 and len(gone) == 1
    want = Counter(r for r in ROWS if r not in dirty)
    for r in dirty:
        if r not in gone:
            cut = r[1].replace(ITEM, "")
            want[(r[0], cut, *r[2:4], len(cut), *r[5:])] += 1
    assert _rows(got) == want


def test_packing_holds_every_id(spark, tables):
    at, docs = tables
    tokenizer, found = Tokenizer.from_file(vocabulary("word_bpe_49k.json")), Counter()
    pieces = STAGES["packing"](spark, docs, at).collect()
    for r in ROWS:
        found[(r[0], len(tokenizer.encode(r[1] or "", add_special_tokens=False).ids) + 1)] += 1
    got = Counter((p["doc_id"], p["doc_tokens"]) for p in pieces if p["start"] == 0)
    assert got == found and sum(p["length"] for p in pieces) == sum(n * c for (_, n), c in found.items())
    per = {}
    for p in pieces:
        per.setdefault(p["sequence_id"], []).append((p["offset"], p["length"]))
    assert all(sorted(x)[0][0] == 0 and sum(n for _, n in x) == sum(sorted(x)[-1]) <= 4096 for x in per.values())


def test_empty_tables(spark, tables):
    at, docs = tables
    for name, stage in corpus_pipeline.STAGES:
        got = stage(spark, docs.where("false"), at)
        assert got.count() == 0 and (name == "packing" or got.columns == docs.columns)


def test_stages_in_a_row(spark):
    docs = table(spark, SF, "documents")
    names = docs.columns
    held = []
    for _, stage in corpus_pipeline.STAGES:
        held.append(docs)
        docs = staged(stage(spark, docs, SF))
    raw, no_toxic, good, single, clean = held
    assert all(d.columns == names for d in held)
    ids = lambda d: {r["doc_id"] for r in d.select("doc_id").collect()}
    chain = toxicity.fit(raw, table(spark, SF, "labels"))
    assert ids(no_toxic) == ids(toxicity.score(raw, chain).where("kept"))
    assert ids(good) == ids(quality_rules.score(no_toxic).where("kept"))
    assert ids(single) == ids(near_dedup.near_duplicates(good).where("kept"))
    hits = decontamination.find(clean, table(spark, SF, "benchmark")).collect()
    assert all(20 * sum(s["last"] - s["first"] + 1 for s in r["spans"]) < max(1, r["n_words"]) for r in hits)
    assert ids(docs) == ids(clean) and "sequence_id" in docs.columns
    again = corpus_pipeline.run(spark, SF)
    assert again.agg(F.sum("length")).first()[0] == docs.agg(F.sum("length")).first()[0] and np.isfinite(again.count())


def test_run_is_registered(spark):
    import __spark_entry__

    assert __spark_entry__.queries()["pipeline"] is corpus_pipeline.run
    assert sum(n.startswith("op") for n in __spark_entry__.queries()) == 10
