"""The operators on texts against brute force, on a small table with nulls, empty, long, repeated and
odd texts and columns with clashing names."""

import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from tokenizers import Tokenizer

from causemine.llm import decontamination, html_extraction, language_id, near_dedup, packing, quality_rules, rans, sharding, token_counts, token_files, toxicity
from causemine.llm.automaton import SuffixAutomaton, words
from causemine.llm.html_tree import main_text
from causemine.llm.tokens import vocabulary

BYTE, WORD = vocabulary("byte_bpe_50k.json"), vocabulary("word_bpe_49k.json")
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, shard int, n_words bigint, rep string, label string"


def corpus():
    draw = random.Random(5)
    vocab = ["".join(draw.choice("abcdeéß") for _ in range(draw.randint(2, 7))) for _ in range(400)]
    texts = [None, "", "   \n ", "one", "One", "a <|endoftext|> b", "日本語 ½ x٣ 😀", "don't  we'LL \t x", "\u0000 nul \x85 next"]
    for _ in range(25):
        own = [draw.choice(vocab) for _ in range(draw.randint(8, 120))]
        texts.append(" ".join(own) + ".")
        near = list(own)
        for _ in range(draw.randint(0, len(own) // 12)):
            near[draw.randrange(len(near))] = draw.choice(vocab)
        texts += [" ".join(near), " ".join(own) + "."]
    texts.append(" ".join(draw.choice(vocab) for _ in range(9000)))
    return [(i, t, None if i % 11 == 0 else "en", "s", len(t or ""), 1, 2, "x", "y") for i, t in enumerate(texts)]


ROWS = corpus()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def ids():
    out = {}
    for path in (BYTE, WORD):
        t = Tokenizer.from_file(path)
        out[path] = {r[0]: t.encode(r[1] or "", add_special_tokens=False).ids for r in ROWS}
    return out


def test_token_counts(docs, empty, ids):
    got = {r["doc_id"]: (r["n_bytes"], r["n_tokens"]) for r in token_counts.count_tokens(docs, BYTE, head=20).collect()}
    assert got == {r[0]: (len((r[1] or "").encode()), len(ids[BYTE][r[0]])) for r in ROWS}
    assert token_counts.count_tokens(docs.union(docs), BYTE).count() == 2 * len(ROWS)
    assert token_counts.count_tokens(empty, BYTE).count() == 0


def test_packing(docs, empty, ids):
    pieces = packing.pack(docs, WORD, 2, window=64).collect()
    found, at = {}, {}
    for p in pieces:
        own = np.frombuffer(p["ids"], "<u4")
        assert len(own) == p["length"] and p["doc_tokens"] == len(ids[WORD][p["doc_id"]]) + 1
        found.setdefault(p["doc_id"], []).append((p["start"], own.tolist()))
        at.setdefault(p["sequence_id"], []).append((p["offset"], p["length"]))
    for doc, own in found.items():
        assert [x for _, part in sorted(own) for x in part] == [*ids[WORD][doc], 2]
    for own in at.values():
        end = 0
        for offset, n in sorted(own):
            assert offset == end
            end += n
        assert end <= 64
    assert packing.pack(empty, WORD, 2).count() == 0


def test_best_fit_takes_the_tightest_window():
    draw = random.Random(2)
    lengths = [draw.randint(1, 50) for _ in range(300)]
    number, offset, used = packing.best_fit_decreasing(np.array(lengths), 50)
    rooms, want = [], []
    for i in sorted(range(300), key=lambda i: -lengths[i]):
        fit = [(r, w) for w, r in enumerate(rooms) if r >= lengths[i]]
        room = min(fit)[0] if fit else 50
        want.append(room - lengths[i])
        if fit:
            w = min(fit)[1]
            rooms[w] -= lengths[i]
        else:
            rooms.append(50 - lengths[i])
    order = sorted(range(300), key=lambda i: -lengths[i])
    assert used == len(rooms) and [50 - int(offset[i]) - lengths[i] for i in order] == want
    held = Counter()
    for n, w in zip(lengths, number):
        held[w] += n
    assert max(held.values()) <= 50


def test_token_files(spark, docs, empty, ids, tmp_path):
    for name, df in (("a", docs), ("b", empty)):
        token_files.write(df, f"file://{tmp_path}/{name}", BYTE, 2, block_ids=300)
    rows = token_files.read(spark, f"file://{tmp_path}/a").orderBy("doc_id").collect()
    at = 0
    for r, want in zip(rows, ROWS, strict=True):
        own = [*ids[BYTE][want[0]], 2]
        assert (r["doc_id"], r["start"], r["n_tokens"]) == (want[0], at, len(own))
        assert np.frombuffer(r["ids"], "<u4").tolist() == own
        at += len(own)
    assert token_files.read(spark, f"file://{tmp_path}/b").count() == 0


def test_rans_round_trip_and_damage():
    draw = np.random.default_rng(1)
    for n in (1, 5, 1000, 70_000):
        own = np.minimum(draw.geometric(0.02, n), 999)
        coder = rans.Table(rans.normalised(np.bincount(own, minlength=1000)))
        block = rans.encode(own, coder, every=8)
        assert (rans.decode(block, coder) == own).all()
        parts = {k: rans.decode_segment(block, coder, k) for k in reversed(range(rans.segments(block)))}
        assert (np.concatenate([parts[k] for k in sorted(parts)]) == own).all()
        assert len(parts) > 1 or n < 70_000
    bad = bytearray(block)
    bad[-3] ^= 1
    with pytest.raises((ValueError, IndexError)):
        rans.decode(bytes(bad), coder)


def shingles(text, size):
    w = (text or "").encode().lower().split()
    return {tuple(w[i : i + size]) for i in range(len(w) - size + 1)} if len(w) >= size else {tuple(w)} - {()}


@pytest.mark.parametrize("size", [2, 5])
def test_near_duplicates(docs, empty, size):
    sets = {r[0]: shingles(r[1], size) for r in ROWS}
    group = {d: d for d in sets}

    def top(d):
        while group[d] != d:
            d = group[d]
        return d

    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = top(a), top(b)
                group[max(x, y)] = min(x, y)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in near_dedup.near_duplicates(docs, size).collect()}
    assert got == {d: (len(s), top(d), top(d) == d) for d, s in sets.items()}
    kept = near_dedup.deduplicated(docs, size)
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.collect()} == {d for d in sets if top(d) == d}
    assert near_dedup.near_duplicates(empty, size).count() == 0


def test_blocks_find_what_stars_miss(spark):
    """A chain of sets, each similar to its neighbours alone, in one bucket."""
    sets = spark.createDataFrame([(i, list(range(i * 10, i * 10 + 100))) for i in range(6)], "rep bigint, hashes array<bigint>")
    members = spark.createDataFrame([(7, i, 100, i) for i in range(6)], "key bigint, rep bigint, n bigint, comp bigint")
    links = {tuple(sorted(r)) for r in near_dedup._block_links(members, sets, 80).collect()}
    assert {(i, i + 1) for i in range(5)} <= links


def test_quality_counts(docs, empty):
    for r in quality_rules.score(docs).collect():
        text = ROWS[r["doc_id"]][1] or ""
        w = re.findall(r"[^\x20\x09-\x0D]+", text)
        seen = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
        covered = {k for i in range(len(w) - 4) if seen[tuple(w[i : i + 5])] > 1 for k in range(i, i + 5)}
        assert (r["n_words"], r["word_chars"], r["n_repeat_words"]) == (len(w), sum(map(len, w)), len(covered))
        assert r["base_failed"] == (len(w) < 10 or 100 * len(covered) > 20 * len(w)) and not (r["base_failed"] and r["kept"])
    kept = {r["doc_id"] for r in quality_rules.keep(docs).collect()}
    assert kept == {r["doc_id"] for r in quality_rules.score(docs).where("kept").collect()} and quality_rules.keep(docs).columns == docs.columns
    assert quality_rules.score(empty).count() == 0


def test_quality_repeats_and_sketches_merge(spark):
    text = "a b c d e x a b c d e f b c d e f\n\nq\nq\n "
    r = quality_rules.score(spark.createDataFrame([(1, text, "en", None)], "doc_id long, text string, lang string, source string")).first()
    assert (r["n_words"], r["n_repeat_words"], r["n_dup_lines"], r["n_symbols"]) == (19, 16, 1, 0)


def test_quality_fences_follow_their_group(spark):
    """A share of symbols that is odd among plain texts, and one that is common in its source."""

    def text(i, symbols):
        own = [f"w{i * 40 + k:04x}"[:5].ljust(5, "x") for k in range(40)]
        return " ".join("#" * min(3, max(0, symbols - 3 * k)) + w[min(3, max(0, symbols - 3 * k)) :] for k, w in enumerate(own))

    rows = [(i, text(i, 14 if i % 20 == 0 else 0), "en", "plain") for i in range(400)]
    rows += [(1000 + i, text(i, 20 + i % 9), "en", "code") for i in range(100)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    kept = {r["doc_id"] for r in quality_rules.score(df).where("kept and not base_failed").collect()}
    assert kept == {i for i in range(400) if i % 20} | {1000 + i for i in range(100)}
    assert {r["doc_id"] for r in quality_rules.keep(df).collect()} == kept
    measured = quality_rules._with_words(df, "text")
    whole = quality_rules.fences(quality_rules.sketches(measured, ["source"]), ["source"])
    high = {r["source"]: r["__max_symbol_share"] for r in whole.collect()}
    assert 0.02 < high["plain"] < 0.07 and 0.14 < high["code"] <= 0.25


def test_decontamination(spark, docs, empty):
    draw = random.Random(3)
    alphabet = [b"aa", b"bb", b"cc"]
    for _ in range(60):
        held = [(str(i), [draw.choice(alphabet) for _ in range(draw.randint(0, 9))]) for i in range(4)]
        machine, text = SuffixAutomaton(held, 4), [draw.choice([*alphabet, b"zz"]) for _ in range(40)]
        hit, names = set(), set()
        for name, w in held:
            k = min(4, len(w))
            for i in range(len(w) - k + 1 if k else 0):
                for j in range(len(text) - k + 1):
                    if text[j : j + k] == w[i : i + k]:
                        hit |= set(range(j, j + k))
                        names.add(name)
        spans, items = machine.matches([text])[0]
        assert {p for a, b in spans for p in range(a, b)} == hit and items == names
    passage = " ".join(ROWS[12][1].split()[:20])
    bench = spark.createDataFrame([(1, passage), (2, None), (3, "..."), (3, "zz9 unknown")], "item_id long, text string")
    assert [last for _, last in decontamination.automata(bench, block_words=1)] == [False, True]
    one = {r["doc_id"]: (r["n_words"], r["items"]) for r in decontamination.find(docs, bench).collect()}
    assert one == {r["doc_id"]: (r["n_words"], r["items"]) for r in decontamination.find(docs, bench, block_words=1).collect()}
    assert "1" in one[12][1] and one[0] == (0, [])
    clean = decontamination.cleaned(docs, bench)
    again = {r["doc_id"]: sum(s["last"] - s["first"] + 1 for s in r["spans"]) for r in decontamination.find(clean, bench).collect()}
    assert all(100 * n < 5 * max(1, one[d][0]) or not n for d, n in again.items()) and clean.columns == docs.columns
    assert {r["doc_id"]: r["text"] for r in clean.collect()}[5] == ROWS[5][1]
    assert decontamination.find(empty, bench).count() == 0 and words("A-b É") == [b"a", b"b", "É".encode()]


def test_sharding(docs, empty):
    for shards in (4, 200):
        rows = sharding.shard(docs, shards).collect()
        per = Counter(r["shard"] for r in rows)
        assert max(per.values()) - min(per.get(s, 0) for s in range(shards)) <= 1 and len(rows) == len(ROWS)
        for s in per:
            assert sorted(r["slot"] for r in rows if r["shard"] == s) == list(range(per[s]))
    rows = sharding.shard(docs, 4).collect()
    assert all((r["size"], r["text_crc32"]) == (len((t := (ROWS[r["doc_id"]][1] or "").encode())) + 16, zlib.crc32(t)) for r in rows)
    at = {}
    for r in rows:
        at.setdefault(ROWS[r["doc_id"]][1] or "", set()).add(r["shard"])
    assert sum(len(s) > 1 for s in at.values()) <= 2
    assert sharding.shard(empty, 4).count() == 0


def test_large_links_move_when_room_is_dealt_over_windows(spark, monkeypatch):
    """As on large input: the hot link needs most of a shard's room, each window has a part of it."""
    monkeypatch.setattr(sharding, "RANKED", 1)
    held = spark.range(6000).selectExpr("id div 2 as link", "cast(id % 2 as int) as shard", "1L as n")
    held = held.unionByName(spark.createDataFrame([(-1, 0, 450), (-1, 1, 450)], "link long, shard int, n long"))
    quota = [3000 + 450 + 460] * 2
    got = sharding.propagate(held, quota, rounds=2).collect()
    assert [r["n"] for r in got if r["link"] == -1] == [900]
    assert sum(r["n"] for r in got) == 6900
    assert all(sum(r["n"] for r in got if r["shard"] == s) <= quota[s] for s in (0, 1))
    assert len({r["link"] for r in got}) == 3001 and len(got) < 6001


def test_language(spark, docs, empty):
    known = {"en": "the quick brown fox jumps over the lazy dog and runs", "de": "der schnelle braune fuchs springt über den faulen hund", "fr": "le renard brun saute par dessus le chien paresseux"}
    train = spark.createDataFrame([(i, known[k] + f" {i}", k) for i in range(60) for k in known], "doc_id long, text string, lang string")
    model = language_id.fit(train)
    test = spark.createDataFrame([(1, "the dog runs over"), (2, "der hund über den"), (3, None), (4, "123 !?"), (5, "le chien saute")], "doc_id long, text string")
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in language_id.identify(test, model).collect()}
    assert [got[i][0] for i in range(1, 6)] == ["en", "de", "und", "und", "fr"] and got[3][1] == 0 and all(0 <= s <= 1 for _, s in got.values())
    assert language_id.identify(empty, language_id.fit(empty)).count() == 0


def test_toxicity(spark, docs, empty):
    rows = [(i, " ".join([f"w{i % 17}", f"v{i % 23}", "plain", "vilest" if i % 4 == 0 else "mild"])) for i in range(200)]
    labels = spark.createDataFrame([(i, 1, int(i % 4 == 0)) for i in range(150)] + [(900, 1, 1), (3, None, None)], "doc_id long, quality int, toxic int")
    df = spark.createDataFrame([*rows, (1000, None), (1001, "")], "doc_id long, text string")
    chain = toxicity.fit(df, labels)
    out = {r["doc_id"] for r in toxicity.score(df, chain).where("toxic").collect()}
    assert out == {i for i in range(200) if i % 4 == 0}
    assert {r["doc_id"] for r in toxicity.clean(df, chain).collect()} == {*range(200), 1000, 1001} - out
    none = toxicity.fit(empty, labels.where("false"))
    assert toxicity.score(docs, none).where("toxic").count() == 0 and toxicity.clean(docs, none).columns == docs.columns


def test_pages(spark):
    page = """<html><head><title>T</title></head><body><header>Site</header><nav><a href=x>a</a></nav><div class="sidebar"><p>Side, text, here and there.</p></div>
    <div class="content"><h1>Head &amp; line</h1><p>First,  with <i>inline</i> text<br>on.<p>Second<ul><li>one<li>two</ul><script>var x="<p>no</p>"</script><form><p>Form</p></form><div class="ad">Buy</div></div>
    <section id="comments"><p>A reader's comment, which is long, long, long.</p></section><footer>foot</footer>"""
    assert main_text(page) == "Head & line\nFirst, with inline text on.\nSecond\none\ntwo"
    for html, want in ((None, ""), ("", ""), ("<p>only", "only"), ("plain", "plain"), ("<p", ""), ("<div>" * 3000 + "deep", "deep")):
        assert main_text(html) == want
    df = spark.createDataFrame([(1, "u", page, "z"), (1, "u", page, "z"), (2, None, None, None)], "page_id long, url string, html string, text string")
    assert sorted((r["page_id"], len(r["text"])) for r in html_extraction.extract(df).collect())[-1] == (2, 0)


def test_pages_keep_the_whole_of_a_long_article():
    """What stands around the best container stays, however the points fall."""
    long = ["Words, of, a, long, paragraph " + "x" * 270 + f" {i}" for i in range(10)]
    inner = "<div class=content>" + "".join(f"<p>{p}</p>" for p in long) + "</div>"
    beside = "<h1>Title</h1><p>Short teaser.</p>bare <b>text</b><ul><li>one<li>two</ul><pre>code</pre>"
    want = "\n".join(["Title", "Short teaser.", "bare text", "one", "two", "code", *long])
    links = "<div><a href=x>Other page</a> <a href=y>Another page</a></div>"
    assert main_text(f"<article>{beside}{inner}</article>") == want
    assert main_text(f"<body>{links}<main><div>{beside}<div>{inner}</div></div></main>{links}") == want
    assert main_text(f"<main><h1>Title</h1><article>{inner}</article>After.</main>") == "\n".join(["Title", *long, "After."])
    assert main_text(f"<div>{beside}{inner}</div>") == want
    assert main_text(f"<div>{links}{beside}{inner}{links}</div>") == want
    assert main_text(f"<body><p>Shop.</p>{links}<article>{inner}</article>") == "\n".join(long)
    assert main_text("<article>" + beside + inner.replace("</div>", "<h2>Part</h2><p>End.</p></div>") + "<div>Last words.</div></article>").endswith("\nPart\nEnd.\nLast words.")
