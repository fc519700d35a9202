"""Worked examples, invariants and edge cases of the rule miner; exact answers by brute force."""

from itertools import combinations

import pytest
from pyspark.sql import functions as F

from causemine.config import Config, least_count
from causemine.functions import metrics
from causemine.operators import baselines, counting, cuboids, items, levelwise, monitor, patterntree, prepare, rules
from causemine.plans import planner
from causemine.queries import RAW, VOCABULARY, literal_rules
from causemine.sources import log_lines, tables
from causemine.streaming import flows

ROWS = [(a, b, c, int(a == "x" and b == "p") if i % 5 else int(c == "u")) for i, (a, b, c) in enumerate((a, b, c) for a in "xyz" for b in "pq" for c in "uvw" for _ in range(4))]


@pytest.fixture(scope="module")
def compact(spark):
    return prepare.preaggregate(spark.createDataFrame(ROWS, "a string, b string, c string, y int"), ["a", "b", "c"]).persist()


def brute(least, longest):
    found = {}
    for k in range(1, longest + 1):
        for cols in combinations(range(3), k):
            for values in {tuple(r[c] for c in cols) for r in ROWS}:
                inside = [r for r in ROWS if all(r[c] == v for c, v in zip(cols, values))]
                pos = sum(r[3] for r in inside)
                if pos >= least:
                    found[tuple(f"{'abc'[c]}={v}" for c, v in zip(cols, values))] = (len(inside), pos)
    return found


def got(df):
    return {tuple(r["itemset"]): (r["n_x"], r["n_xy"]) for r in df.collect()}


@pytest.mark.parametrize("longest", [1, 2, 3, 5])
def test_miners_equal_brute_force(compact, longest):
    want = brute(3, longest)
    assert got(levelwise.mine_levelwise(compact, 3, longest)) == want
    assert got(levelwise.mine_levelwise(compact, 3, longest, parallelism=3)) == want
    assert got(patterntree.mine_patterntree(compact, 3, longest, 2)) == want
    assert got(patterntree.mine_patterntree(compact, 3, longest, 5, reference="joint")) == want
    for most in (1, 20):
        assert got(patterntree.mine_patterntree(compact, 3, longest, 5, unit_most=most)) == want
    assert got(levelwise.mine_levelwise(compact, 3, longest, parallelism=1)) == want
    assert got(cuboids.mine_cuboids(compact, 3, longest)) == want


def test_weights_and_merging(spark, compact):
    df = spark.createDataFrame(ROWS, "a string, b string, c string, y int")
    parts = [prepare.preaggregate(df.where(x), ["a", "b", "c"]) for x in ("a = 'x'", "a <> 'x'")]
    assert sorted(map(tuple, prepare.merge_compact(*parts, parts[0]).collect())) != sorted(map(tuple, compact.collect()))
    assert sorted(map(tuple, prepare.merge_compact(*parts).collect())) == sorted(map(tuple, compact.collect()))
    raw = prepare.preaggregate(df, ["a", "b", "c"], enabled=False)
    assert got(patterntree.mine_patterntree(raw, 3, 3)) == got(patterntree.mine_patterntree(compact, 3, 3))


def test_invariants(compact):
    n, p = items.totals(compact)
    for r in rules.score_rules(cuboids.mine_cuboids(compact, 1, 3), n, p).collect():
        assert 0 <= r["supp"] <= 1 and r["n_xy"] <= min(r["n_x"], p)
        assert r["lift"] <= min(n / p, n / r["n_x"]) + 1e-9


def test_filters_worked_examples(spark):
    chain = literal_rules(spark, [(["a"], 80, 2.0), (["a", "b", "c"], 78, 6.0)])
    left = lambda df: sorted(r["key"] for r in df.collect())
    assert left(rules.condense(chain, 1.02)) == ["a", "a|b|c"]
    assert left(rules.condense(chain, 1.05)) == ["a|b|c"]
    assert left(rules.condense(chain, 1.05, 3.0, 3.0)) == ["a"]
    weak = literal_rules(spark, [(["a"], 50, 5.0), (["a", "b"], 40, 1.5)])
    assert left(rules.drop_redundant_long(weak)) == ["a"]
    steps = literal_rules(spark, [(["a"], 50, 1.0), (["a", "b"], 50, 2.0), (["a", "b", "c"], 50, 4.0)])
    assert left(rules.condense(steps, 1.05, 2.0, 1.0)) == []
    assert left(rules.condense(steps, 1.05, 2.0, 1.0, "sequential")) == ["a"]


def test_confidence_misses_what_lift_finds(spark):
    row = spark.range(1).select(metrics.confidence(F.lit(100), F.lit(10100)).alias("c"), metrics.lift(F.lit(100), F.lit(10100), F.lit(100), F.lit(1000100)).alias("l"), metrics.conviction(F.lit(5), F.lit(5), F.lit(5), F.lit(10)).alias("v")).first()
    assert row["c"] == pytest.approx(0.00990099) and row["l"] == pytest.approx(99.0198, abs=1e-3) and row["v"] is None


def test_edges(spark):
    none = prepare.preaggregate(spark.createDataFrame([("x", None, 0), ("y", "a=|b", 0)], "a string, b string, y int"), ["a", "b"])
    assert planner.mined_rules(none, Config(algorithm="patterntree")).count() == 0
    every = prepare.preaggregate(spark.createDataFrame([("x", None, 1), ("y", "a=|b", 1)], "a string, b string, y int"), ["a", "b"])
    found = planner.mined_rules(every, Config(min_support=0.5, max_length=9, algorithm="levelwise")).collect()
    assert {r["key"]: r["lift"] for r in found} == {"a=x": 1.0, "a=y": 1.0, "b=a\\=\\|b": 1.0, "a=y|b=a\\=\\|b": 1.0}
    assert got(cuboids.mine_cuboids(every, 1, 9)) == got(patterntree.mine_patterntree(every, 1, 9))
    assert least_count(1.0, 7) == 7 and least_count(0.1, 15) == 2 and least_count(0.1, 0) == 1
    with pytest.raises(ValueError):
        Config(min_support=0)


def test_pruning_inside_the_search_misses_joint_causes(spark):
    df = spark.createDataFrame([(a, b, int((a == "1") != (b == "1"))) for a in "01" for b in "01" for _ in range(10)], "a string, b string, y int")
    c = prepare.preaggregate(df, ["a", "b"])
    assert baselines.prune_by_lift(c, 1, 2, 1.3).count() == 0
    assert baselines.contrast_sets(c, 0.05, 0.01, 2).count() == 0
    n, p = items.totals(c)
    assert rules.filter_lift(rules.score_rules(levelwise.mine_levelwise(c, 1, 2), n, p), 1.3).count() == 2


def test_structuring(spark):
    log_lines.register(spark)
    lines = spark.read.format("log_lines").option("text", RAW).load()
    wide = prepare.structure_log(lines, spark.createDataFrame(VOCABULARY, "pattern string, kind string, tool string"), ["disk_error", "reboot"])
    assert {r["time"]: (r["disk_error"], r["reboot"], r["tool"]) for r in wide.collect()}["1:07"] == (0, 1, "y")


def test_joins_in_time(spark):
    ev = spark.createDataFrame([(1, 100), (1, 205), (2, 50)], "k int, s long").select("k", F.timestamp_seconds("s").alias("ts"))
    cf = spark.createDataFrame([(1, 90, "a"), (1, 205, "b")], "k int, s long, v string").select("k", F.timestamp_seconds("s").alias("ts"), "v")
    assert sorted((r["k"], r["v"]) for r in prepare.enrich_asof(ev, cf, "k", "ts", ["v"]).collect() if r["v"]) == [(1, "a"), (1, "b")]
    near = prepare.within(ev, cf.withColumnRenamed("ts", "t2"), "k", "ts", "t2", 10)
    assert sorted(r["v"] for r in near.collect()) == ["a", "b"]


def test_bounds_alerts_and_feedback(spark, compact):
    assert planner.candidate_bound(4, 2) == 10 and planner.exclusive_bound([2, 3], 2) == 11
    r = planner.mined_rules(compact, Config(algorithm="cuboids", max_length=2))
    assert monitor.new_rules(r, r).count() == 0 and monitor.changed_rules(r, r).count() == 0
    fb = spark.createDataFrame([("a=x", "hide")], "key string, verdict string")
    assert "a=x" not in {x["key"] for x in monitor.apply_feedback(r, fb).collect()}
    metrics.register(spark)
    assert spark.sql("select rule_lift(1, 2, 3, 12) x").first()["x"] == 2.0


def test_scan_is_pruned_and_pushed(spark):
    from causemine.sources.tables import load

    folder = "/root/testdata/sf0.001"
    text = planner.plan_text(prepare.preaggregate(prepare.label(load(spark, folder, "lineitem").where("l_returnflag = 'R'"), "l_linestatus = 'F'"), ["l_returnflag"]))
    assert "EqualTo(l_returnflag,R)" in text and "l_comment" not in text and text.count("Exchange (") <= 2


def test_streams_read_folders_of_unordered_files(spark, tmp_path):
    """More part files than two triggers take, days out of order, copies days apart."""
    at = f"file://{tmp_path}"
    late = "timestamp_ntz '2024-01-01' + make_dt_interval(cast(pmod(id * 7919, 30) as int), cast(pmod(id, 24) as int))"
    rows = spark.range(1200).selectExpr("id % 1000 as event_id", f"{late} as ts", "id % 10 as user_id", "'view' as event_type", "cast(id as double) as value", "'{}' as props")
    rows.repartition(40).write.parquet(f"{at}/events.parquet")
    spark.range(10).selectExpr("id as c_custkey", "'A' as c_mktsegment").coalesce(1).write.parquet(f"{at}/customer.parquet")
    assert len(list(tmp_path.glob("events.parquet/*.parquet"))) == 40
    assert flows.dedup(spark, at).first()["n"] == 1000
    assert flows.tumbling(spark, at).groupBy().sum("n").first()[0] == 1200
    assert flows.enriched(spark, at).first()["n"] == 1200
    assert flows.final_rules(spark, at).where("key = 'event_type=view'").first()["n_x"] == 1200


def test_slices_with_escaped_or_long_values(spark):
    values = ["plain", "a=b|c", "back\\slash", "long" * 3000]
    rows = [(v, x, 10, n) for v in values for x, n in (("p", 9), ("q", 1))]
    compact = spark.createDataFrame(rows, "service string, x string, n_all long, n_pos long")
    found = {(r["label"], r["key"]): (r["n"], r["n_y"], r["n_x"], r["n_xy"]) for r in monitor.mine_by_slice(compact, "service", 0.5, 1).collect()}
    assert found == {(v, "x=p"): (20, 10, 10, 9) for v in values}
    raw = spark.createDataFrame([(v, "p") for v in values], "service string, x string")
    assert {r["label"] for r in monitor.mine_each_label(raw, ["x"], "service", 0.5, 1).collect()} == set(values)


def test_sets_are_counted_in_several_passes(spark, compact):
    known = items.Items.of(compact, 3)
    rows = items.itemize(compact, known)
    sets = levelwise.next_candidates(levelwise.first_level(known, spark), known.columns)
    want = sorted(map(tuple, ((tuple(r["items"]), r["n_x"], r["n_xy"]) for r in counting.count_sets(rows, sets).collect())))
    for options in ({"most": 3}, {"parallelism": 4}, {"parallelism": 1, "most": 5}):
        assert want == sorted((tuple(r["items"]), r["n_x"], r["n_xy"]) for r in counting.count_sets(rows, sets, **options).collect())


def test_the_degree_of_parallelism_is_that_of_the_tasks(spark, compact):
    known = items.Items.of(compact, 3)
    rows = items.itemize(compact, known)
    sets = [[i] for i in range(len(known))]
    for n in (1, 2, 5):
        assert counting._pass(rows, sets, n).rdd.getNumPartitions() == n


def test_fifty_columns(spark):
    """As many columns as grouping sets could not take: C(50, 5) of them are two million."""
    names = [f"c{i:02d}" for i in range(50)]
    rows = [(*[f"v{(k * (i + 3) + i) % 9}" if (k * (2 * i + 1)) % 11 else "usual" for i in range(50)], "ab"[k % 2], k % 5) for k in range(600)]
    df = spark.createDataFrame([(*r[:-1], int(r[-1] == 0)) for r in rows], ", ".join(f"{n} string" for n in [*names, "service"]) + ", y int")
    compact = prepare.preaggregate(df, [*names, "service"])
    found = monitor.mine_by_slice(compact, "service", 0.2, 3).collect()
    assert len(found) > 500 and {r["label"] for r in found} == {"a", "b"}
    for r in found[::97]:
        own = [x for x in rows if x[50] == r["label"] and all(x[names.index(i.split("=")[0])] == i.split("=")[1] for i in r["itemset"])]
        assert (r["n_x"], r["n_xy"]) == (len(own), sum(x[-1] == 0 for x in own))


def test_contrast_sets_by_brute_force(compact):
    n, p = items.totals(compact)
    cells = {r["itemset"] if isinstance(r["itemset"], tuple) else tuple(r["itemset"]): (r["n_x"], r["n_xy"]) for r in cuboids.cuboids(compact, 2).where("n_xy > 0").collect()}

    def stays(nx, nxy, share):
        a, b, c = nxy, nx - nxy, p - nxy
        d = n - a - b - c
        chi = n * (a * d - b * c) ** 2 / max(1, (a + b) * (c + d) * (a + c) * (b + d))
        return chi > baselines.chi2_critical(share) and abs(a / p - b / (n - p)) > 0.01

    ones = {s for s in cells if len(s) == 1}
    first = 0.05 / 2 / len(ones)
    good = {s for s in ones if stays(*cells[s], first)}
    pairs = {(*a, *b) for a in good for b in good if a < b and a[0][0] != b[0][0]}
    share = min(first, 0.05 / 4 / max(1, len(pairs)))
    want = good | {s for s in pairs if s in cells and stays(*cells[s], share)}
    assert want and {tuple(r["itemset"]) for r in baselines.contrast_sets(compact, 0.05, 0.01, 2).collect()} == want


def test_trend_compares_neighbouring_periods_alone(spark):
    rows = [(day, "x", int(i < n)) for day, n in ((1, 4), (2, 2), (4, 1), (9, 3)) for i in range(5)] + [(day, "z", 0) for day in (1, 2, 4, 9) for _ in range(5)]
    found = {r["period"]: (r["change"], r["season_change"]) for r in monitor.rule_trend(spark.createDataFrame(rows, "day int, a string, y int"), ["a"], "y", F.col("day"), 0.5, 1, season=7).collect()}
    assert found == {1: (None, None), 2: (0.0, None), 4: (None, None), 9: (None, 0.0)}


def test_tree_paths_read_as_rules():
    text = "Model\n  If (feature 0 <= 0.5)\n   Predict: 0.0\n  Else (feature 0 > 0.5)\n   If (feature 1 <= 0.5)\n    Predict: 0.0\n   Else (feature 1 > 0.5)\n    Predict: 1.0\n"
    assert baselines.tree_paths(text, ["a=x", "b=y"]) == [("not a=x", 0.0), ("a=x and not b=y", 0.0), ("a=x and b=y", 1.0)]


def test_log_files_in_parts(spark, tmp_path):
    lines = [f"{i % 24}:{i % 60:02d} message {i}" for i in range(500)]
    (tmp_path / "a.log").write_text("\n".join(lines[:300]) + "\n")
    (tmp_path / "b.log").write_text("\n".join(lines[300:]))
    log_lines.register(spark)
    for size in (7, 100, 10**6):
        found = spark.read.format("log_lines").option("bytesPerPartition", size).load(str(tmp_path))
        assert sorted(r["message"] for r in found.collect()) == sorted(x.split(" ", 1)[1] for x in lines)


def test_names_with_signs(spark):
    df = spark.createDataFrame([("x", 1), ("y", 0)], "`it's a=b` string, y int")
    c = prepare.preaggregate(df, ["it's a=b"])
    want = {("it's a\\=b=x",): (1, 1)}
    assert got(cuboids.mine_cuboids(c, 1, 1)) == got(levelwise.mine_levelwise(c, 1, 1)) == got(patterntree.mine_patterntree(c, 1, 1)) == want


def test_presets_and_whole_analysis(spark):
    df = spark.createDataFrame(ROWS, "a string, b string, c string, y int")
    for preset in (Config.urgent(), Config.thorough(), Config.monitor(), Config(min_support=0.4, algorithm="cuboids")):
        found = planner.explain_failures(df, "y", preset.with_(distinct_ratio=1.0)).collect()
        assert all(r["lift"] >= preset.min_lift and r["supp"] >= preset.min_support and r["len"] <= preset.max_length for r in found)
    assert planner.explain_failures(df, "y", Config(min_support=0.4, distinct_ratio=1.0, exclude=("a",))).where("key like '%a=%'").count() == 0


def test_routing_reads_only_the_wanted_days(spark, tmp_path):
    hot, archive = f"{tmp_path}/hot", f"{tmp_path}/archive"
    for day, n in (("2024-01-01", 1), ("2024-01-02", 2), ("2024-01-03", 4)):
        tables.put_day(spark.createDataFrame([("x", n, 0)], "a string, n_all long, n_pos long"), hot, day)
    tables.archive_days(spark, hot, archive, "2024-01-03")
    total = lambda a, b: tables.compact_days(spark, hot, archive, a, b, "2024-01-03").first()["n_all"]
    assert (total("2024-01-01", "2024-01-03"), total("2024-01-02", "2024-01-02"), total("2024-01-03", "2024-01-09")) == (7, 2, 4)
    assert "PartitionFilters: [isnotnull(day" in tables.compact_days(spark, hot, archive, "2024-01-02", "2024-01-02", "2024-01-03")._jdf.queryExecution().toString()
