"""The registered queries: every method, baseline and measure over the experiment workloads."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles as o
from .config import Config, least_count
from .functions import items_sql
from .operators import baselines, counting, cuboids, items, levelwise, monitor, patterntree, prepare, rules, textflow
from .plans import planner
from .plans.staging import folder, staged
from .sources import tables
from .sources.tables import load
from .sources.workloads import END_STATES, WORKLOADS, end_state_rows
from .streaming import flows

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def _query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


def _compact(spark: SparkSession, d: str, name: str) -> DataFrame:
    w = WORKLOADS[name]
    return staged(prepare.preaggregate(w.rows(spark, d), w.names))


def _shown(found: DataFrame) -> DataFrame:
    return found.select("key", "len", "n_x", "n_xy", *[F.round(c, 6).alias(c) for c in ("supp_all", "supp", "confidence", "lift", "conviction", "chi2")])


def _sets(found: DataFrame) -> DataFrame:
    return found.select(F.array_join("itemset", "|").alias("key"), "len", "n_x", "n_xy")


def _mined(spark: SparkSession, d: str, name: str, support: float, length: int, algorithm: str = "patterntree") -> DataFrame:
    return planner.mined_rules(_compact(spark, d, name), Config(min_support=support, max_length=length, algorithm=algorithm))


# --- preparation -------------------------------------------------------------------------------

_KINDS = ["click", "error", "purchase", "signup", "view"]


def _vocabulary(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(f"^{k}$", k, None) for k in _KINDS], "pattern string, kind string, tool string")


@_query("structure_events_wide", "select date_trunc('hour', ts)::varchar as hour, " + ", ".join(f"count(*) filter (event_type = '{k}')::bigint as n_{k}" for k in _KINDS) + " from events group by 1")
def _(spark, d):
    hour = F.date_format(F.date_trunc("hour", F.col("ts").cast("timestamp")), "yyyy-MM-dd HH:mm:ss").alias("hour")
    lines = load(spark, d, "events").select(hour.alias("time"), F.col("event_type").alias("message"))
    wide = prepare.structure_log(lines, _vocabulary(spark), _KINDS)
    return wide.select(F.col("time").alias("hour"), *[F.col(k).alias(f"n_{k}") for k in _KINDS])


@_query("structure_events_narrow", "select date_trunc('hour', ts)::varchar as hour, event_type as kind, count(*)::bigint as n from events group by 1, 2")
def _(spark, d):
    hour = F.date_format(F.date_trunc("hour", F.col("ts").cast("timestamp")), "yyyy-MM-dd HH:mm:ss").alias("hour")
    lines = load(spark, d, "events").select(hour.alias("time"), F.col("event_type").alias("message"))
    return prepare.structure_log(lines, _vocabulary(spark), _KINDS, "narrow").select(F.col("time").alias("hour"), "kind", "n")


RAW = "1:00 disk read failure\n1:00 disk read failure\n1:05 host restarted by agent x\n1:07 power cycled host (agent y)\n1:09 disk read failure\n1:10 ticket opened: cause unknown\n1:11 unrelated chatter\n1:12 ticket opened: cause known"
VOCABULARY = [("disk read failure", "disk_error", None), ("restarted by agent x", "reboot", "x"), ("power cycled", "reboot", "y"), ("cause unknown", "undiagnosed", None), ("cause known", "diagnosed", None)]


#: Events as lines of a raw log, hours since 1970 and minutes before the message: reboots are worded in two
#: ways, views are chatter, and clicks have no time.
_HOST = "coalesce(cast(user_id as string), 'unknown')"
_RAW_LINE = f"""concat(case when event_type = 'click' then '' else concat(unix_date(cast(ts as date)) * 24 + hour(ts), ':', lpad(minute(ts), 2, '0')) end, ' ', case
    when event_type = 'error' then concat('disk read failure on host ', {_HOST})
    when event_type = 'purchase' and user_id % 2 = 0 then concat('host ', {_HOST}, ' restarted by agent x')
    when event_type = 'purchase' then concat('power cycled host ', {_HOST}, ' (agent y)')
    when event_type = 'signup' and event_id % 3 = 0 then 'ticket opened: cause known'
    when event_type = 'signup' then 'ticket opened: cause unknown'
    else 'unrelated chatter' end) as value"""
_RAW_SQL = """select (date_diff('day', date '1970-01-01', ts::date) * 24 + hour(ts))::varchar || ':' || lpad(minute(ts)::varchar, 2, '0') as time,
    count(*) filter (event_type = 'error')::bigint as disk_error, count(*) filter (event_type = 'purchase')::bigint as reboot,
    count(*) filter (event_type = 'signup' and (event_id % 3 = 0) is not true)::bigint as undiagnosed, count(*) filter (event_type = 'signup' and event_id % 3 = 0)::bigint as diagnosed,
    max(case when event_type = 'purchase' then case when user_id % 2 = 0 then 'x' else 'y' end end) as tool
    from events where event_type in ('error', 'purchase', 'signup') and ts >= timestamp '1970-01-01' group by 1"""


@_query("structure_raw_lines", _RAW_SQL)
def _(spark, d):
    lines = prepare.parse_lines(load(spark, d, "events").selectExpr(_RAW_LINE))
    return prepare.structure_log(lines, spark.createDataFrame(VOCABULARY, "pattern string, kind string, tool string"), ["disk_error", "reboot", "undiagnosed", "diagnosed"])


@_query("enrich_star", "select r_name, c_mktsegment, count(*)::bigint as n from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1, 2")
def _(spark, d):
    t = {n: load(spark, d, n) for n in ("orders", "customer", "nation", "region")}
    star = prepare.enrich(t["orders"], [(t["customer"], F.expr("o_custkey = c_custkey")), (t["nation"], F.expr("c_nationkey = n_nationkey")), (t["region"], F.expr("n_regionkey = r_regionkey"))], "inner")
    return star.groupBy("r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@_query("enrich_left_missing", "select c_mktsegment, count(*)::bigint as n, count(*) filter (o_orderkey is null)::bigint as missing from customer left join orders on c_custkey = o_custkey group by 1")
def _(spark, d):
    both = prepare.enrich(load(spark, d, "customer"), [(load(spark, d, "orders", ["o_custkey", "o_orderkey"]), F.expr("c_custkey = o_custkey"))])
    return both.groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.count_if(F.col("o_orderkey").isNull()).alias("missing"))


@_query("label_counts_binary", o.rows("server_like") + " select y::bigint as y, count(*)::bigint as n from base group by 1")
def _(spark, d):
    own = prepare.label(WORKLOADS["server_like"].rows(spark, d).withColumnRenamed("y", "failed"), "failed = 1")
    return own.groupBy("y").agg(F.count("*").alias("n"))


@_query("label_counts_multi", f"with base as ({END_STATES.sql(f', {o.END_STATE} as end_state')}) select end_state, count(*)::bigint as n from base group by 1")
def _(spark, d):
    return end_state_rows(spark, d).groupBy("end_state").agg(F.count("*").alias("n"))


@_query("bucket_latency", "select case when value <= 50 then '(-inf,50]' when value <= 150 then '(50,150]' else '(150,inf)' end as bucket, count(*)::bigint as n from events group by 1")
def _(spark, d):
    return prepare.bucketize(load(spark, d, "events", ["value"]), "value", [50, 150], "bucket").groupBy("bucket").agg(F.count("*").alias("n"))


@_query("bucket_threshold_sweep", "select t::double as threshold, count(*) filter (value > t)::bigint as n_pos, count(*)::bigint as n from events, (values (50.0), (100.0), (150.0), (200.0)) g(t) group by t")
def _(spark, d):
    return prepare.sweep_threshold(load(spark, d, "events", ["value"]), "value", [50, 100, 150, 200])


@_query("bucket_quantile_edges", "with o as (select value, row_number() over (order by value) as r, count(*) over () as c from events), e as (select min(value) filter (r >= ceil(c * 0.25)) as a, min(value) filter (r >= ceil(c * 0.5)) as b, min(value) filter (r >= ceil(c * 0.75)) as d from o) select 1 + (value > a)::bigint + (value > b)::bigint + (value > d)::bigint as part, count(*)::bigint as n from events, e group by 1")
def _(spark, d):
    """The parts by number, as texts of edges differ between engines. The accuracy makes edges exact here."""
    events = load(spark, d, "events", ["value"])
    edges = prepare.quantile_edges(events, "value", 4, accuracy=10_000_000)
    cut = prepare.bucketize(events, "value", edges, "bucket")
    number = sum((F.col("value") > e).cast("long") for e in edges) + F.lit(1)
    return cut.groupBy("bucket", number.alias("part")).agg(F.count("*").alias("n")).select("part", "n")


_LINE = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_discount", "l_returnflag", "l_linestatus"]
_DISTINCT = " union all ".join(f"select '{c}' as \"column\", count(*)::bigint as n, count(distinct {c})::bigint as n_distinct from lineitem" for c in _LINE)


@_query("profile_columns", _DISTINCT)
def _(spark, d):
    return prepare.profile_columns(load(spark, d, "lineitem", _LINE), exact=True).select("column", "n", "n_distinct")


def _auto(ratio):
    def run(spark, d):
        kept = prepare.auto_exclude(load(spark, d, "lineitem", _LINE), ratio)
        return spark.createDataFrame([(c,) for c in kept], '"column" string'.replace('"', ""))

    return run


_query("auto_exclude_2pct", f"select \"column\" from ({_DISTINCT}) where n_distinct <= 0.02 * n")(_auto(0.02))
_query("auto_exclude_sweep", f"select r::double as ratio, count(*)::bigint as kept from ({_DISTINCT}), (values (0.001), (0.02), (0.05), (0.3)) g(r) where n_distinct <= r * n group by r")(
    lambda spark, d: spark.createDataFrame([(r,) for r in (0.001, 0.02, 0.05, 0.3)], "ratio double").join(prepare.profile_columns(load(spark, d, "lineitem", _LINE), exact=True), F.expr("n_distinct <= ratio * n")).groupBy("ratio").agg(F.count("*").alias("kept"))
)

for _n in ("narrow", "mid"):
    _query(f"preagg_{_n}", o.compact(_n) + f" select {', '.join(WORKLOADS[_n].names)}, n_all, n_pos from compact")(lambda spark, d, n=_n: prepare.preaggregate(WORKLOADS[n].rows(spark, d), WORKLOADS[n].names))

_SHAPES = ("narrow", "mid", "server_like", "wide_9", "events_shape", "wide_20", "wide_50")


@_query("preagg_reduction", " union all ".join(f"({o.compact(n)} select '{n}' as workload, sum(n_all)::bigint as n, count(*)::bigint as compact_rows, round(sum(n_all)::double / count(*), 6) as reduction from compact)" for n in _SHAPES))
def _(spark, d):
    out = None
    for n in _SHAPES:
        own = _compact(spark, d, n).agg(F.sum("n_all").alias("n"), F.count("*").alias("compact_rows")).select(F.lit(n).alias("workload"), "n", "compact_rows", F.round(F.col("n").cast("double") / F.col("compact_rows"), 6).alias("reduction"))
        out = own if out is None else out.unionByName(own)
    return out


@_query("preagg_merge_by_year", o.compact("narrow") + f" select {', '.join(WORKLOADS['narrow'].names)}, n_all, n_pos from compact")
def _(spark, d):
    w = WORKLOADS["narrow"]
    df = w.rows(spark, d, ", year(o.o_orderdate) as year")
    return prepare.merge_compact(prepare.preaggregate(df.where("year < 1995"), w.names), prepare.preaggregate(df.where("year >= 1995"), w.names))


# --- items and miners --------------------------------------------------------------------------


@_query("item_dictionary", o.mined("server_like", 1, 100000) + " select (row_number() over (order by n_xy desc, string_split(key, '=')[1], string_split(key, '=')[2]) - 1)::integer as item, string_split(key, '=')[1] as col, string_split(key, '=')[2] as val, n_x, n_xy from rules")
def _(spark, d):
    c = _compact(spark, d, "server_like")
    return items.item_dictionary(c, least_count(0.1, items.totals(c)[1]))


_FREQUENT = ", freq as (" + " union all ".join(f"select '{c}' as col, {c} as val from compact, tot group by {c}, p having sum(n_pos)::hugeint * 1000000 >= p::hugeint * 100000" for c in WORKLOADS["request_like"].names) + ")"
_KEPT = ", ".join(f"case when {c} in (select val from freq where col = '{c}') then {c} end as {c}" for c in WORKLOADS["request_like"].names)


@_query("onehot_sparse", o.compact("request_like") + _FREQUENT + f", kept as (select {_KEPT}, n_all, n_pos from compact) select array_to_string(list_sort(list_filter([{', '.join(chr(39) + c + '=' + chr(39) + ' || ' + c for c in WORKLOADS['request_like'].names)}], lambda x: x is not null)), '|') as items, sum(n_all)::bigint as n_all, sum(n_pos)::bigint as n_pos from kept group by 1")
def _(spark, d):
    """Each row as the set of its frequent items; rows that are then equal are one."""
    c = _compact(spark, d, "request_like")
    known = items.Items.of(c, least_count(0.1, items.totals(c)[1]))
    return items.itemize(c, known).select(F.array_join(F.array_sort(known.named(F.col("items"))), "|").alias("items"), "n_all", "n_pos")


@_query("onehot_wide", o.compact("narrow") + " select (returnflag = 'R') as r, (linestatus = 'F') as f, sum(n_all)::bigint as n_all from compact group by 1, 2")
def _(spark, d):
    c = _compact(spark, d, "narrow")
    wide = items.one_hot_wide(c, items.Items.of(c, 1))
    return wide.groupBy(F.col("`returnflag=R`").alias("r"), F.col("`linestatus=F`").alias("f")).agg(F.sum("n_all").alias("n_all"))


@_query("second_compaction", o.compact("request_like") + _FREQUENT + f", kept as (select {_KEPT}, n_all, n_pos from compact) select {', '.join(WORKLOADS['request_like'].names)}, sum(n_all)::bigint as n_all, sum(n_pos)::bigint as n_pos from kept group by {', '.join(WORKLOADS['request_like'].names)}")
def _(spark, d):
    c = _compact(spark, d, "request_like")
    return items.compact_again(c, items.Items.of(c, least_count(0.1, items.totals(c)[1])))


def _miner(workload, support, length, algorithm):
    return lambda spark, d: _sets(_mined(spark, d, workload, support, length, algorithm))


_query("levelwise_w1_l3", o.sets("server_like", 3, 100000))(_miner("server_like", 0.1, 3, "levelwise"))
_query("levelwise_w2_l4", o.sets("request_like", 4, 100000))(_miner("request_like", 0.1, 4, "levelwise"))
_query("patterntree_w1_l5", o.sets("server_like", 5, 100000))(_miner("server_like", 0.1, 5, "patterntree"))
_query("patterntree_w2_l5", o.sets("request_like", 5, 100000))(_miner("request_like", 0.1, 5, "patterntree"))
_query("cuboids_w1", o.sets("server_like", 3, 100000))(_miner("server_like", 0.1, 3, "cuboids"))


def _tree(**options):
    def run(spark, d):
        c = _compact(spark, d, "server_like")
        return _sets(patterntree.mine_patterntree(c, least_count(0.1, items.totals(c)[1]), 5, **options))

    return run


_query("patterntree_sharded_w1", o.sets("server_like", 5, 100000))(_tree(shards=3))
_query("patterntree_joint_w1", o.sets("server_like", 5, 100000))(_tree(reference="joint"))


@_query("patterntree_unweighted_equals_weighted", o.sets("narrow", 4, 50000))
def _(spark, d):
    w = WORKLOADS["narrow"]
    c = prepare.preaggregate(w.rows(spark, d), w.names, enabled=False)
    return _sets(patterntree.mine_patterntree(c, least_count(0.05, items.totals(c)[1]), 4))


@_query("levelwise_single_thread_w1", o.sets("server_like", 2, 200000))
def _(spark, d):
    c = _compact(spark, d, "server_like")
    return _sets(levelwise.mine_levelwise(c, least_count(0.2, items.totals(c)[1]), 2, parallelism=1))


@_query("levelwise_candidates_k2", o.mined("server_like", 1, 100000) + " select least(a.key, b.key) || '|' || greatest(a.key, b.key) as key from rules a join rules b on string_split(a.key, '=')[1] < string_split(b.key, '=')[1]")
def _(spark, d):
    known = _known(_compact(spark, d, "server_like"))
    found = levelwise.next_candidates(levelwise.first_level(known, spark), known.columns)
    return found.select(F.array_join(F.array_sort(known.named(F.col("items"))), "|").alias("key"))


@_query("levelwise_pruned_k3", o.mined("server_like", 2, 100000) + ", two as (select itemset[1] as a, itemset[2] as b from rules where len = 2) select array_to_string(list_sort([x.a, x.b, y.b]), '|') as key from two x join two y on x.b = y.a join two z on z.a = x.a and z.b = y.b")
def _(spark, d):
    c = _compact(spark, d, "server_like")
    known = _known(c)
    rows = items.itemize(c, known)
    first = levelwise.first_level(known, spark)
    pairs = counting.count_sets(rows, levelwise.next_candidates(first, known.columns)).where(F.col("n_xy") >= least_count(0.1, items.totals(c)[1]))
    pairs = staged(pairs)
    found = levelwise.prune_candidates(levelwise.next_candidates(pairs, known.columns), pairs)
    return found.select(F.array_join(F.array_sort(known.named(F.col("items"))), "|").alias("key"))


def _known(c: DataFrame) -> items.Items:
    return items.Items.of(c, least_count(0.1, items.totals(c)[1]))


@_query("patterntree_split_units_w1", o.sets("server_like", 5, 100000))
def _(spark, d):
    """The same with units so small that most are split, some to the end."""
    c = _compact(spark, d, "server_like")
    return _sets(patterntree.mine_patterntree(c, least_count(0.1, items.totals(c)[1]), 5, unit_most=500))


_query("itemsets_wide_20_l3", o.sets("wide_20", 3, 300000))(_miner("wide_20", 0.3, 3, "patterntree"))
_query("itemsets_wide_20_levelwise_l3", o.sets("wide_20", 3, 300000))(_miner("wide_20", 0.3, 3, "levelwise"))
_query("itemsets_wide_50_l2", o.sets("wide_50", 2, 100000))(_miner("wide_50", 0.1, 2, "patterntree"))


@_query("miners_agree_wide", "select * from (values ('wide_20', 0::bigint, true), ('wide_50', 0::bigint, true)) t(workload, n_different, many)")
def _(spark, d):
    """Level-wise and tree over 20 and 50 features, to length 5, with thousands of sets."""
    out = None
    for name, support, length in (("wide_20", 0.2, 5), ("wide_50", 0.1, 5)):
        c = _compact(spark, d, name)
        least = least_count(support, items.totals(c)[1])
        a, b = (staged(_sets(f(c, least, length))) for f in (levelwise.mine_levelwise, patterntree.mine_patterntree))
        differ = a.exceptAll(b).unionAll(b.exceptAll(a)).agg(F.count("*").alias("n_different"))
        own = differ.crossJoin(b.agg((F.count("*") > 2000).alias("many"))).select(F.lit(name).alias("workload"), "n_different", "many")
        out = own if out is None else out.unionAll(own)
    return out


@_query("miners_agree", "select 0::bigint as n_different")
def _(spark, d):
    c = _compact(spark, d, "mid")
    least = least_count(0.2, items.totals(c)[1])
    a, b, e = (_sets(f(c, least, 3)) for f in (levelwise.mine_levelwise, patterntree.mine_patterntree, cuboids.mine_cuboids))
    return a.exceptAll(b).unionAll(b.exceptAll(a)).unionAll(b.exceptAll(e)).unionAll(e.exceptAll(b)).agg(F.count("*").alias("n_different"))


# --- rules and filters -------------------------------------------------------------------------

for _q, _w, _s, _k in (("w1", "server_like", 0.1, 5), ("w2", "request_like", 0.1, 5), ("w9", "latency", 0.1, 3), ("w11", "session", 0.05, 4), ("w12", "text", 0.1, 3)):
    _query(f"rules_{_q}", o.rules(_w, _k, round(_s * 1e6)))(lambda spark, d, w=_w, s=_s, k=_k: _shown(_mined(spark, d, w, s, k)))

_query("rules_each_label_w10", o.by_label(2, 200000))(lambda spark, d: monitor.mine_each_label(end_state_rows(spark, d), END_STATES.names, "end_state", 0.2, 2).select("label", "key", "len", "n_x", "n_xy", F.round("lift", 6).alias("lift")))
_query("rules_by_slice_w1", o.sliced("mid", "region", "", 2, 300000) + " select region as label, key, n_x, n_xy, round(lift, 6) as lift from rules")(lambda spark, d: monitor.mine_by_slice(_compact(spark, d, "mid"), "region", 0.3, 2).select("label", "key", "n_x", "n_xy", F.round("lift", 6).alias("lift")))


@_query("confidence_vs_lift", o.mined("request_like", 2, 0) + " select key, round(confidence, 6) as confidence, round(lift, 6) as lift, confidence >= 0.5 as passes_half from rules")
def _(spark, d):
    """The target is rare: parts of its cause have a lift of some 20 with a confidence of a tenth."""
    c = _compact(spark, d, "request_like")
    n, p = items.totals(c)
    found = rules.score_rules(cuboids.mine_cuboids(c, 1, 2), n, p)
    return found.select("key", F.round("confidence", 6).alias("confidence"), F.round("lift", 6).alias("lift"), (F.col("confidence") >= 0.5).alias("passes_half"))


def _condensed(workload, support, length, **options):
    def run(spark, d):
        found = staged(rules.filter_lift(_mined(spark, d, workload, support, length), 1.0))
        return rules.condense(found, **options).select("key", "len", "n_xy", F.round("lift", 6).alias("lift"))

    return run


_OUT = " select key, len, n_xy, round(lift, 6) as lift from r where "
_query("filter1_w1", o.condensed("server_like", 5, 100000, 1.0, 1.05, 1.0, "simultaneous") + _OUT + "not exists (from f1 where f1.key = r.key)")(lambda spark, d: rules.drop_redundant_long(staged(rules.filter_lift(_mined(spark, d, "server_like", 0.1, 5), 1.0))).select("key", "len", "n_xy", F.round("lift", 6).alias("lift")))
_query("filter2_w1", o.condensed("server_like", 5, 100000, 1.0, 1.05, 1.0, "simultaneous") + _OUT + "not exists (from f2 where f2.key = r.key)")(lambda spark, d: rules.drop_subsumed_short(staged(rules.filter_lift(_mined(spark, d, "server_like", 0.1, 5), 1.0))).select("key", "len", "n_xy", F.round("lift", 6).alias("lift")))
_LEFT = "not exists (from f1 where f1.key = r.key) and not exists (from f2 where f2.key = r.key)"
_BOTH = _OUT + _LEFT
_query("condense_w1", o.condensed("server_like", 5, 100000, 1.0, 1.05, 1.0, "simultaneous") + _BOTH)(_condensed("server_like", 0.1, 5))
_query("condense_w1_strong", o.condensed("server_like", 5, 100000, 1.0, 1.05, 1.2, "simultaneous") + _BOTH)(_condensed("server_like", 0.1, 5, h_lift_long=1.2, h_lift_short=1.2))
_query("condense_w2_seq", o.condensed("request_like", 5, 100000, 1.0, 1.05, 1.0, "sequential") + _BOTH)(_condensed("request_like", 0.1, 5, mode="sequential"))
for _n, _k in (("five_way", 5), ("five_way", 3), ("five_way_noisy", 5), ("five_way_noisy", 3)):
    _query(f"condense_{_n}_l{_k}", o.condensed(_n, _k, 500000, 1.0, 1.05, 1.0, "simultaneous") + _BOTH)(_condensed(_n, 0.5, _k))


def literal_rules(spark: SparkSession, rows: list[tuple[list[str], int, float]]) -> DataFrame:
    return spark.createDataFrame([("y", s, "|".join(s), len(s), n, lift) for s, n, lift in rows], "label string, itemset array<string>, key string, len int, n_xy bigint, lift double")


def _condensed_counts(workload, support, length, cases, column):
    def run(spark, d):
        found, out = staged(rules.filter_lift(_mined(spark, d, workload, support, length), 1.0)), None
        for name, case in cases.items():
            own = rules.condense(found, *case).agg(F.count("*").alias("n_rules")).select(F.lit(name).alias(column), "n_rules")
            out = own if out is None else out.unionAll(own)
        return out

    return run


_CASES = {name: (hs, hl, hl, "simultaneous") for name, hs, hl in (("h_supp 1.02", 1.02, 1.0), ("h_supp 1.05", 1.05, 1.0), ("h_lift 3", 1.05, 3.0))}
_query("condense_examples", o.condensed_counts("five_way_noisy", 5, 500000, 1.0, _CASES, "case_name"))(_condensed_counts("five_way_noisy", 0.5, 5, _CASES, "case_name"))
_MODES = {m: (1.05, 2.0, 1.0, m) for m in ("sequential", "simultaneous")}
_query("condense_annihilation", o.condensed_counts("short_steps", 3, 500000, 1.0, _MODES, "mode"))(_condensed_counts("short_steps", 0.5, 3, _MODES, "mode"))


_query("evidence_groups_w1", o.mined("server_like", 3, 100000) + " select n_x, n_xy, count(*)::bigint as n_rules, round(max(lift), 6) as lift from rules group by n_x, n_xy")(lambda spark, d: rules.evidence_groups(_mined(spark, d, "server_like", 0.1, 3)).select("n_x", "n_xy", "n_rules", F.round("lift", 6).alias("lift")))
#: Rules are grouped by the list of the compact rows that they cover.
_COVERED = o.mined("five_way", 5, 900000) + ", numbered as (select *, row_number() over () as number from compact), has as (select number, list_filter([" + ", ".join(f"'{c}=' || {c}" for c in WORKLOADS["five_way"].names) + "], lambda x: x is not null) as held from numbered), covered as (select key, n_x, n_xy, list(number order by number) as numbers from rules join has on list_has_all(held, itemset) group by 1, 2, 3) select n_x, n_xy, count(*)::bigint as n_rules from covered group by n_x, n_xy, numbers"
_query("evidence_proven_five_way", _COVERED)(lambda spark, d: _proven(spark, d).select("n_x", "n_xy", "n_rules"))
_query("exclusive_rules_five_way", o.mined("five_way", 5, 500000) + " select key, n_x from rules where n_x = n_xy")(lambda spark, d: rules.exclusive_rules(_mined(spark, d, "five_way", 0.5, 5)).select("key", "n_x"))
_query("exclusive_rules_w1", o.mined("server_like", 5, 20000) + " select key, n_x from rules where n_x = n_xy")(lambda spark, d: rules.exclusive_rules(_mined(spark, d, "server_like", 0.02, 5)).select("key", "n_x"))
_query("confident_rules_w1", o.mined("server_like", 5, 100000) + " select key, round(confidence, 6) as confidence from rules where confidence >= 0.5")(lambda spark, d: rules.filter_confidence(_mined(spark, d, "server_like", 0.1, 5), 0.5).select("key", F.round("confidence", 6).alias("confidence")))
_query("explain_failures_w11", o.condensed("session", 5, 50000, 2.0, 1.05, 1.0, "simultaneous") + _BOTH)(lambda spark, d: planner.explain_failures(WORKLOADS["session"].rows(spark, d), "y", Config(min_support=0.05, min_lift=2.0)).select("key", "len", "n_xy", F.round("lift", 6).alias("lift")))


def _proven(spark, d):
    c = _compact(spark, d, "five_way")
    return rules.same_evidence(c, planner.mined_rules(c, Config(min_support=0.9, max_length=5, algorithm="patterntree")))


# --- curves ------------------------------------------------------------------------------------

_SUPPORTS, _LENGTHS = [0.02, 0.05, 0.1, 0.2, 0.4, 0.5], [2, 3, 4, 5]


def _curve_sql(name):
    grid = ", ".join(f"({s}::double, {round(s * 1e6)}, {k})" for s in _SUPPORTS for k in _LENGTHS)
    return o.mined(name, 5, 20000) + f", curve as (select s as min_support, k::integer as max_length, count(key)::bigint as n_itemsets from (values {grid}) g(s, m, k) left join rules on len <= k and n_xy::hugeint * 1000000 >= p::hugeint * m group by s, k)"


def _curve(spark, d, name):
    found = staged(_mined(spark, d, name, 0.02, 5))
    row = found.select("n_y").first()
    return planner.itemset_curve(found, row["n_y"] if row else 0, _SUPPORTS, _LENGTHS)


@_query("curve_itemsets_wide_20", o.mined("wide_20", 3, 300000) + f", curve as (select s as min_support, k::integer as max_length, count(key)::bigint as n_itemsets from (values {', '.join(f'({s}::double, {round(s * 1e6)}, {k})' for s in (0.3, 0.4, 0.5) for k in (1, 2, 3))}) g(s, m, k) left join rules on len <= k and n_xy::hugeint * 1000000 >= p::hugeint * m group by s, k) select * from curve")
def _(spark, d):
    found = staged(_mined(spark, d, "wide_20", 0.3, 3))
    return planner.itemset_curve(found, found.select("n_y").first()["n_y"], [0.3, 0.4, 0.5], [1, 2, 3])


for _q, _w in (("w1", "server_like"), ("w2", "request_like")):
    _query(f"curve_itemsets_{_q}", _curve_sql(_w) + " select * from curve")(lambda spark, d, w=_w: _curve(spark, d, w))
_query("convergence_w1", _curve_sql("server_like") + " select min(min_support) as min_support from (select min_support, max(n_itemsets) as a, min(n_itemsets) as b from curve group by 1) where b > 0 and a <= 10 * b")(lambda spark, d: planner.convergence_point(_curve(spark, d, "server_like")))


_VALUES = ", per as (" + " union all ".join(f"select {i} as col, count(distinct {c})::bigint as m from compact" for i, c in enumerate(WORKLOADS["server_like"].names)) + ")"


@_query("candidate_bounds", o.compact("server_like") + _VALUES + ", whole as (select sum(m)::bigint as m from per) select 'all' as bound, (m + m * (m - 1) // 2 + m * (m - 1) * (m - 2) // 6)::bigint as n from whole union all select 'exclusive', (m + (select sum(a.m * b.m) from per a join per b on a.col < b.col) + (select sum(a.m * b.m * c.m) from per a join per b on a.col < b.col join per c on b.col < c.col))::bigint from whole")
def _(spark, d):
    """Over the items that the table has: a number for each column comes to the driver."""
    w = WORKLOADS["server_like"]
    per = [r["m"] for r in items.item_counts(prepare.preaggregate(w.rows(spark, d), w.names)).groupBy("col").agg(F.count("*").alias("m")).collect()]
    return spark.createDataFrame([("all", planner.candidate_bound(sum(per), 3)), ("exclusive", planner.exclusive_bound(per, 3))], "bound string, n bigint")


_LIFTS = [0.5, 1.0, 2.0, 5.0, 7.0, 10.0, 50.0, 100.0]
for _q, _w, _s, _k in (("w1", "server_like", 0.1, 5), ("w1_thorough", "server_like", 0.4, 5), ("w2", "request_like", 0.1, 5), ("w2_thorough", "request_like", 0.5, 5), ("w11", "session", 0.05, 4)):
    _sql = o.mined(_w, _k, round(_s * 1e6)) + f", curve as (select t::double as min_lift, count(key)::bigint as n_rules from (values {', '.join(f'({t}::double)' for t in _LIFTS)}) g(t) left join rules on lift >= t group by t)"
    _query(f"curve_lift_{_q}", _sql + " select * from curve")(lambda spark, d, w=_w, s=_s, k=_k: monitor.lift_curve(_mined(spark, d, w, s, k), _LIFTS))
    if _q == "w1":
        _query("stable_band_w1", _sql + ", runs as (select n_rules, min(min_lift) as low, max(min_lift) as high from curve where n_rules > 0 group by n_rules) select n_rules, low, high from runs order by high - low desc, low limit 1")(lambda spark, d: monitor.stable_band(monitor.lift_curve(_mined(spark, d, "server_like", 0.1, 5), _LIFTS)))

_RARE = [1.0, 2.0, 5.0, 20.0, 50.0, 100.0, 120.0, 200.0]
_query("curve_lift_w10", o.by_label(3, 50000, "w10_rules") + f", curve as (select t::double as min_lift, count(key)::bigint as n_rules from (values {', '.join(f'({t}::double)' for t in _RARE)}) g(t) left join w10_rules on raw >= t and label = 'escalate' group by t) select * from curve")(lambda spark, d: monitor.lift_curve(staged(monitor.mine_each_label(end_state_rows(spark, d), END_STATES.names, "end_state", 0.05, 3).where("label = 'escalate'")), _RARE))

_KNOWN = "returnflag=R|linestatus=F|orderstatus=P"
_query("appears_at_w1", o.mined("server_like", 5, 100000) + f" select key, round(supp, 6) as supp, round(lift, 6) as lift, (select count(*) from rules b where b.lift > a.lift)::bigint as higher from rules a where key = '{_KNOWN}'")(lambda spark, d: monitor.appears_at(staged(_mined(spark, d, "server_like", 0.1, 5)), _KNOWN).select("key", F.round("supp", 6).alias("supp"), F.round("lift", 6).alias("lift"), "higher"))
def _retention(workload, support, **options):
    def run(spark, d):
        found = staged(rules.filter_lift(_mined(spark, d, workload, support, 5), 1.0))
        return monitor.retention(found, rules.condense(found, **options)).withColumn("retained", F.round("retained", 6))

    return run


for _q, _w, _s, _m in (("w1", "server_like", 0.1, "simultaneous"), ("w1_thorough", "server_like", 0.4, "simultaneous"), ("w2", "request_like", 0.1, "sequential"), ("w2_thorough", "request_like", 0.5, "sequential")):
    _query(f"retention_{_q}", o.condensed(_w, 5, round(_s * 1e6), 1.0, 1.05, 1.0, _m) + f", left_over as (select key from r where {_LEFT}) select (select count(*) from r)::bigint as n_before, (select count(*) from left_over)::bigint as n_after, round((select count(*) from left_over)::double / (select count(*) from r), 6) as retained")(_retention(_w, _s, mode=_m))

# --- baselines ---------------------------------------------------------------------------------

_query("naive_groupby_error_rate", o.rows("server_like") + " select returnflag, linestatus, orderstatus, count(*)::bigint as n, sum(y)::bigint as n_pos, round(avg(y), 6) as rate from base group by 1, 2, 3")(lambda spark, d: baselines.naive_groupby(WORKLOADS["server_like"].rows(spark, d), ["returnflag", "linestatus", "orderstatus"]).withColumn("rate", F.round("rate", 6)))
_query("mllib_patterns_w1", o.mined("server_like", 8, 200000) + " select list_aggregate(list_sort(itemset), 'string_agg', '|') as key, n_xy as freq from rules")(lambda spark, d: baselines.mllib_patterns(WORKLOADS["server_like"].rows(spark, d), WORKLOADS["server_like"].names, "y", 0.2).select(F.array_join(F.array_sort("items"), "|").alias("key"), "freq"))
_query("prune_by_lift_w16", o.mined("parity", 1, 1) + " select key, len, n_x, n_xy from rules where lift >= 1.3")(lambda spark, d: _sets((lambda c: baselines.prune_by_lift(c, 1, 2, 1.3))(_compact(spark, d, "parity"))))
_query("full_search_w16", o.rules("parity", 2, 1, 1.3))(lambda spark, d: _shown(rules.filter_lift(_mined(spark, d, "parity", 0.000001, 2), 1.3)))
_query("contrast_w16")(lambda spark, d: _sets(baselines.contrast_sets(_compact(spark, d, "parity"), 0.05, 0.05, 2)))
_query("contrast_w1")(lambda spark, d: _sets(baselines.contrast_sets(_compact(spark, d, "narrow"), 0.05, 0.05, 2)))
_query("cooccurrence_w1", o.cells("server_like", 2) + " select itemset[1] as a, itemset[2] as b, n_x, n_xy from cells where len(itemset) = 2")(lambda spark, d: baselines.cooccurrence(_compact(spark, d, "server_like")))
_query("prune_by_lift_w1", o.mined("narrow", 2, 1) + ", one as (select key from rules where len = 1 and lift >= 1.1) select key, len, n_x, n_xy from rules where lift >= 1.1 and (len = 1 or (itemset[1] in (from one) and itemset[2] in (from one)))")(lambda spark, d: _sets(baselines.prune_by_lift(_compact(spark, d, "narrow"), 1, 2, 1.1)))
_query("negative_rules_w1", o.mined("server_like", 3, 100000) + ", longer as (select itemset, n_x, n_xy, unnest(itemset) as z from rules where len > 1), pairs as (select a.key, z as without, a.n, a.p, a.n_x - b.n_x as n_x, a.n_xy - b.n_xy as n_xy from longer b join rules a on a.key = array_to_string(list_filter(b.itemset, lambda x: x <> z), '|')) select 'y' as label, key, without, n_x, n_xy, round((n_xy::double / n_x) * (n::double / p), 6) as lift from pairs where n_x > 0")(lambda spark, d: baselines.negative_rules(_mined(spark, d, "server_like", 0.1, 3)).withColumn("lift", F.round("lift", 6)))
_query("drop_ubiquitous_w1", o.mined("server_like", 3, 100000) + ", same as (select key from rules where len = 1 and abs(lift - 1) <= 0.02) select key from rules where not list_has_any(itemset, (select list(key) from same))")(lambda spark, d: baselines.drop_ubiquitous(staged(_mined(spark, d, "server_like", 0.1, 3))).select("key"))
_query("ubiquitous_w1", o.mined("server_like", 1, 100000) + " select key as item, round(lift, 6) as lift from rules where abs(lift - 1) <= 0.02")(lambda spark, d: baselines.ubiquitous(_mined(spark, d, "server_like", 0.1, 1)).withColumn("lift", F.round("lift", 6)))


def _model(f):
    def run(spark, d):
        c = _compact(spark, d, "server_like")
        return f(c, items.Items.of(c, least_count(0.1, items.totals(c)[1])))

    return run


_query("tree_baseline_w1")(_model(baselines.tree_baseline))
_query("forest_baseline_w1")(_model(baselines.forest_baseline))
_query("logit_baseline_w1")(_model(baselines.logit_baseline))
_query("bayes_patterns_w1")(_model(lambda c, i: baselines.bayes_baseline(c, i, planner.mined_rules(c, Config(max_length=3, algorithm="patterntree")))))

# --- monitoring, text, timings -----------------------------------------------------------------


_YEARS = o.sliced("narrow", "year", "year(o.o_orderdate)", 4, 100000)


def _years(spark, d):
    w = WORKLOADS["narrow"]
    df = w.rows(spark, d, ", year(o.o_orderdate) as year")
    return [staged(planner.mined_rules(staged(prepare.preaggregate(df.where(f"year = {y}"), w.names)), Config(algorithm="patterntree"))) for y in (1996, 1997)]


@_query("new_rules_by_year", _YEARS + " select b.key, b.n_xy, round(b.lift, 6) as lift from rules b where b.year = 1997 and not exists (from rules a where a.year = 1996 and a.key = b.key)")
def _(spark, d):
    return monitor.new_rules(*_years(spark, d)).select("key", "n_xy", F.round("lift", 6).alias("lift"))


@_query("changed_rules_by_year", _YEARS + ", a as (from rules where year = 1996), b as (from rules where year = 1997) select coalesce(a.key, b.key) as key, round(a.lift, 6) as lift_before, round(b.lift, 6) as lift_now from a full join b on a.key = b.key where a.lift is null or b.lift is null or greatest(a.lift, b.lift) >= 1.02 * least(a.lift, b.lift)")
def _(spark, d):
    return monitor.changed_rules(*_years(spark, d), factor=1.02).select("key", F.round("lift_before", 6).alias("lift_before"), F.round("lift_now", 6).alias("lift_now"))


@_query("alerts_by_year", _YEARS + " select b.key, case when a.key is null then 'new' else 'stronger' end as alert, round(b.lift, 6) as lift from (from rules where year = 1997 and lift >= 1.0) b left join (from rules where year = 1996) a on a.key = b.key where a.key is null or b.lift >= 1.02 * a.lift")
def _(spark, d):
    return monitor.alerts(*_years(spark, d), min_lift=1.0, factor=1.02).select("key", "alert", F.round("lift", 6).alias("lift"))


def _trend_sql(name, expression, micro, length, season):
    text = o.sliced(name, "period", expression, length, micro)
    return text + f" select a.period::bigint as period, a.key, a.n_xy, round(a.lift, 6) as lift, round(a.lift - b.lift, 6) as change, round(a.lift - c.lift, 6) as season_change from rules a left join rules b on b.key = a.key and b.period = a.period - 1 left join rules c on c.key = a.key and c.period = a.period - {season}"


def _trend(name, expression, support, length, season):
    def run(spark, d):
        w = WORKLOADS[name]
        found = monitor.rule_trend(w.rows(spark, d, f", {expression} as period"), w.names, "y", F.col("period"), support, length, season)
        return found.select("period", "key", "n_xy", *[F.round(c, 6).alias(c) for c in ("lift", "change", "season_change")])

    return run


_MONTH = "year(o.o_orderdate) * 12 + month(o.o_orderdate)"
_query("rule_trend_day", _trend_sql("session", "day(e.ts)", 200000, 2, 7))(_trend("session", "day(e.ts)", 0.2, 2, 7))
_query("rule_trend_month", _trend_sql("narrow", _MONTH, 300000, 2, 12))(_trend("narrow", _MONTH, 0.3, 2, 12))


@_query("rule_seasonality", _trend_sql("narrow", _MONTH, 300000, 1, 12).replace(" select a.period", ", trend as (select a.period") + ") select key, count(*)::bigint as n, round(avg(abs(change)), 6) as by_month, round(avg(abs(season_change)), 6) as by_year from trend where season_change is not null group by key")
def _(spark, d):
    """Whether a rule's lift is nearer to that of the same month a year ago than to the month before."""
    found = _trend("narrow", _MONTH, 0.3, 1, 12)(spark, d).where("season_change is not null")
    return found.groupBy("key").agg(F.count("*").alias("n"), F.round(F.avg(F.abs("change")), 6).alias("by_month"), F.round(F.avg(F.abs("season_change")), 6).alias("by_year"))


@_query("feedback_rank", o.mined("server_like", 3, 100000) + f" select key, (key = '{_KNOWN}')::integer as promoted, (row_number() over (order by key = '{_KNOWN}' desc, lift desc, supp desc, key))::integer as rank from rules where key <> 'returnflag=R'")
def _(spark, d):
    fb = spark.createDataFrame([(_KNOWN, "promote"), ("returnflag=R", "hide")], "key string, verdict string")
    return monitor.apply_feedback(_mined(spark, d, "server_like", 0.1, 3), fb).select("key", "promoted", "rank")


@_query("text_keyword_topics", "with w as (select distinct lang, doc_id, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) as word from documents), c as (select lang, word, count(*)::bigint as n from w where len(word) > 2 group by 1, 2) select lang, word, n, rank::integer as rank from (select *, row_number() over (partition by lang order by n desc, word) as rank from c) where rank <= 5")
def _(spark, d):
    return textflow.keyword_topics(load(spark, d, "documents", ["lang", "text"]), "lang", 5)


@_query("text_topic_rules")
def _(spark, d):
    docs = load(spark, d, "documents")
    topics = textflow.topics_supervised(docs, load(spark, d, "labels").select("doc_id", F.col("toxic").alias("topic")))
    own = docs.join(topics, "doc_id").select("lang", "source", F.col("topic").alias("y"))
    return planner.explain_failures(own, "y", Config(min_support=0.05)).select("key", "len", "n_xy", F.round("lift", 6).alias("lift"))


_query("text_lda_topics")(lambda spark, d: textflow.topics_unsupervised(load(spark, d, "documents", ["doc_id", "text"]), 4).groupBy("topic").agg(F.count("*").alias("n")))
_query("advise_w1")(lambda spark, d: planner.advise(_compact(spark, d, "server_like"), [0.1, 0.4], [3, 5]))
_query("thread_sweep_w1")(lambda spark, d: planner.thread_sweep(_compact(spark, d, "server_like"), Config(min_support=0.1, max_length=3), [1, 2, 4, 8, 9, 16]))
_query("time_to_cause_w1")(lambda spark, d: planner.time_to_cause(WORKLOADS["server_like"].rows(spark, d), "y", _KNOWN, Config(min_support=0.4, min_lift=5.0)))


@_query("plan_metrics_w1")
def _(spark, d):
    w = WORKLOADS["narrow"]
    found = planner.plan_metrics(prepare.preaggregate(w.rows(spark, d), w.names))
    return spark.createDataFrame(list(found.items()), "metric string, value bigint")


# --- what users of the methods need around them ----------------------------------------------------

_query("support_exclude_w2", o.compact("request_like") + _FREQUENT + " select distinct col as \"column\" from freq")(lambda spark, d: (lambda c: spark.createDataFrame([(x,) for x in prepare.support_exclude(c, least_count(0.1, items.totals(c)[1]))], "column string"))(_compact(spark, d, "request_like")))


@_query("compact_days_routed", "select event_type, hour(ts) // 6 as band, count(*)::bigint as n_all, count(*) filter (value > 150)::bigint as n_pos from events where day(ts) between 5 and 20 group by 1, 2")
def _(spark, d):
    """Recent days in the hot store, older ones in the archive, a range across both."""
    rows = load(spark, d, "events").select("event_type", F.floor(F.hour("ts") / 6).alias("band"), (F.col("value") > 150).alias("y"), F.date_format("ts", "yyyy-MM-dd").alias("day"))
    daily = prepare.preaggregate(rows, ["day", "event_type", "band"])
    hot, archive = folder(spark), folder(spark)
    daily.write.partitionBy("day").parquet(hot)
    tables.archive_days(spark, hot, archive, "2024-01-16")
    return tables.compact_days(spark, hot, archive, "2024-01-05", "2024-01-20", "2024-01-16")


_query("where_conditions", "select count(*)::bigint as n from events where event_type in ('error', 'view') and value between 5 and 50 and event_type like '%r%'")(lambda spark, d: items_sql.where(load(spark, d, "events"), "event_type in error, view", "value between 5 and 50", "event_type like %r%").agg(F.count("*").alias("n")))
_query("json_features", "select (json_extract(props, '$.k')::bigint) // 20 as band, count(*)::bigint as n from events group by 1")(lambda spark, d: load(spark, d, "events").select(F.floor(F.get_json_object("props", "$.k").cast("long") / 20).alias("band")).groupBy("band").agg(F.count("*").alias("n")))


@_query("itemset_signatures", o.mined("narrow", 3, 100000) + " select count(distinct key)::bigint as n_sets, count(distinct key)::bigint as n_signatures from rules")
def _(spark, d):
    found = _mined(spark, d, "narrow", 0.1, 3)
    return found.agg(F.count_distinct("key").alias("n_sets"), F.count_distinct(items_sql.signature(F.reverse("itemset"))).alias("n_signatures"))


@_query("subsets_lateral", o.mined("narrow", 3, 300000) + ", s as (select itemset, unnest(range(1, 1 << len)) as bits from rules) select array_to_string(list_filter(itemset, lambda x, i: (bits >> (i - 1)) & 1 = 1), '|') as subset, count(*)::bigint as n from s group by 1")
def _(spark, d):
    items_sql.register(spark)
    found = staged(_mined(spark, d, "narrow", 0.3, 3))
    return spark.sql("select array_join(subset, '|') as subset, count(*) as n from {found}, lateral subsets(itemset, 3) group by 1", found=found)


_query("mask_aggregate", "select event_type, bit_or(1::bigint << (hour(ts) // 6)::integer)::bigint as bands from events group by 1")(lambda spark, d: load(spark, d, "events").groupBy("event_type").agg(items_sql.mask_sum((F.hour("ts") / 6).cast("int")).alias("bands")))
_query("sampled_reference", "select count(*)::bigint as n_pos from events where value > 150")(lambda spark, d: tables.sampled(load(spark, d, "events").withColumn("y", (F.col("value") > 150).cast("int")), "y", 0.2).where("y = 1").agg(F.sum("weight").cast("long").alias("n_pos")))

# --- streams -----------------------------------------------------------------------------------

_TIME = "strftime({}, '%Y-%m-%d %H:%M:%S.%f')"
_LOT = "least(3, (day(ts) - 1) // 8 + case when event_id % 5 = 0 then 1 else 0 end)"
_DAILY = "with base as (select event_type, (hour(ts) // 6)::varchar as hour_band, case when value > 150 then 1 else 0 end as y, ts from events)"


def _stream_rules(where: str, tag: str) -> str:
    """Rules of at most two items over a part of the events."""
    sets = "(event_type), (hour_band), (event_type, hour_band)"
    text = f", t{tag} as (select count(*)::bigint as n, sum(y)::bigint as p from base where {where})"
    return text + f", r{tag} as (select array_to_string(list_filter([case when grouping(event_type) = 0 then 'event_type=' || event_type end, case when grouping(hour_band) = 0 then 'hour_band=' || hour_band end], lambda x: x is not null), '|') as key, count(*)::bigint as n_x, sum(y)::bigint as n_xy, (sum(y)::double / count(*)) * (any_value(n)::double / any_value(p)) as lift from base, t{tag} where {where} group by grouping sets ({sets}) having sum(y)::hugeint * 1000000 >= any_value(p)::hugeint * 100000)"


_query("stream_preagg_tumbling", "select date_trunc('day', ts)::varchar as start, event_type, count(*)::bigint as n from events group by 1, 2")(flows.tumbling)
_query("stream_preagg_sliding", f"select {_TIME.format('date_trunc(' + chr(39) + 'hour' + chr(39) + ', ts) - to_hours(k)')} as start, event_type, count(*)::bigint as n from events, range(6) g(k) group by 1, 2")(flows.sliding)
_query("stream_preagg_session", f"with g as (select user_id, ts, case when ts - lag(ts) over w < interval 30 minutes then 0 else 1 end as new from events window w as (partition by user_id order by ts)), s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from g) select user_id, {_TIME.format('min(ts)')} as start, count(*)::bigint as n from s group by user_id, k")(flows.by_session)
_query("stream_dedup", "select count(distinct event_id)::bigint as n from events")(flows.dedup)
_query("stream_late_rows", f"with e as (select event_id, ts, {_LOT} as lot from events), t as (select lot, max(ts) as top from e group by lot) select strftime(ts, '%Y-%m-%d') as day, count(*)::bigint as n, count(*) filter (ts < (select max(top) from t where t.lot < e.lot) - interval 1 hour)::bigint as n_late from e group by 1")(flows.counted_late)
_query("stream_static_enrich", "select c_mktsegment as segment, count(*)::bigint as n from events join customer on user_id = c_custkey group by 1")(flows.enriched)
_query("stream_interval_join", "select a.event_id as error_id, b.event_id as view_id from events a join events b on a.user_id = b.user_id and a.event_type = 'error' and b.event_type = 'view' and b.ts <= a.ts and b.ts >= a.ts - interval 1 hour")(flows.before_errors)
_query("stream_running_weights", "with g as (select event_type, ts, value, case when ts - lag(ts) over w > interval 20 minutes then 1 else 0 end as new from events window w as (partition by event_type order by ts)), s as (select *, sum(new) over (partition by event_type order by ts rows unbounded preceding) as k from g) select event_type, count(*)::bigint as n_all, count(*) filter (value > 150)::bigint as n_pos from s a where k = (select max(k) from s b where a.event_type = b.event_type) group by 1")(flows.stateful)
_query("stream_rules_final", _DAILY + _stream_rules("true", "0") + " select key, n_x, n_xy, round(lift, 6) as lift from r0")(flows.final_rules)
_query("stream_alerts", _DAILY + _stream_rules("ts < timestamp '2024-01-16'", "1") + _stream_rules("ts >= timestamp '2024-01-16'", "2") + " select r2.key, case when r1.key is null then 'new' else 'stronger' end as alert, r2.n_xy, round(r2.lift, 6) as lift from r2 left join r1 on r1.key = r2.key where r2.lift >= 1.0 and (r1.key is null or r2.lift >= 1.05 * r1.lift)")(flows.final_alerts)
