"""The experiment workloads: which tables are joined, which features they have, and the planted
failure. The same text serves Spark and any SQL engine, so results can be held against it."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from .tables import load


@dataclass(frozen=True)
class Workload:
    name: str
    tables: tuple[tuple[str, str, str], ...]  # table, alias, join condition
    features: tuple[tuple[str, str], ...]  # name, expression
    label: str
    where: str = "true"

    @property
    def names(self) -> list[str]:
        return [n for n, _ in self.features]

    def sql(self, extra: str = "", engine: str = "duckdb") -> str:
        """The labelled rows as a SELECT. extra: more select items."""
        (first, alias, _), *rest = self.tables
        joins = " ".join(f"join {t} {a} on {on}" for t, a, on in rest)
        own = ", ".join(f"cast({e} as varchar) as {n}" for n, e in self.features)
        text = f"select {own}, case when {self.label} then 1 else 0 end as y{extra} from {first} {alias} {joins} where {self.where}"
        return text if engine == "duckdb" else text.replace("as varchar", "as string").replace(" // ", " div ").replace("isodow(e.ts)", "(weekday(e.ts) + 1)")

    def rows(self, spark: SparkSession, folder: str, extra: str = "") -> DataFrame:
        """The labelled rows. Dimensions are joined as their sizes suggest; a dimension that fits
        under the session's threshold is broadcast."""
        names = {t for t, _, _ in self.tables}
        text = self.sql(extra, "spark")
        views = {t: f"{{{t}}}" for t in names}
        for t in names:
            text = text.replace(f"from {t} ", f"from {views[t]} ").replace(f"join {t} ", f"join {views[t]} ")
        return spark.sql(text, **{t: load(spark, folder, t) for t in names})


_STAR = (
    ("lineitem", "l", ""),
    ("orders", "o", "l.l_orderkey = o.o_orderkey"),
    ("customer", "c", "o.o_custkey = c.c_custkey"),
    ("nation", "n", "c.c_nationkey = n.n_nationkey"),
    ("region", "r", "n.n_regionkey = r.r_regionkey"),
    ("part", "p", "l.l_partkey = p.p_partkey"),
)
_SUPPLIER = (("supplier", "s", "l.l_suppkey = s.s_suppkey"), ("nation", "sn", "s.s_nationkey = sn.n_nationkey"), ("region", "sr", "sn.n_regionkey = sr.r_regionkey"))
_LINE = (("returnflag", "l.l_returnflag"), ("linestatus", "l.l_linestatus"), ("orderstatus", "o.o_orderstatus"), ("priority", "o.o_orderpriority"), ("segment", "c.c_mktsegment"), ("region", "r.r_name"))
_TYPE, _BRAND = ("type", "p.p_type"), ("brand", "p.p_brand")
_H, _G = "(l.l_orderkey * 31 + l.l_linenumber * 17)", "(l.l_orderkey * 7 + l.l_linenumber * 3)"
_REQUEST = (*_LINE, _BRAND, _TYPE)
_EVENTS = (("events", "e", ""), ("customer", "c", "e.user_id = c.c_custkey"), ("nation", "n", "c.c_nationkey = n.n_nationkey"), ("region", "r", "n.n_regionkey = r.r_regionkey"))
_EVENT = (("event_type", "e.event_type"), ("segment", "c.c_mktsegment"), ("region", "r.r_name"), ("hour_band", "hour(e.ts) // 6"))
_FIVE = "l.l_returnflag = 'R' and l.l_linestatus = 'F' and o.o_orderstatus = 'P' and o.o_orderpriority = '1-URGENT' and c.c_mktsegment = 'BUILDING'"
_W1 = f"(l.l_returnflag = 'R' and l.l_linestatus = 'F' and o.o_orderstatus = 'P' and {_H} % 10 < 8) or {_G} % 17 = 0"



def _attributes(count: int, configurations: int, least: int, values: int) -> tuple[tuple[str, str], ...]:
    """Features of a fleet in which an entity has one of so many configurations: each has a common
    value, which a share of the configurations has (from least / 97 on, in steps), and rarer ones."""
    own = f"(l.l_partkey % {configurations})"
    return tuple((f"a{k:02d}", f"case when ({own} * {31 + 2 * k}) % 97 < {least + (k * 7) % 30} then 'usual' else 'v' || cast(({own} * {k + 1}) % {values} as varchar) end") for k in range(count))


WORKLOADS = {
    w.name: w
    for w in (
        Workload("server_like", _STAR + _SUPPLIER, (*_LINE, _TYPE, ("supp_region", "sr.r_name")), _W1),
        Workload("narrow", _STAR[:2], _LINE[:4], _W1),
        Workload("mid", _STAR, (*_LINE, _TYPE), _W1),
        Workload("request_like", _STAR, _REQUEST, f"(p.p_brand = 'Brand#13' and r.r_name = 'ASIA' and {_H} % 10 < 5) or {_G} % 997 = 0"),
        Workload("latency", _EVENTS, (*_EVENT, ("weekday", "isodow(e.ts)")), "e.value > 150"),
        Workload("session", _EVENTS, _EVENT, "(e.event_type = 'error' and c.c_mktsegment = 'BUILDING' and r.r_name = 'ASIA' and e.event_id % 10 < 8) or e.event_id % 23 = 0"),
        Workload("text", (("documents", "d", ""),), (("lang", "d.lang"), ("source", "d.source"), ("length_band", "case when d.n_chars < 500 then 'a' when d.n_chars < 2000 then 'b' when d.n_chars < 8000 then 'c' else 'd' end")), "(d.source = 'src3' and d.lang = 'en' and d.doc_id % 10 < 9) or d.doc_id % 37 = 0"),
        Workload("parity", _STAR, (_LINE[1], _LINE[2], _LINE[0], _LINE[4]), "(l.l_linestatus = 'F') <> (o.o_orderstatus = 'P')", "o.o_orderstatus in ('P', 'O')"),
        # As wide as the published data: 20 features of some 1,500 values, and 50 features of some 500.
        Workload("wide_20", _STAR[:2], (*_LINE[:3], *_attributes(17, 291, 48, 101)), _W1),
        Workload("wide_50", _STAR[:5], (_LINE[0], _LINE[5], *_attributes(48, 291, 22, 10)), f"(l.l_returnflag = 'R' and r.r_name = 'ASIA' and {_H} % 20 < 1) or {_G} % 997 = 0"),
        Workload("events_shape", _EVENTS[:1], (_EVENT[0], _EVENT[3], ("weekday", "isodow(e.ts)"), ("band", "case when e.value > 50 then 'high' else 'low' end")), "e.value > 150"),
        Workload("wide_9", _STAR, (*_LINE, _TYPE, _BRAND, ("nation", "n.n_name"), ("discount", "cast(round(l.l_discount * 100) as integer)")), _W1),
        Workload("five_way", _STAR, _REQUEST, f"({_FIVE}) or {_G} % 100003 = 0"),
        Workload("five_way_noisy", _STAR, _REQUEST, f"({_FIVE}) or {_G} % 499 = 0"),
        # Each item of the cause raises lift, but less than twofold, and all its parts hold in every failure.
        Workload("short_steps", _STAR[:2], (("discount_band", "case when l.l_discount < 0.065 then 'low' else 'high' end"), ("urgent", "case when o.o_orderpriority = '1-URGENT' then 'yes' else 'no' end"), ("partial", "case when o.o_orderstatus = 'P' then 'yes' else 'no' end")), "l.l_discount < 0.065 and o.o_orderpriority <> '1-URGENT' and o.o_orderstatus <> 'P'"),
    )
}
#: Many end states of one process: the label column has several values.
END_STATE = (
    f"case when p.p_brand = 'Brand#7' and o.o_orderpriority = '1-URGENT' and {_H} % 10 < 6 then 'escalate' "
    f"when (c.c_mktsegment = 'MACHINERY' and l.l_returnflag = 'A' and {_H} % 10 < 1) or {_G} % 41 = 0 then 'exception' "
    f"when {_G} % 43 = 0 then 'retry' when {_G} % 47 = 0 then 'repair' else 'done' end"
)
END_STATES = Workload("end_states", _STAR, _REQUEST, "false")


def end_state_rows(spark: SparkSession, folder: str) -> DataFrame:
    return END_STATES.rows(spark, folder, f", {END_STATE} as end_state").drop("y")
