"""SQL for other engines that says what the queries return: grouping sets give every cell, and
rules, filters and curves are written out over the cells."""

from __future__ import annotations

from itertools import combinations

from .sources.workloads import END_STATE, END_STATES, WORKLOADS, Workload

RULE = "key, len, n_x, n_xy, round(supp_all, 6) as supp_all, round(supp, 6) as supp, round(confidence, 6) as confidence, round(lift, 6) as lift, round(conviction, 6) as conviction, round(chi2, 6) as chi2"


def rows(name: str) -> str:
    return f"with base as ({WORKLOADS[name].sql()})"


def compact(name: str) -> str:
    dims = ", ".join(WORKLOADS[name].names)
    return rows(name) + f", compact as (select {dims}, count(*)::bigint as n_all, sum(y)::bigint as n_pos from base group by {dims}), tot as (select sum(n_all)::bigint as n, sum(n_pos)::bigint as p from compact)"


def _cells(w: Workload, length: int, source: str = "compact", extra: str = "") -> str:
    names = [n for n in w.names if n != extra]
    sets = ", ".join("(" + ", ".join([*([extra] if extra else []), *s]) + ")" for k in range(1, min(length, len(names)) + 1) for s in combinations(names, k))
    part = ", ".join(f"case when grouping({c}) = 0 then '{c}=' || {c} end" for c in names)
    own = f"{extra}, " if extra else ""
    return f"select {own}list_filter([{part}], lambda x: x is not null) as itemset, sum(n_all)::bigint as n_x, sum(n_pos)::bigint as n_xy from {source} group by grouping sets ({sets})"


def cells(name: str, length: int) -> str:
    return compact(name) + f", cells as ({_cells(WORKLOADS[name], length)})"


def _measures(source: str) -> str:
    return f"""select itemset, array_to_string(itemset, '|') as key, len(itemset)::integer as len, n, p, n_x, n_xy,
    n_x::double / n as supp_all, n_xy::double / p as supp, n_xy::double / n_x as confidence, (n_xy::double / n_x) * (n::double / p) as lift,
    case when n_xy < n_x then (1 - p::double / n) / (1 - n_xy::double / n_x) end as conviction,
    n::double * power(n_xy::double * (n - n_x - p + n_xy) - (n_x - n_xy)::double * (p - n_xy), 2) / nullif(n_x::double * (n - n_x) * p * (n - p), 0) as chi2
    from {source}"""


def mined(name: str, length: int, micro: int) -> str:
    return cells(name, length) + f", rules as materialized ({_measures(f'(select * from cells, tot where n_xy >= 1 and n_xy::hugeint * 1000000 >= p::hugeint * {micro})')})"


def pairs(name: str, length: int, micro: int, min_lift: float) -> str:
    text = mined(name, length, micro) + f", r as materialized (select * from rules where lift >= {min_lift})"
    # The parts of a rule, by the bits of a number, meet the shorter rules by their key.
    text += ", parts as (select key as long_key, lift as long_lift, n_xy as long_n, array_to_string(list_filter(itemset, lambda x, i: (bits >> (i - 1)) & 1 = 1), '|') as key from (select *, unnest(range(1, (1 << len) - 1)) as bits from r where len > 1))"
    return text + ", pairs as materialized (select long_key, b.key as short_key, long_lift, b.lift as short_lift, long_n, b.n_xy as short_n from parts join r b on b.key = parts.key)"


def filters(h_supp: float, h_lift_long: float, h_lift_short: float, mode: str, f1: str = "f1", f2: str = "f2") -> str:
    """What each of the two filters drops, as tables f1 and f2."""
    text = f", {f1} as materialized (select distinct long_key as key from pairs where short_lift * {h_lift_long} >= long_lift)"
    seen = f"(select * from pairs anti join {f1} on long_key = {f1}.key anti join {f1} g on short_key = g.key)" if mode == "sequential" else "pairs"
    return text + f", {f2} as materialized (select distinct short_key as key from {seen} where long_n * {h_supp}::double >= short_n and long_lift > short_lift * {h_lift_short})"


def condensed(name: str, length: int, micro: int, min_lift: float, h_supp: float, h_lift: float, mode: str) -> str:
    return pairs(name, length, micro, min_lift) + filters(h_supp, h_lift, h_lift, mode)


def condensed_counts(name: str, length: int, micro: int, min_lift: float, cases: dict[str, tuple[float, float, float, str]], column: str) -> str:
    """How many rules each case of (h_supp, h_lift_long, h_lift_short, mode) leaves."""
    text = pairs(name, length, micro, min_lift) + "".join(filters(*case, f"f1_{i}", f"f2_{i}") for i, case in enumerate(cases.values()))
    left = "(select count(*) from r where not exists (from f1_{0} f where f.key = r.key) and not exists (from f2_{0} f where f.key = r.key))::bigint"
    return text + " " + " union all ".join(f"select '{c}' as {column}, {left.format(i)} as n_rules" for i, c in enumerate(cases))


def sliced(name: str, by: str, expression: str, length: int, micro: int) -> str:
    """Rules inside each value of `by`, which is a feature or an expression over the tables."""
    w = WORKLOADS[name]
    extra = "" if by in w.names else f", {expression} as {by}"
    dims = ", ".join([n for n in w.names if n != by] + [by])
    text = f"with base as ({w.sql(extra)}), compact as (select {dims}, count(*)::bigint as n_all, sum(y)::bigint as n_pos from base group by {dims}), tot as (select {by}, sum(n_all)::bigint as n, sum(n_pos)::bigint as p from compact group by {by})"
    text += f", cells as ({_cells(w, length, extra=by)})"
    return text + f", rules as materialized (select cells.{by}, array_to_string(itemset, '|') as key, len(itemset)::integer as len, n_x, n_xy, n_xy::double / p as supp, (n_xy::double / n_x) * (n::double / p) as lift from cells join tot on cells.{by} = tot.{by} where n_xy >= 1 and n_xy::hugeint * 1000000 >= p::hugeint * {micro})"


def rules(name: str, length: int, micro: int, min_lift: float = 0.0) -> str:
    return mined(name, length, micro) + f" select {RULE} from rules where lift >= {min_lift}"


def sets(name: str, length: int, micro: int) -> str:
    return mined(name, length, micro) + " select key, len, n_x, n_xy from rules"


def by_label(length: int, micro: int, only: str = "") -> str:
    w, dims = END_STATES, ", ".join(END_STATES.names)
    text = f"with base as ({w.sql(f', {END_STATE} as end_state')}), compact as (select {dims}, end_state, count(*)::bigint as n_all, count(*)::bigint as n_pos from base group by {dims}, end_state)"
    text += f", per as ({_cells(w, length, extra='end_state')}), whole as ({_cells(w, length)}), tot as (select end_state, sum(n_all)::bigint as p from compact group by end_state)"
    text += f", found as (select per.end_state as label, per.itemset, whole.n_x, per.n_xy, tot.p, (select sum(n_all)::bigint from compact) as n from per join whole on per.itemset = whole.itemset join tot on per.end_state = tot.end_state where per.n_xy::hugeint * 1000000 >= tot.p::hugeint * {micro})"
    if only:
        return text + f", {only} as (select label, array_to_string(itemset, '|') as key, (n_xy::double / n_x) * (n::double / p) as raw from found)"
    return text + " select label, array_to_string(itemset, '|') as key, len(itemset)::integer as len, n_x, n_xy, round((n_xy::double / n_x) * (n::double / p), 6) as lift from found"
