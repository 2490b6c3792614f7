"""DuckDB SQL of the registered queries, written from the definitions."""

from __future__ import annotations

import math


def hex8(share: float) -> str:
    return f"{math.ceil(share * 2**32):08x}"


INS, DEL, M, SALT = hex8(0.1), hex8(0.98), hex8(0.1), "s1"
MONEY = "cast(l_extendedprice as decimal(12,2))"
REV = "(cast(l_extendedprice as decimal(12,2)) * (1 - cast(l_discount as decimal(4,2))))"

LINE = """line as (select *, row_number() over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice,
 l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) as l_seq from lineitem)"""
SPLIT = LINE + """, split as (select *, substr(md5('d0|' || l_orderkey || '|' || l_seq), 1, 8) as dh from line)"""
ORDER_SPLIT = LINE + """, split as (select l.*, o.* exclude (o_orderkey), substr(md5('d0|' || l_orderkey), 1, 8) as dh from line l join orders o on l_orderkey = o_orderkey)"""


def sampled(key: str, m: str = M, salt: str = SALT) -> str:
    return f"substr(md5('{salt}|' || {key}), 1, 8) < '{m}'"


def demand(with_samples: bool = True) -> str:
    """CTEs stale, fresh, stale_s, fresh_s of demand per part."""
    agg = f"select l_partkey, count(*) as n, sum({MONEY}) as v from split where {{}} group by l_partkey"
    out = f"with {SPLIT}, stale as ({agg.format(f"dh >= '{INS}'")}), fresh as ({agg.format(f"dh < '{DEL}'")})"
    if with_samples:
        out += f", stale_s as (select * from stale where {sampled('l_partkey')}), fresh_s as (select * from fresh where {sampled('l_partkey')})"
    return out


def plain(q) -> str:
    """SQL aggregate of an AggQuery (DuckDB)."""
    hit = f"filter (where {q.cond})"
    return {
        "sum": f"coalesce(cast(sum({q.attr}) {hit} as double), 0)",
        "count": f"cast(count(*) {hit} as double)",
        "avg": f"cast(sum({q.attr}) {hit} as double) / cast(count({q.attr}) {hit} as double)",
        "median": f"quantile_cont(cast({q.attr} as double), 0.5) {hit}",
        "percentile": f"quantile_cont(cast({q.attr} as double), {q.p}) {hit}",
        "ratio": f"cast(sum({q.attr}) {hit} as double) / cast(sum({q.over}) {hit} as double)",
        "var": f"var_samp(cast({q.attr} as double)) {hit}",
        "stddev": f"stddev_samp(cast({q.attr} as double)) {hit}",
    }[q.agg]


def four_answers(ctes: str, q, digits: int = 4) -> str:
    scale = 10.0 if q.agg in ("sum", "count") else 1.0
    a = plain(q)
    return f"""{ctes}, a as (select (select {a} from fresh) as truth, (select {a} from stale) as stale, (select {a} from fresh_s) * {scale} as direct, (select {a} from stale_s) * {scale} as was_s)
select round(truth, {digits}) as truth, round(stale, {digits}) as stale, round(direct, {digits}) as direct, round(stale + direct - was_s, {digits}) as correction from a"""


def contributions_sql(q, m: float = 0.1) -> str:
    amount = "1.0" if q.agg == "count" else f"cast({q.attr} as double)"
    return f"case when {q.cond} then {amount} / {m} else 0.0 end"


METHODS = ("stale", "direct", "correction")
#: CTE ``e`` over ``a`` (truth and the methods), and the select that follows it: one row a method and group of ``by``.
ERRORS = "e as (select *, " + ", ".join(f"abs({m} - truth) / nullif(abs(truth), 0) as err_{m}" for m in METHODS) + " from a)"
SUMMARY = " union all ".join(
    f"select {{by}}, '{m}' as method, round(quantile_cont(err_{m}, 0.5), 5) as median, round(quantile_cont(err_{m}, 0.75), 5) as q75, round(max(err_{m}), 5) as worst, round(avg(err_{m}), 5) as mean, count(err_{m}) as n,"
    f" round(quantile_cont(err_stale, 0.5) / nullif(quantile_cont(err_{m}, 0.5), 0), 5) as gain from e group by {{by}}"
    for m in METHODS
)
FRAMES = {"t": "true", "s": "is_old", "d": "in_sample", "c": "is_old and in_sample"}


def sums_by_frame(by: str, values: tuple[str, ...] = ("x", "y")) -> str:
    """Select list of sums and counts a frame, of rows with the flags ``is_old`` and ``in_sample``."""
    return f"select {by}, " + ", ".join(f"sum({v}) filter (where {cond}) as {v}_{t}, count({v}) filter (where {cond}) as n{v}_{t}" for t, cond in FRAMES.items() for v in values) + f" from r group by {by}"


def estimates(by: str, agg: str = "kind", scale: float = 10.0) -> str:
    """Select of truth and the three methods from ``sums_by_frame``; ``agg`` is a column with sum, ratio or avg."""

    def value(t: str) -> str:
        k = scale if t in "dc" else 1.0
        return f"case {agg} when 'sum' then coalesce(cast(x_{t} as double), 0) * {k} when 'avg' then cast(x_{t} as double) / nullif(nx_{t}, 0) else cast(x_{t} as double) / nullif(cast(y_{t} as double), 0) end"

    return f"""select {by}, t as truth, s as stale, d as direct, case when coalesce(s, d) is not null then coalesce(s, 0) + coalesce(d, 0) - coalesce(c, 0) end as correction
 from (select {by}, {", ".join(f"{value(t)} as {t}" for t in FRAMES)} from g)"""
