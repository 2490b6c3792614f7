"""Queries of the engine and their DuckDB SQL, by the ids of the survey's inventory."""

from __future__ import annotations

import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles as O
from .functions import hashing as H
from .functions import table_functions
from .operators import bootstrap, cleaning, estimate, intervals, joins, maintenance, metrics, outliers, skew, staleness
from .operators.estimate import AggQuery
from .plans import keys, pushdown
from .plans.nodes import Aggregate, Difference, Distinct, Intersect, Join, KeyHash, Project, Scan, Select, Union, Windowed
from .sources import tables as T
from .workloads import base, complex_views, cube, demand, join_view, log_views, minibatch, outlier_sweep, timing

M, KEY = base.RATIO, ("l_partkey",)
_queries: dict = {}
_sql: dict = {}


def _add(name: str, sql: str | None = None):
    def keep(f):
        _queries[name] = f
        if sql:
            _sql[name] = sql
        return f

    return keep


def _rounded(df: DataFrame, digits: int = 4) -> DataFrame:
    return df.select(*[F.round(F.col(c).cast("double"), digits).alias(c) if t.startswith(("double", "decimal")) else F.col(c) for c, t in df.dtypes])


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Total demand: truth, stale answer, direct estimate, correction."""
    return _four("sum")(spark, sf_dir)


def _demand(spark: SparkSession, sf_dir: str, **options) -> base.State:
    return demand.build(spark, sf_dir, **options)


def _visible(df: DataFrame, *columns: str) -> DataFrame:
    return df.select(*[F.col(c).cast("bigint") if c == "n" else F.col(c).cast("double") if c == "v" else F.col(c) for c in columns])


# --- keys, provenance, staleness -------------------------------------------------
_add("k1_sequence_key", f"with {O.LINE} select l_orderkey, cast(l_seq as int) as l_seq, l_partkey from line")(lambda s, d: T.lines(s, d).select("l_orderkey", "l_seq", "l_partkey"))


@_add("k8_audit_key", f"with {O.LINE}, c as (select count(*) as n from line group by l_orderkey, l_seq) select cast(sum(n) as bigint) as n_rows, count(*) as n_keys, cast(sum(case when n > 1 then 1 else 0 end) as bigint) as n_repeated from c")
def _k8(spark, d):
    return keys.audit_key(T.lines(spark, d), T.KEYS["lineitem"])


def _audited(name: str, key: str, table: str) -> str:
    columns = key.replace(",", ", ")
    return f"select '{name}' as node, '{key}' as key, cast(coalesce(sum(n), 0) as bigint) as n_rows, count(*) as n_keys from (select {columns}, count(*) as n from {table} group by {columns})"


_FEW = "(select p_partkey, p_brand as brand from part where p_size > 10)"
_SALE, _COUNTED = "(select * from line join orders on l_orderkey = o_orderkey)", "(select o_custkey, count(*) as n from line join orders on l_orderkey = o_orderkey group by 1)"
_NODE_KEYS = (
    ("leaf", "l_orderkey,l_seq", "line"), ("selection", "l_orderkey,l_seq", "(select * from line where l_quantity > 1)"), ("projection", "p_partkey", _FEW), ("join", "l_orderkey,l_seq,o_orderkey", _SALE), ("aggregation", "o_custkey", _COUNTED),
    ("distinct", "p_partkey,brand", f"(select distinct * from {_FEW})"), ("union", "p_partkey", f"(select * from {_FEW} union select * from {_FEW})"), ("intersection", "p_partkey", f"(select * from {_FEW} intersect select * from {_FEW})"),
    ("difference", "p_partkey", f"(select * from {_FEW} except select * from {_FEW})"), ("repaired", "o_custkey", _COUNTED), ("reduced_join", "l_orderkey,l_seq", _SALE),
)


@_add("k2_key_rules", f"with {O.LINE} " + " union all ".join(_audited(*x) for x in _NODE_KEYS))
def _key_rules(spark, d):
    """The inferred key of one node of each kind, and what the node's rows say of it: as many keys as rows."""
    line, order, part = (Scan(t, T.lines(spark, d) if t == "lineitem" else T.load(spark, d, t), T.KEYS[t]) for t in ("lineitem", "orders", "part"))
    joined = Join(line, order, (("l_orderkey", "o_orderkey"),), "inner", "left")
    few = Project(Select(part, "p_size > 10"), (("p_partkey", "p_partkey"), ("brand", "p_brand")))
    counts = Aggregate(joined, ("o_custkey",), (("n", "count(1)"),))
    nodes = {"leaf": line, "selection": Select(line, "l_quantity > 1"), "projection": few, "join": joined, "aggregation": counts, "distinct": Distinct(few), "union": Union(few, few), "intersection": Intersect(few, few), "difference": Difference(few, few), "repaired": keys.repair_key(Project(counts, (("n", "n"),)))}
    inferred = [(name, node, keys.infer_key(node)) for name, node in nodes.items()] + [("reduced_join", joined, keys.infer_key(joined, reduce_fk=True))]
    out = None
    for name, node, key in inferred:
        part_ = keys.audit_key(node.lower(), key).select(F.lit(name).alias("node"), F.lit(",".join(key)).alias("key"), "n_rows", "n_keys")
        out = part_ if out is None else out.unionByName(part_)
    return out


@_add("k9_lineage", f"with {O.SPLIT} select l_orderkey, cast(l_seq as int) as l_seq from split where l_partkey in (3, 17) and dh < '{O.DEL}'")
def _k9(spark, d):
    c = demand.changes(spark, d)
    plan = demand.VIEW.plan({"lineitem": c.new("lineitem"), "part": c.old["part"]}, T.KEYS)
    wanted = spark.sql("SELECT * FROM VALUES (3L), (17L) AS t(l_partkey)")
    return keys.lineage(plan, wanted, "lineitem").select("l_orderkey", "l_seq")


_CLASSES = O.demand(False) + """, c as (select case when s.l_partkey is null then 'missing' when f.l_partkey is null then 'superfluous' when s.n = f.n and s.v = f.v then 'unchanged' else 'incorrect' end as class
 from stale s full outer join fresh f on s.l_partkey = f.l_partkey) select class, count(*) as n, round(count(*) / sum(count(*)) over (), 6) as share from c group by class"""


@_add("k11_staleness_profile", _CLASSES)
def _k11(spark, d):
    s = _demand(spark, d)
    return _rounded(staleness.staleness_profile(s.stale, s.fresh, KEY), 6)


@_add("k11_staleness_orders", f"""with {O.ORDER_SPLIT}, s as (select l_orderkey, count(*) as n from split where dh >= '{O.INS}' group by 1), f as (select l_orderkey, count(*) as n from split where dh < '{O.hex8(0.95)}' group by 1),
 c as (select case when s.l_orderkey is null then 'missing' when f.l_orderkey is null then 'superfluous' when s.n = f.n then 'unchanged' else 'incorrect' end as class from s full outer join f on s.l_orderkey = f.l_orderkey) select class, count(*) as n from c group by class""")
def _k11b(spark, d):
    c = base.order_changes(spark, d, 0.1, 0.05)
    lines = lambda t: t.groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"))
    whole = lambda li, o: lines(join_view.view_rows(li, o))
    return staleness.staleness_profile(whole(c.old["lineitem"], c.old["orders"]), whole(c.new("lineitem"), c.new("orders")), ("l_orderkey",)).select("class", "n")


@_add("k12_is_stale", f"with {O.SPLIT} select count(*) filter (where dh < '{O.INS}' or dh >= '{O.DEL}') > 0 as changed, count(*) filter (where dh < '00000000') > 0 as unchanged from split")
def _k12(spark, d):
    return spark.createDataFrame([(demand.changes(spark, d).is_stale(), demand.changes(spark, d, 0.0, 0.0).is_stale())], "changed boolean, unchanged boolean")


# --- key-hash filter and push-down -----------------------------------------------
for _m in (0.05, 0.1, 0.25):
    _add(f"h1_key_hash_orders_{int(_m * 100)}", f"select o_orderkey, o_custkey from orders where {O.sampled('o_orderkey', O.hex8(_m))}")(lambda s, d, m=_m: H.key_hash_filter(T.load(s, d, "orders"), "o_orderkey", m).select("o_orderkey", "o_custkey"))
_add("h1_key_hash_lines", f"with {O.LINE} select l_orderkey, cast(l_seq as int) as l_seq from line where {O.sampled("l_orderkey || '|' || l_seq")}")(lambda s, d: H.key_hash_filter(T.lines(s, d), ["l_orderkey", "l_seq"], M).select("l_orderkey", "l_seq"))
_add("h2_sha256_orders", "select o_orderkey from orders where substr(sha256('s1|' || o_orderkey), 1, 8) < '1999999a'")(lambda s, d: H.key_hash_filter(T.load(s, d, "orders"), "o_orderkey", M, family="sha2_256").select("o_orderkey"))


@_add("h2_hash_families")
def _h2(spark, d):
    """Realised ratio of each family."""
    orders = T.load(spark, d, "orders")
    return orders.agg(*[F.avg(H.in_sample(orders, ["o_orderkey"], M, family=f).cast("double")).alias(f) for f in H.FAMILIES])


@_add("h3_hash_uniformity", "with h as (select cast(floor(cast('0x' || substr(md5('s1|' || o_orderkey), 1, 8) as bigint) * 16 / 4294967296) as int) as bucket from orders), c as (select bucket, count(*) as n from h group by 1) select bucket, n, (select count(*) from orders) / 16.0 as expected, round((n - (select count(*) from orders) / 16.0) * (n - (select count(*) from orders) / 16.0) / ((select count(*) from orders) / 16.0), 6) as chi2 from c")
def _h3(spark, d):
    return _rounded(H.hash_uniformity(T.load(spark, d, "orders"), ["o_orderkey"]), 6)


_add("h4_text_key", "select n_name, n_nationkey from nation where substr(md5('s1|' || n_name || '|' || n_nationkey), 1, 8) < '80000000'")(lambda s, d: H.key_hash_filter(T.load(s, d, "nation"), ["n_name", "n_nationkey"], 0.5).select("n_name", "n_nationkey"))
_add("h5_refine", f"select o_orderkey from orders where {O.sampled('o_orderkey', O.hex8(0.25))} and not {O.sampled('o_orderkey', O.hex8(0.1))}")(lambda s, d: H.refine(T.load(s, d, "orders"), ["o_orderkey"], 0.1, 0.25).select("o_orderkey"))


def _pushed(name: str, make, key, columns: tuple[str, ...], sql: str) -> None:
    """The sample through the rewritten plan."""
    _add(name, sql)(lambda s, d: pushdown.push(KeyHash(make(s, d), key, M))[0].lower().select(*columns))


def _scan(spark, d, t: str) -> Scan:
    return Scan(t, T.lines(spark, d) if t == "lineitem" else T.load(spark, d, t), T.KEYS[t])


def _cust(spark, d, where: str) -> Project:
    return Project(Select(_scan(spark, d, "orders"), where), (("o_custkey", "o_custkey"),))


_IN = O.sampled("o_custkey")
_pushed("p1_selection", lambda s, d: Select(_scan(s, d, "orders"), "o_totalprice > 100000"), ("o_orderkey",), ("o_orderkey",), f"select o_orderkey from orders where o_totalprice > 100000 and {O.sampled('o_orderkey')}")
_pushed("p2_projection", lambda s, d: Project(_scan(s, d, "orders"), (("id", "o_orderkey"), ("twice", "o_custkey * 2"))), ("id",), ("id", "twice"), f"select o_orderkey as id, o_custkey * 2 as twice from orders where {O.sampled('o_orderkey')}")
_pushed("p3_aggregation", lambda s, d: Aggregate(_scan(s, d, "orders"), ("o_custkey",), (("n", "count(1)"),)), ("o_custkey",), ("o_custkey", "n"), f"select o_custkey, count(*) as n from orders where {_IN} group by 1")
_pushed("p4_union", lambda s, d: Union(_cust(s, d, "o_orderstatus = 'F'"), _cust(s, d, "o_orderstatus = 'O'")), ("o_custkey",), ("o_custkey",), f"select distinct o_custkey from orders where o_orderstatus in ('F', 'O') and {_IN}")
_pushed("p5_intersection", lambda s, d: Intersect(_cust(s, d, "o_orderstatus = 'F'"), _cust(s, d, "o_orderstatus = 'O'")), ("o_custkey",), ("o_custkey",), f"select o_custkey from orders where o_orderstatus = 'F' and {_IN} intersect select o_custkey from orders where o_orderstatus = 'O'")
_pushed("p6_difference", lambda s, d: Difference(_cust(s, d, "o_orderstatus = 'F'"), _cust(s, d, "o_orderstatus = 'O'")), ("o_custkey",), ("o_custkey",), f"select o_custkey from orders where o_orderstatus = 'F' and {_IN} except select o_custkey from orders where o_orderstatus = 'O'")
_pushed("p7_join_blocked", lambda s, d: Join(Select(_scan(s, d, "part"), "p_partkey < 40"), Select(_scan(s, d, "supplier"), "s_suppkey < 10")), ("p_partkey", "s_suppkey"), ("p_partkey", "s_suppkey"), f"select p_partkey, s_suppkey from part, supplier where p_partkey < 40 and s_suppkey < 10 and {O.sampled("p_partkey || '|' || s_suppkey")}")
_pushed("p8_join_one_side", lambda s, d: Join(_scan(s, d, "orders"), _scan(s, d, "customer"), (("o_custkey", "c_custkey"),)), ("o_orderkey",), ("o_orderkey", "c_nationkey"), f"select o_orderkey, c_nationkey from orders join customer on o_custkey = c_custkey where {O.sampled('o_orderkey')}")
_pushed("p9_join_foreign_key", lambda s, d: Join(_scan(s, d, "lineitem"), _scan(s, d, "orders"), (("l_orderkey", "o_orderkey"),), "inner", "left"), ("l_orderkey", "l_seq", "o_orderkey"), ("l_orderkey", "o_custkey"), f"with {O.LINE} select l_orderkey, o_custkey from line join orders on l_orderkey = o_orderkey where {O.sampled("l_orderkey || '|' || l_seq || '|' || o_orderkey")}")
_pushed("p10_join_equality", lambda s, d: Join(_scan(s, d, "lineitem"), _scan(s, d, "orders"), (("l_orderkey", "o_orderkey"),), "left"), ("l_orderkey",), ("l_orderkey", "o_custkey"), f"select l_orderkey, o_custkey from lineitem left join orders on l_orderkey = o_orderkey where {O.sampled('l_orderkey')}")


def _full_join(s, d):
    side = lambda where, n: Project(Aggregate(Select(_scan(s, d, "orders"), where), ("o_custkey",), ((n, "count(1)"),)), (("o_custkey", "o_custkey"), (n, n)))
    return Join(side("o_orderstatus = 'F'", "n_f"), side("o_orderstatus = 'P'", "n_p"), (("o_custkey", "o_custkey"),), "full")


_pushed("p10_full_outer_join", _full_join, ("o_custkey",), ("o_custkey", "n_f", "n_p"), f"with f as (select o_custkey, count(*) as n_f from orders where o_orderstatus = 'F' group by 1), p as (select o_custkey, count(*) as n_p from orders where o_orderstatus = 'P' group by 1) select * from f full join p using (o_custkey) where {_IN}")
_pushed("p11_semi_join", lambda s, d: Join(_scan(s, d, "customer"), _scan(s, d, "orders"), (("c_custkey", "o_custkey"),), "left_semi"), ("c_custkey",), ("c_custkey",), f"select c_custkey from customer where c_custkey in (select o_custkey from orders) and {O.sampled('c_custkey')}")
_pushed("p11_anti_join", lambda s, d: Join(_scan(s, d, "customer"), Select(_scan(s, d, "orders"), "o_orderdate >= '1998-01-01'"), (("c_custkey", "o_custkey"),), "left_anti"), ("c_custkey",), ("c_custkey",), f"select c_custkey from customer where c_custkey not in (select o_custkey from orders where o_orderdate >= '1998-01-01') and {O.sampled('c_custkey')}")
_pushed("p12_window", lambda s, d: Windowed(_scan(s, d, "orders"), ("o_custkey",), (("place", "row_number() over (partition by o_custkey order by o_orderdate, o_orderkey)"),)), ("o_custkey",), ("o_orderkey", "place"), f"select o_orderkey, cast(row_number() over (partition by o_custkey order by o_orderdate, o_orderkey) as int) as place from orders where {_IN}")
_add("p14_pushdown_report")(demand.pushdown_report)


# --- refresh ---------------------------------------------------------------------
_FRESH = O.demand(False) + " select l_partkey, n, cast(v as double) as v from fresh"
for _name in ("recompute", "change_table", "signed_union"):
    _id = {"recompute": "r1", "change_table": "r2", "signed_union": "r3"}[_name]
    _add(f"{_id}_{_name}_refresh", _FRESH)(lambda s, d, n=_name: _visible(maintenance.refresh(demand.PLAIN, (st := _demand(s, d)).stale, st.changes, n), "l_partkey", "n", "v"))
    _add(f"r9_refresh_sample_{_name}", O.demand() + " select l_partkey, n, cast(v as double) as v from fresh_s")(lambda s, d, n=_name: _visible(_demand(s, d, strategy=n).fresh_s, "l_partkey", "n", "v"))


@_add("r4_updates_refresh", f"""with {O.SPLIT}, new as (select l_partkey, {O.MONEY} as v, dh from split union all select l_partkey, cast({O.MONEY} * 1.1 as decimal(12,2)), 'u' from split where dh >= '80000000' and dh < '8ccccccd')
 select l_partkey, count(*) as n, cast(sum(v) as double) as v from new where dh = 'u' or (dh < '80000000' or dh >= '8ccccccd') group by 1""")
def _r4(spark, d):
    c = base.line_changes(spark, d, 0.0, 0.0, updated=True)
    return _visible(maintenance.refresh(demand.PLAIN, maintenance.stale_plan(demand.PLAIN, c).lower(), c), "l_partkey", "n", "v")


_CUST = base.View("customer_lines", ("o_custkey",), (("n", "1"), ("v", demand.PRICE)), lambda leaf: Join(leaf["lineitem"], leaf["orders"], (("l_orderkey", "o_orderkey"),), "inner", "left"), ("lineitem", "orders"))


@_add("r5_join_delta_refresh", f"with {O.ORDER_SPLIT} select o_custkey, count(*) as n, cast(sum({O.MONEY}) as double) as v from split where dh < '{O.hex8(0.95)}' group by 1")
def _r5(spark, d):
    c = base.order_changes(spark, d, 0.1, 0.05)
    return _visible(maintenance.refresh(_CUST, maintenance.stale_plan(_CUST, c).lower(), c), "o_custkey", "n", "v")


@_add("r5_join_delta_sample", f"with {O.ORDER_SPLIT} select o_custkey, count(*) as n, cast(sum({O.MONEY}) as double) as v from split where dh < '{O.hex8(0.95)}' and {O.sampled('o_custkey')} group by 1")
def _r5s(spark, d):
    c = base.order_changes(spark, d, 0.1, 0.05)
    return _visible(maintenance.refresh_sample(_CUST, maintenance.stale_plan(_CUST, c).lower(), c, M), "o_custkey", "n", "v")


_add("r6_join_view_refresh", f"with {O.ORDER_SPLIT} select l_orderkey, cast(l_seq as int) as l_seq, o_custkey from split where dh < '{O.hex8(0.95)}'")(lambda s, d: join_view.frames(s, d, deleted=0.05)["fresh"].select("l_orderkey", "l_seq", "o_custkey"))
_add("r6_join_view_sample", f"with {O.ORDER_SPLIT} select l_orderkey, cast(l_seq as int) as l_seq, o_custkey from split where dh < '{O.hex8(0.95)}' and {O.sampled("l_orderkey || '|' || l_seq")}")(lambda s, d: join_view.frames(s, d, deleted=0.05)["fresh_s"].select("l_orderkey", "l_seq", "o_custkey"))


@_add("r7_touched_groups", f"with {O.SPLIT} select l_partkey, max(l_extendedprice) as dearest, cast(count(distinct l_suppkey) as bigint) as suppliers from split where dh < '{O.DEL}' group by 1")
def _r7(spark, d):
    c = demand.changes(spark, d)
    aggs = (("dearest", "max(l_extendedprice)"), ("suppliers", "count(distinct l_suppkey)"))
    stale = Aggregate(Scan("lineitem", c.old["lineitem"], T.KEYS["lineitem"]), KEY, aggs).lower()
    return maintenance.touched_group_refresh(KEY, aggs, stale, c.new("lineitem"), c.delta("lineitem")).lower()


@_add("r11_correspondence", O.demand() + """ select 'uniform' as clause, cast((select count(*) from fresh_s) as double) as observed, round((select count(*) from fresh) * 0.1, 4) as expected, cast(0 as bigint) as violations
 union all select 'superfluous', 0.0, 0.0, (select count(*) from fresh_s where l_partkey not in (select l_partkey from fresh))
 union all select 'missing', cast((select count(*) from fresh_s where l_partkey not in (select l_partkey from stale)) as double), round((select count(*) from fresh where l_partkey not in (select l_partkey from stale)) * 0.1, 4), 0
 union all select 'preserved', cast((select count(*) from stale_s where l_partkey in (select l_partkey from fresh_s)) as double), cast((select count(*) from stale_s where l_partkey in (select l_partkey from fresh)) as double), (select count(*) from stale_s where l_partkey in (select l_partkey from fresh) and l_partkey not in (select l_partkey from fresh_s))""")
def _r11(spark, d):
    s = _demand(spark, d)
    return _rounded(cleaning.check_correspondence(s.stale, s.fresh, s.stale_s, s.fresh_s, KEY, M))


# --- estimators and intervals ------------------------------------------------------
def _four(name: str):
    def run(spark, d):
        s = _demand(spark, d)
        return _rounded(estimate.answers(s.stale, s.fresh, s.stale_s, s.fresh_s, demand.QUERIES[name], M))

    return run


for _name, _q in demand.QUERIES.items():
    _add(f"e_{_name}_all_answers", O.four_answers(O.demand(), _q))(_four(_name))


@_add("e7_drift_sum", O.demand() + " select round(cast((select sum(v) from fresh_s) - (select sum(v) from stale_s) as double) * 10, 2) as drift")
def _e7(spark, d):
    s = _demand(spark, d)
    return _rounded(estimate.drift_estimate(s.stale_s, s.fresh_s, demand.QUERIES["sum"], M), 2)


@_add("e8_grouped_correction", f"""with {O.SPLIT}, b as (select l_partkey, p_brand, dh, {O.MONEY} as v from split join part on l_partkey = p_partkey),
 stale as (select p_brand, sum(v) as v from b where dh >= '{O.INS}' group by 1), f as (select p_brand, sum(v) as v from b where dh < '{O.DEL}' and {O.sampled('l_partkey')} group by 1), s as (select p_brand, sum(v) as v from b where dh >= '{O.INS}' and {O.sampled('l_partkey')} group by 1)
 select p_brand, round(cast(stale.v as double) + (coalesce(cast(f.v as double), 0) * 10 - coalesce(cast(s.v as double), 0) * 10), 2) as estimate from stale left join f using (p_brand) left join s using (p_brand)""")
def _e8(spark, d):
    s = _demand(spark, d, plain=False)
    return _rounded(estimate.correction_estimate(s.stale, s.stale_s, s.fresh_s, AggQuery("sum", "v", "true", ("p_brand",)), M), 2)


_PAIRS = O.demand() + ", p as (select coalesce(f.l_partkey, s.l_partkey) as l_partkey, coalesce(cast(f.v as double) / 0.1, 0) as f, coalesce(cast(s.v as double) / 0.1, 0) as s from fresh_s f full join stale_s s on f.l_partkey = s.l_partkey)"


@_add("e9_choose_estimator", _PAIRS + " select case when sum(s * s) <= 2 * sum(s * f) then 'correction' else 'direct' end as choice from p")
def _e9(spark, d):
    s = _demand(spark, d)
    return estimate.choose_estimator(s.stale_s, s.fresh_s, demand.QUERIES["sum"], M, KEY).select("choice")


@_add("e12_variance_report", _PAIRS + " select round(var_samp(f) / 1e10, 3) as var_fresh, round(var_samp(s) / 1e10, 3) as var_stale, round(covar_samp(f, s) / 1e10, 3) as cov, round(var_samp(f - s) / 1e10, 3) as var_diff, count(*) as k from p")
def _e12(spark, d):
    s = _demand(spark, d)
    r = estimate.variance_report(s.stale_s, s.fresh_s, demand.QUERIES["sum"], M, KEY)
    return r.select(*[F.round(F.col(c) / 1e10, 3).alias(c) for c in ("var_fresh", "var_stale", "cov", "var_diff")], "k")


@_add("e13_effective_sample", O.demand() + " select count(*) as k, round(avg(case when n > 32 then 1 else 0 end), 6) as selectivity, cast(sum(case when n > 32 then 1 else 0 end) as bigint) as k_eff, sum(case when n > 32 then 1 else 0 end) >= 30 as safe from fresh_s")
def _e13(spark, d):
    return _rounded(estimate.effective_sample_size(_demand(spark, d).fresh_s, demand.QUERIES["count_busy"]), 6)


@_add("e14_extreme", O.demand() + " select round(cast((select max(v) from stale) as double) + greatest(0, (select max(cast(f.v - s.v as double)) from fresh_s f join stale_s s using (l_partkey))), 2) as estimate")
def _e14(spark, d):
    s = _demand(spark, d)
    return _rounded(estimate.extreme_estimate(s.stale, s.stale_s, s.fresh_s, AggQuery("max", "v"), KEY).select("estimate"), 2)


@_add("e15_lookup", f"with {O.SPLIT} select l_partkey, count(*) as n from split where dh < '{O.DEL}' and l_partkey = 7 group by 1")
def _e15(spark, d):
    return estimate.lookup_exact(demand.changes(spark, d).new("lineitem"), {"l_partkey": 7}, [F.count(F.lit(1)).alias("n")], KEY)


_Y = "cast(v as double) / 0.1"
_WIDTHS = {"printed": f"1.96 * stddev_samp({_Y}) / sqrt(count(*))", "clt": f"1.96 * stddev_samp({_Y}) * sqrt(count(*))", "ht": f"1.96 * sqrt(0.9 * sum(({_Y}) * ({_Y})))"}
for _v, _w in _WIDTHS.items():
    _id = {"printed": "i1", "clt": "i6", "ht": "i7"}[_v]
    _add(f"{_id}_direct_interval_{_v}", O.demand() + f" select round(cast(sum(v) as double) * 10, 1) as estimate, round({_w}, 1) as half_width, count(*) as k from fresh_s")(lambda s, d, v=_v: _rounded(intervals.direct_interval(_demand(s, d).fresh_s, demand.QUERIES["sum"], M, KEY, variance=v).select("estimate", "half_width", "k"), 1))


@_add("i5_correction_interval", _PAIRS + " select round((select cast(sum(v) as double) from stale) + sum(f) - sum(s), 1) as estimate, round(1.96 * sqrt(0.9 * sum((f - s) * (f - s))), 1) as half_width, count(*) as k from p")
def _i5(spark, d):
    s = _demand(spark, d)
    return _rounded(intervals.correction_interval(s.stale, s.stale_s, s.fresh_s, demand.QUERIES["sum"], M, KEY).select("estimate", "half_width", "k"), 1)


@_add("i8_cluster_interval", f"with {O.ORDER_SPLIT}, y as (select l_orderkey, sum({O.MONEY}) as v from split where {O.sampled('l_orderkey')} group by 1) select round(cast(sum(v) as double) * 10, 1) as estimate, round(1.96 * sqrt(0.9 * sum(cast(v as double) / 0.1 * cast(v as double) / 0.1)), 1) as half_width, count(*) as k from y")
def _i8(spark, d):
    f = join_view.frames(spark, d, sample_on="prefix")
    return _rounded(intervals.direct_interval(f["fresh_s"], AggQuery("sum", demand.PRICE), M, join_view.KEY, cluster_by=("l_orderkey",)).select("estimate", "half_width", "k"), 1)


@_add("i9_linearised_average", O.demand() + " select round(avg(cast(v as double)), 2) as estimate, round(1.96 * sqrt(0.9 * (select sum((cast(v as double) - (select avg(cast(v as double)) from fresh_s)) * (cast(v as double) - (select avg(cast(v as double)) from fresh_s))) from fresh_s)) / count(*), 2) as half_width from fresh_s")
def _i9(spark, d):
    return _rounded(intervals.direct_interval(_demand(spark, d).fresh_s, demand.QUERIES["avg"], M, KEY).select("estimate", "half_width"), 2)


_LADDER = " + ".join(f"cast(h >= '{b}' as int)" for b in bootstrap.poisson_ladder())


def _boot(side: str, seed: str = "b1", n: int = 40) -> str:
    return f"(select b, v, w from (select b, v, {_LADDER} as w from (select b, v, substr(md5('{seed}|' || b || '|' || l_partkey), 1, 8) as h from {side}, range(1, {n + 1}) t(b))) where w > 0)"


@_add("i10_bootstrap_direct", O.demand() + f", r as (select b, cast(sum(v * w) as double) * 10 as x from {_boot('fresh_s')} group by b) select round(quantile_cont(x, 0.025), 0) as low, round(quantile_cont(x, 0.975), 0) as high, count(*) as replicates from r")
def _i10(spark, d):
    return _rounded(bootstrap.bootstrap_direct(_demand(spark, d).fresh_s, demand.QUERIES["sum"], M, KEY, 40).select("low", "high", "replicates"), 0)


@_add("i11_bootstrap_correction", O.demand() + f", f as (select b, cast(sum(v * w) as double) * 10 as x from {_boot('fresh_s')} group by b), s as (select b, cast(sum(v * w) as double) * 10 as x from {_boot('stale_s')} group by b), c as (select f.x - s.x as x from f join s using (b)) select round((select cast(sum(v) as double) from stale) + quantile_cont(x, 0.025), 0) as low, round((select cast(sum(v) as double) from stale) + quantile_cont(x, 0.975), 0) as high, count(*) as replicates from c")
def _i11(spark, d):
    s = _demand(spark, d)
    return _rounded(bootstrap.bootstrap_correction(s.stale, s.stale_s, s.fresh_s, demand.QUERIES["sum"], M, KEY, 40).select("low", "high", "replicates"), 0)


def _medians(side: str, seed: str = "b1") -> str:
    return f"(select b, quantile_cont(cast(v as double), 0.5) as x from {_boot(side, seed, bootstrap.REPLICATES)}, unnest(range(w)) group by b)"


def _median_drift(form: str, fresh_seed: str, stale_seed: str) -> str:
    return f"""select round(was + f - s, 4) as estimate, round(was + quantile_cont(d, 0.025), 4) as low, round(was + quantile_cont(d, 0.975), 4) as high, count(d) as replicates, '{form}' as form
 from (select f.x - s.x as d from {_medians('fresh_s', fresh_seed)} f join {_medians('stale_s', stale_seed)} s using (b)), (select (select median(cast(v as double)) from stale) as was, (select median(cast(v as double)) from fresh_s) as f, (select median(cast(v as double)) from stale_s) as s) group by was, f, s"""


@_add("s41_bootstrap_udaf", O.demand() + f" select b, round(x, 4) as v from {_medians('fresh_s')}")
def _s41(spark, d):
    return _rounded(bootstrap.direct_replicates_udaf(_demand(spark, d).fresh_s, demand.QUERIES["median"], KEY).select(F.col("b").cast("bigint"), "v"))


@_add("i11_bootstrap_median", O.demand() + " " + _median_drift("paired", "b1", "b1") + " union all " + _median_drift("unpaired", "b1f", "b1s"))
def _i11m(spark, d):
    s = _demand(spark, d)
    q = demand.QUERIES["median"]
    paired = bootstrap.bootstrap_correction(s.stale, s.stale_s, s.fresh_s, q, M, KEY).withColumn("form", F.lit("paired"))
    return _rounded(paired.unionByName(bootstrap.bootstrap_correction(s.stale, s.stale_s, s.fresh_s, q, M, KEY, paired=False).withColumn("form", F.lit("unpaired"))))


@_add("i13_coverage", O.demand(False) + f""", p as (select coalesce(f.l_partkey, s.l_partkey) as k, coalesce(cast(f.v as double), 0) as f, coalesce(cast(s.v as double), 0) as s from fresh f full join stale s on f.l_partkey = s.l_partkey),
 t as (select sum(f) as truth, sum(s) as was from p), salts as (select 'c' || i as salt from range(20) r(i)), x as (select salt, f, f - s as d from p, salts where substr(md5(salt || '|' || k), 1, 8) < '{O.M}')
 select salt, abs(sum(f) / 0.1 - (select truth from t)) <= 1.96 * sqrt(0.9 * sum(f * f)) / 0.1 as direct_covers, abs((select was from t) + sum(d) / 0.1 - (select truth from t)) <= 1.96 * sqrt(0.9 * sum(d * d)) / 0.1 as correction_covers from x group by salt""")
def _i13(spark, d):
    s = _demand(spark, d)
    return intervals.coverage_trial(s.stale, s.fresh, demand.QUERIES["sum"], M, KEY, [f"c{i}" for i in range(20)]).select("salt", "direct_covers", "correction_covers")


# --- outlier sets --------------------------------------------------------------------
_add("o1_outlier_index", f"with {O.LINE} select l_orderkey, cast(l_seq as int) as l_seq, l_extendedprice from line where l_extendedprice > 104000 order by l_extendedprice desc, l_orderkey, l_seq limit 100")(lambda s, d: outliers.build_outlier_index(T.lines(s, d), "l_extendedprice", T.KEYS["lineitem"], 104000).select("l_orderkey", "l_seq", "l_extendedprice"))
_add("o2_both_tails", "(select event_id from events where value > 150 order by value desc, event_id limit 50) union (select event_id from events where value < 1 order by value, event_id limit 50)")(lambda s, d: outliers.build_outlier_index(T.load(s, d, "events"), "value", ("event_id",), (1, 150), 50, "both").select("event_id"))
_add("o3_threshold_topk", "select min(l_extendedprice) as threshold from (select l_extendedprice from lineitem order by 1 desc limit 100)")(lambda s, d: outliers.threshold_topk(T.load(s, d, "lineitem"), "l_extendedprice"))
_add("o4_threshold_sigma", "select round(avg(value) + 3 * stddev_pop(value), 6) as threshold from events")(lambda s, d: _rounded(outliers.threshold_sigma(T.load(s, d, "events"), "value"), 6))


@_add("o6_update_index", "with n as (select * from events where substr(md5('d0|' || event_id), 1, 8) < '80000000' and substr(md5('d0|' || event_id), 1, 8) >= '0ccccccd') select event_id from n where value > 150 order by value desc, event_id limit 50")
def _o6(spark, d):
    e = T.load(spark, d, "events")
    part = lambda low, high: base.change_share(e, ("event_id",), low, high)
    index = outliers.build_outlier_index(part(0.0, 0.3), "value", ("event_id",), 150, 1000)
    return outliers.update_outlier_index(index, part(0.3, 0.5), part(0.0, 0.05), "value", ("event_id",), 150, 50).select("event_id")


_Z = f"""with {O.LINE}, z as (select *, round(l_extendedprice * power((cast('0x' || substr(md5('z|' || l_orderkey || '|' || l_seq), 1, 8) as bigint) + 1) / 4294967296.0, -0.75), 2) as price_z, substr(md5('d0|' || l_orderkey || '|' || l_seq), 1, 8) as dh from line),
 fresh as (select l_orderkey, sum(cast(price_z as decimal(24,2))) as rev from z group by 1), stale as (select l_orderkey, sum(cast(price_z as decimal(24,2))) as rev from z where dh >= '{O.INS}' group by 1),
 o as (select * from fresh where l_orderkey in (select l_orderkey from (select l_orderkey from z order by price_z desc, l_orderkey, l_seq limit 100))),
 f as (select * from fresh where {O.sampled('l_orderkey')} and l_orderkey not in (select l_orderkey from o)), s as (select * from stale where {O.sampled('l_orderkey')} and l_orderkey not in (select l_orderkey from o))"""


@_add("o13_direct_with_outliers", _Z + " select round(cast((select sum(rev) from f) as double) * 10 + cast((select sum(rev) from o) as double), 1) as estimate")
def _o13(spark, d):
    s = outlier_sweep.build(spark, d, 4)
    return _rounded(outliers.direct_with_outliers(s.fresh_s, outlier_sweep.outlier_rows(s, 100), AggQuery("sum", "rev"), M, s.view.keys), 1)


@_add("o14_correction_with_outliers", _Z + " select round(cast((select sum(rev) from stale) as double) + (cast((select sum(rev) from f) as double) - cast((select sum(rev) from s) as double)) * 10 + cast((select sum(rev) from o) as double) - cast((select sum(rev) from stale where l_orderkey in (select l_orderkey from o)) as double), 1) as estimate")
def _o14(spark, d):
    s = outlier_sweep.build(spark, d, 4)
    return _rounded(outliers.correction_with_outliers(s.stale, s.stale_s, s.fresh_s, outlier_sweep.outlier_rows(s, 100), AggQuery("sum", "rev"), M, s.view.keys), 1)


@_add(
    "o16_interval_with_outliers",
    _Z
    + """, d as (select l_orderkey, coalesce(cast(f.rev as double), 0) / 0.1 - coalesce(cast(s.rev as double), 0) / 0.1 as y from f full join s using (l_orderkey)),
 e as (select cast((select sum(rev) from stale) as double) + (cast((select sum(rev) from f) as double) - cast((select sum(rev) from s) as double)) * 10 + cast((select sum(rev) from o) as double) - cast((select sum(rev) from stale where l_orderkey in (select l_orderkey from o)) as double) as estimate,
 (select 1.96 * sqrt(0.9 * sum(y * y)) from d) as half_width)
 select round(estimate, 1) as estimate, round(half_width, 1) as half_width, round(estimate - half_width, 1) as low, round(estimate + half_width, 1) as high from e""",
)
def _o16(spark, d):
    s = outlier_sweep.build(spark, d, 4)
    return _rounded(outliers.interval_with_outliers(s.stale, s.stale_s, s.fresh_s, outlier_sweep.outlier_rows(s, 100), AggQuery("sum", "rev"), M, s.view.keys), 1)


_SWEEP = (O.LINE, lambda key, salt: f"substr(md5({salt} || '|' || {key}), 1, 8) < '{O.M}'")
_add("o17_size_sweep", outlier_sweep.errors_sql(*_SWEEP, ("v3",), (4,), (0, 10, 100, 1000), "cap", O.INS))(outlier_sweep.size_sweep)
_add("w3_outlier_z_sweep", outlier_sweep.errors_sql(*_SWEEP, outlier_sweep.VIEWS, (1, 2, 3, 4), (100,), "view, z", O.INS))(outlier_sweep.z_sweep)
_add("w3_outlier_times")(outlier_sweep.size_times)


# --- baselines and measures ------------------------------------------------------------
@_add("b4_refresh_then_sample", O.demand() + " select l_partkey, n, cast(v as double) as v from fresh_s")
def _b4(spark, d):
    s = _demand(spark, d)
    return _visible(cleaning.refresh_then_sample(demand.PLAIN, s.stale, s.changes, M), "l_partkey", "n", "v")


@_add("b5_naive_row_sample", f"""with {O.SPLIT}, stale as (select l_partkey, count(*) as n from split where dh >= '{O.INS}' group by 1), d as (select l_partkey, case when dh < '{O.INS}' then 1 else -1 end as w from split where (dh < '{O.INS}' or dh >= '{O.DEL}') and {O.sampled("l_orderkey || '|' || l_seq", O.M, 'r1')}),
 u as (select l_partkey, n from stale where {O.sampled('l_partkey')} union all select l_partkey, w from d) select l_partkey, cast(sum(n) as bigint) as n from u group by 1 having sum(n) > 0""")
def _b5(spark, d):
    s = _demand(spark, d)
    return cleaning.naive_row_sample_refresh(demand.PLAIN, s.stale_s, s.changes, M).select("l_partkey", F.col("n").cast("bigint"))


_add("k10_sample_base_first", f"with {O.LINE} select l_partkey, count(*) as n from line where {O.sampled("l_orderkey || '|' || l_seq")} group by 1")(lambda s, d: cleaning.sample_base_then_view(T.lines(s, d), T.KEYS["lineitem"], KEY, M))
_add("b7_rowwise_clean", O.demand() + " select l_partkey, n from fresh where l_partkey in (select l_partkey from stale_s)")(lambda s, d: _visible(cleaning.rowwise_clean_only((st := _demand(s, d)).stale_s, st.fresh, KEY), "l_partkey", "n"))


@_add("a14_work_report", O.demand() + f", k as (select * from split where {O.sampled('l_partkey')}) select 'scan stale demand_plain' as leaf, (select count(*) from stale) as rows, (select count(*) from stale_s) as kept union all select 'scan changes lineitem', (select count(*) from split where dh < '{O.INS}' or dh >= '{O.DEL}'), (select count(*) from k where dh < '{O.INS}' or dh >= '{O.DEL}')")
def _a14(spark, d):
    s = _demand(spark, d)
    return metrics.work_report(maintenance.refresh_plan(demand.PLAIN, s.stale, s.changes), M, KEY)


# --- workloads ----------------------------------------------------------------------------
_WIDE = f""", w as (select split.*, c_mktsegment, cn.n_name as c_nation, cr.r_name as c_region, sn.n_name as s_nation, p_brand, p_type, p_size, p_retailprice, p_name, strftime(o_orderdate, '%Y-%m') as o_month, cast(year(o_orderdate) as int) as o_year, cast(year(l_shipdate) as int) as l_year, sum(cast(l_quantity as decimal(12,2))) over (partition by l_orderkey) as order_qty
 from split join customer on o_custkey = c_custkey join nation cn on c_nationkey = cn.n_nationkey join region cr on cn.n_regionkey = cr.r_regionkey join supplier on l_suppkey = s_suppkey join nation sn on s_nationkey = sn.n_nationkey join part on l_partkey = p_partkey)"""


def _join_rows(names: tuple[str, ...], n: int, old: str = f"dh >= '{O.INS}'", more: str = "") -> str:
    """CTEs up to ``g``: sums by draw, template and group; ``more`` is a further table (size) that ``old`` may use."""
    values = ", ".join(str(tuple(d)) for d in join_view.draws(0, n))
    names_of = ", ".join(c.split()[0] for c in join_view.DRAW.split(", "))
    columns = {c: c for c in names_of.split(", ")}
    parts = []
    for name in names:
        q = join_view.query(name, columns)
        key = " || '|' || ".join(f"cast({c} as varchar)" for c in q.group_by) or "''"
        sample = O.sampled("l_orderkey" if name == "j18" else "l_orderkey || '|' || l_seq")
        attr = "1" if q.agg == "count" else q.attr
        over = f"cast({q.over} as decimal(30,6))" if q.agg == "ratio" else "cast(null as decimal(30,6))"
        kind = "ratio" if q.agg == "ratio" else "sum"
        parts.append(f"select {'size, ' if more else ''}draw, '{name}' as query_id, '{kind}' as kind, {key} as group_key, {old} as is_old, {sample} as in_sample, cast({attr} as decimal(30,6)) as x, {over} as y from w, draws{', ' + more if more else ''} where {q.cond.replace('interval 90 days', 'interval 90 day')}")
    by = ("size, " if more else "") + "draw, query_id, kind, group_key"
    return f"with {O.ORDER_SPLIT}{_WIDE}, draws({names_of}) as (values {values}), r as ({' union all '.join(parts)}), g as ({O.sums_by_frame(by)}), a as ({O.estimates(by)})"


for _name in join_view.TEMPLATES:
    _add(f"w1_{_name}", _join_rows((_name,), 1) + " select group_key, " + ", ".join(f"round({c}, 5) as {c}" for c in ("truth", *O.METHODS)) + " from a")(
        lambda s, d, n=_name: _rounded(join_view.run(s, d, names=(n,)).select("group_key", "truth", "stale", "direct", "correction"), 5)
    )
_add("w1_accuracy", _join_rows(tuple(join_view.TEMPLATES), 20) + f", {O.ERRORS} " + O.SUMMARY.format(by="query_id"))(lambda s, d: _rounded(join_view.accuracy(s, d), 5))
_SIZES_SQL = ", ".join(f"({x}, '{O.hex8(x)}')" for x in (0.025, 0.05, 0.1, 0.2, 0.3, 0.4, 0.5))
_add(
    "w1_break_even_sweep",
    _join_rows(("j10",), 1, "dh >= bound", f"(values {_SIZES_SQL}) as z(size, bound)") + f", {O.ERRORS} select cast(size as double) as size, " + ", ".join(f"round(quantile_cont(err_{m}, 0.5), 5) as {m}" for m in O.METHODS) + " from e group by size",
)(lambda s, d: _rounded(join_view.delta_sweep(s, d), 5))
_add("w4_cube_sample", f"with {O.ORDER_SPLIT} select o_custkey, c_nationkey, n_regionkey, p_brand, count(*) as n, round(cast(sum({O.REV}) as double), 4) as rev from split join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join part on l_partkey = p_partkey where {O.sampled("o_custkey || '|' || c_nationkey || '|' || n_regionkey || '|' || p_brand")} group by 1, 2, 3, 4")(
    lambda s, d: _rounded(cube.build(s, d).fresh_s.select(*cube.DIMENSIONS, F.col("n").cast("bigint").alias("n"), "rev"), 4)
)


def _rollup_sql(agg: str) -> str:
    """Errors of all proper roll-ups of the base cube."""
    dims = cube.DIMENSIONS
    cells = f"select {', '.join(dims)}, sum({O.REV}) as rev from split join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join part on l_partkey = p_partkey where {{}} group by all"
    key = O.sampled(" || '|' || ".join(dims))
    value = "cast(sum(rev) {f} as double)" if agg == "sum" else "quantile_cont(cast(rev as double), 0.5) {f}"
    picks = ", ".join(f"{value.format(f=f"filter (where frame = '{t}')")} {f'* {10.0}' if agg == 'sum' and t in 'dc' else ''} as {t}" for t in O.FRAMES)
    sets = ", ".join(f"({', '.join(x)})" for x in cube.rollup_sets())
    name = "concat_ws(',', " + ", ".join(f"case when grouping({c}) = 0 then '{c}' end" for c in dims) + ")"
    return f"""with {O.ORDER_SPLIT}, fresh as ({cells.format("true")}), old as ({cells.format(f"dh >= '{O.INS}'")}),
 r as (select 't' as frame, * from fresh union all select 's', * from old union all select 'd', * from fresh where {key} union all select 'c', * from old where {key}),
 g as (select {name} as query_id, {picks} from r group by grouping sets ({sets})),
 a as (select query_id, t as truth, s as stale, d as direct, case when coalesce(s, d) is not null then coalesce(s, 0) + coalesce(d, 0) - coalesce(c, 0) end as correction from g), {O.ERRORS} {O.SUMMARY.format(by="query_id")}"""


for _agg in ("sum", "median"):
    _add(f"w4_rollup_errors_{_agg}", _rollup_sql(_agg))(lambda s, d, a=_agg: _rounded(cube.rollup_errors(cube.build(s, d), a), 5))
_add("w4_exact_cube", f"with {O.ORDER_SPLIT} select o_custkey, c_nationkey, n_regionkey, p_brand, round(cast(sum({O.REV}) as double), 4) as rev, count(*) as n, cast(grouping_id(o_custkey, c_nationkey, n_regionkey, p_brand) as bigint) as gid from split join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join part on l_partkey = p_partkey group by cube (o_custkey, c_nationkey, n_regionkey, p_brand)")(
    lambda s, d: _rounded(cube.exact_cube(cube.build(s, d)).withColumn("n", F.col("n").cast("bigint")), 4)
)
_LOG = {"l1": ("user_id", "user_id"), "l2": ("user_id || '|' || event_type", "user_id, event_type"), "l3": ("user_id || '|' || cast(day as varchar)", "user_id, day"), "l5": ("event_type || '|' || hour_text", "event_type, hour_text"), "l7": ("k || '|' || cast(day as varchar)", "k, day")}
for _name, (_text, _by) in _LOG.items():
    _add(
        f"w5_{_name}_fresh_sample",
        f"with e as (select *, cast(ts as date) as day, strftime(ts, '%Y-%m-%d %H') as hour_text, json_extract_string(props, '$.k') as k from events) select {_by}, count(*) as n, round(cast(sum(cast(value as decimal(18,4))) as double), 4) as total from e where {O.sampled(_text)} group by {_by}",
    )(lambda s, d, n=_name: _rounded(log_views.build(s, d, n).fresh_s.select(*log_views.VIEWS[n].keys, F.col("n").cast("bigint").alias("n"), "total"), 4))
_EVENTS = """bounds as (select epoch_us(min(ts)) as first, epoch_us(max(ts)) as last from events),
 n0 as (select *, coalesce(ts - lag(ts) over w > interval 12 hour, true) as opens from events window w as (partition by user_id order by ts, event_id)),
 n1 as (select *, sum(cast(opens as int)) over (partition by user_id order by ts, event_id rows unbounded preceding) as nth from n0),
 ev as (select n1.*, cast(ts as date) as day, strftime(ts, '%Y-%m-%d %H') as hour_text, json_extract_string(props, '$.k') as k, cast(min(ts) over (partition by user_id, nth) as date) as session_day,
 epoch_us(ts) < first + round((last - first) * 0.8) as is_old from n1, bounds)"""


def _log_accuracy_sql() -> str:
    """Every view before and after, and its random queries."""
    ctes, parts = [], []
    for name, view in log_views.VIEWS.items():
        second = "cast(sum(cast(event_type = 'error' as int)) as decimal(30,6)) as errors" if name == "l4" else "cast(sum(cast(value as decimal(18,4))) as decimal(30,6)) as total"
        for tag, where in (("t", "true"), ("s", "is_old")):
            ctes.append(f"{name}_{tag} as (select {', '.join(view.keys)}, count(*) as n, {second} from ev where {where} group by {', '.join(view.keys)})")
        key = " || '|' || ".join(f"cast({c} as varchar)" for c in view.keys)
        for query_id, q in log_views.queries(name):
            kind, x = ("avg" if q.agg == "avg" else "sum"), ("1" if q.agg == "count" else q.attr)
            for tag, frame, where in (("t", "t", "true"), ("s", "s", "true"), ("d", "t", O.sampled(key)), ("c", "s", O.sampled(key))):
                parts.append(f"select '{name}' as view, '{query_id}' as query_id, '{kind}' as kind, '{tag}' as frame, cast({x} as decimal(30,6)) as x from {name}_{frame} where ({q.cond}) and {where}")
    sums = ", ".join(f"sum(x) filter (where frame = '{t}') as x_{t}, count(x) filter (where frame = '{t}') as nx_{t}, cast(null as double) as y_{t}" for t in O.FRAMES)
    return f"with {_EVENTS}, {', '.join(ctes)}, r as ({' union all '.join(parts)}), g as (select view, query_id, kind, {sums} from r group by 1, 2, 3), a as ({O.estimates('view, query_id')}), {O.ERRORS} {O.SUMMARY.format(by='view')}"


_add("w5_accuracy", _log_accuracy_sql())(lambda s, d: _rounded(log_views.accuracy(s, d), 5))
_add(
    "w5_l6_sessions",
    f"""with e as (select *, coalesce(ts - lag(ts) over w > interval 12 hour, true) as opens from events window w as (partition by user_id order by ts, event_id)),
 n as (select *, sum(cast(opens as int)) over (partition by user_id order by ts, event_id rows unbounded preceding) as nth from e), b as (select *, cast(min(ts) over (partition by user_id, nth) as date) as session_day from n)
 select user_id, session_day, count(*) as n, round(cast(sum(cast(value as decimal(18,4))) as double), 4) as total from b where {O.sampled("user_id || '|' || cast(session_day as varchar)")} group by 1, 2""",
)(lambda s, d: _rounded(log_views.build(s, d, "l6").fresh_s.select("user_id", "session_day", F.col("n").cast("bigint").alias("n"), "total"), 4))
_add("w5_l8_active_days", "select user_id, count(distinct cast(ts as date)) as days, count(*) as n from events group by 1")(lambda s, d: log_views.active_days(T.load(s, d, "events")).select("user_id", "days", F.col("n").cast("bigint").alias("n")))
for _name, _f in complex_views.QUERIES.items():
    _add(f"w2_{_name}", complex_views.SQL.get(_name))(_f)
_add("w2_accuracy", complex_views.accuracy_sql(O.ERRORS, O.SUMMARY, O.INS))(lambda s, d: _rounded(complex_views.accuracy(s, d), 5))
_add("w2_times")(complex_views.times)
_add("w2_verdicts")(complex_views.verdicts)


@contextmanager
def _scratch(spark, name: str):
    """A folder of this run alone for stored views, in the warehouse, which all executors reach; removed at the end.

    Runs of the same or another timing query beside this one do not share it. What a run cached is freed too.
    """
    warehouse = spark.conf.get("spark.sql.warehouse.dir").rstrip("/")
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{warehouse}/freshview_timing/{name}-{uuid.uuid4().hex}")
    try:
        yield path.toString()
    finally:
        timing.free_cached()
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def _timed(times, work: str):
    def run(spark, d):
        with _scratch(spark, work) as folder:
            return times(spark, d, folder, work)

    return run


for _work, _id in (("join_view", "w1"), ("cube", "w4")):
    _add(f"{_id}_time_by_ratio")(_timed(timing.times_by_ratio, _work))
    _add(f"{_id}_time_by_change")(_timed(timing.times_by_change, _work))


@_add("w1_total_time")
def _total(spark, d):
    with _scratch(spark, "total") as folder:
        rows = timing.total_times(timing.join_view_stored(spark, d, folder), AggQuery("sum", "l_extendedprice", "l_quantity > 10"))
    return spark.createDataFrame(rows, "method string, maintenance_s double, query_s double")


_add("w7_throughput")(minibatch.throughput)
_add("w7_period_errors")(minibatch.period_errors)
_add("w7_smallest_batch")(lambda s, d: minibatch.smallest_batch(minibatch.throughput(s, d)))
_add("w7_cpu_utilisation")(minibatch.utilisation)
_add("skew_popular_parts", f"with {O.LINE} select cast(floor(2000 * power((cast('0x' || substr(md5('z|' || l_orderkey || '|' || l_seq), 1, 8) as bigint) + 1) / 4294967296.0, 2)) as bigint) as part, count(*) as n from line group by 1")(
    lambda s, d: T.lines(s, d).select(skew.popular(2000, skew.unit(["l_orderkey", "l_seq"]), 2).alias("part")).groupBy("part").agg(F.count(F.lit(1)).alias("n"))
)


# --- surrounding operators ------------------------------------------------------------------
_SIZES = "(values ('small', 1, 10), ('medium', 10, 25), ('large', 25, 51), ('odd', 5, 12)) as t(label, low, high)"


@_add("s14_range_join", f"select p_partkey, label from part join {_SIZES} on p_size >= low and p_size < high")
def _s14(spark, d):
    return joins.range_join(T.load(spark, d, "part"), "p_size", spark.sql("SELECT * FROM VALUES ('small', 1, 10), ('medium', 10, 25), ('large', 25, 51), ('odd', 5, 12) AS t(label, low, high)"), "low", "high", 10).select("p_partkey", "label")


def _kind(spark, d, kind: str, *names: tuple[str, str]) -> DataFrame:
    return T.load(spark, d, "events").filter(F.col("event_type") == kind).select("user_id", *[F.col(a).alias(b) for a, b in names])


@_add("s15_interval_join", "select c.event_id as click, e.event_id as error from events c join events e on c.user_id = e.user_id and c.event_type = 'click' and e.event_type = 'error' and e.ts > c.ts and e.ts <= c.ts + interval 6 hour")
def _s15(spark, d):
    return joins.interval_join(_kind(spark, d, "click", ("event_id", "click"), ("ts", "ts_click")), _kind(spark, d, "error", ("event_id", "error"), ("ts", "ts_error")), "user_id", "ts_click", "ts_error", 6 * 3600).select("click", "error")


@_add("s16_asof_join", "select e.event_id, c.event_id as asof_click from (select * from events where event_type = 'error') e asof left join (select * from events where event_type = 'click') c on e.user_id = c.user_id and e.ts >= c.ts")
def _s16(spark, d):
    return joins.asof_join(_kind(spark, d, "error", ("event_id", "event_id"), ("ts", "ts")), _kind(spark, d, "click", ("event_id", "click"), ("ts", "ts")), "user_id", "ts", ["click"], "click").select("event_id", "asof_click")


_add("s13_theta_join", "select r_regionkey, n_nationkey from region join nation on r_regionkey < n_regionkey")(lambda s, d: Join(_scan(s, d, "region"), _scan(s, d, "nation"), condition="r_regionkey < n_regionkey").lower().select("r_regionkey", "n_nationkey"))
_add("s21_distinct_counts", "select l_suppkey, count(distinct l_partkey) as parts, count(distinct l_orderkey) as orders from lineitem group by 1")(lambda s, d: T.load(s, d, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey").alias("orders")))
_add("s21_distinct_sketch")(lambda s, d: T.load(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts")))
_add("s24_grouping_sets", "select l_returnflag, l_linestatus, cast(grouping_id(l_returnflag, l_linestatus) as bigint) as gid, count(*) as n from lineitem group by rollup (l_returnflag, l_linestatus)")(lambda s, d: T.load(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("n")))
_add("s25_ranks", "select o_orderkey, cast(rank() over w as int) as r, cast(dense_rank() over w as int) as dr, cast(ntile(4) over (partition by o_custkey order by o_orderdate, o_orderkey) as int) as quarter from orders window w as (partition by o_custkey order by o_orderpriority)")(
    lambda s, d: T.load(s, d, "orders").selectExpr("o_orderkey", "rank() over (partition by o_custkey order by o_orderpriority) as r", "dense_rank() over (partition by o_custkey order by o_orderpriority) as dr", "ntile(4) over (partition by o_custkey order by o_orderdate, o_orderkey) as quarter")
)
_add("s26_running_sums", "select event_id, count(*) over (partition by user_id order by ts, event_id rows unbounded preceding) as so_far, lag(event_id) over (partition by user_id order by ts, event_id) as before from events")(
    lambda s, d: T.load(s, d, "events").selectExpr("event_id", "count(*) over (partition by user_id order by ts, event_id rows unbounded preceding) as so_far", "lag(event_id) over (partition by user_id order by ts, event_id) as before")
)
_add("s27_top_per_group", "select * from (select o_custkey, o_orderkey, cast(row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as int) as place from orders) where place <= 3")(lambda s, d: joins.top_per_group(T.load(s, d, "orders").select("o_custkey", "o_orderkey", "o_totalprice"), ["o_custkey"], "o_totalprice", 3, ["o_orderkey"]).select("o_custkey", "o_orderkey", "place"))


def _langs(s, d, source: str) -> Scan:
    return Scan("documents", T.load(s, d, "documents").filter(F.col("source") == source).select("lang"), ("lang",))


for _kind_, _node, _word in (("union", Union, "union all"), ("intersect", Intersect, "intersect all"), ("difference", Difference, "except all")):
    _add(f"s28_bag_{_kind_}", f"select lang from documents where source = 'src0' {_word} select lang from documents where source = 'src1'")(lambda s, d, n=_node: n(_langs(s, d, "src0"), _langs(s, d, "src1"), bag=True).lower())


@_add("s40_sql_in_sample", f"select o_orderkey, substr(md5('s1|' || o_orderkey), 1, 8) as h from orders where {O.sampled('o_orderkey')}")
def _s40(spark, d):
    H.register_sql_functions(spark)
    T.load(spark, d, "orders").createOrReplaceTempView("freshview_orders")
    return spark.sql("SELECT o_orderkey, key_hash(CAST(o_orderkey AS STRING), 's1') AS h FROM freshview_orders WHERE in_sample(CAST(o_orderkey AS STRING), 0.1D, 's1')")


@_add("s42_answer_fresh", _PAIRS + " select 'direct' as method, round(sum(f), 0) as estimate, round(1.96 * sqrt(0.9 * sum(f * f)), 0) as width from p union all select 'correction', round((select cast(sum(v) as double) from stale) + sum(f) - sum(s), 0), round(1.96 * sqrt(0.9 * sum((f - s) * (f - s))), 0) from p")
def _s42(spark, d):
    s = _demand(spark, d)
    row = table_functions.prepared(s.stale, s.stale_s, s.fresh_s, demand.QUERIES["sum"], M, KEY)
    return table_functions.answer_fresh(spark, row).select("method", F.round("estimate", 0).alias("estimate"), F.round((F.col("high") - F.col("low")) / 2, 0).alias("width"))


def queries() -> dict:
    return dict(_queries)


def oracle_sql() -> dict:
    return dict(_sql)
