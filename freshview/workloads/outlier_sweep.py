"""Outlier sets under growing skew: order revenue and four complex views with a power tail on the price."""

from __future__ import annotations

import random
import re
import time

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import hex8, key_text
from ..operators.estimate import AggQuery, correction_estimate, direct_estimate
from ..operators.metrics import relative_error
from ..operators.outliers import OutlierSet, build_outlier_index, correction_with_outliers, direct_with_outliers, push_up
from ..operators.skew import tailed, unit
from ..operators.views import View
from ..plans.nodes import Project
from ..sources import tables as T
from ..sources.changes import ChangeSet
from .base import CHANGED, RATIO, State, order_changes, state_of
from .complex_views import MAINTAINED, SUMMED, VIEW_SQL

PRICE = "cast(price_z as decimal(24,2))"
VIEW = View("order_revenue", ("l_orderkey",), (("rev", PRICE), ("n", "1")), lambda leaf: leaf["lineitem"], ("lineitem",))


def skewed_lines(spark: SparkSession, sf_dir: str, z: float) -> DataFrame:
    return T.lines(spark, sf_dir).withColumn("price_z", tailed(F.col("l_extendedprice"), unit(["l_orderkey", "l_seq"]), z))


def build(spark: SparkSession, sf_dir: str, z: float, m: float = RATIO, frac: float = CHANGED, view: View = VIEW) -> State:
    lines = skewed_lines(spark, sf_dir, z)
    return state_of(view, ChangeSet.from_split({"lineitem": lines}, T.KEYS, {"lineitem": (frac, 0.0)}), m)


def outlier_rows(state: State, cap: int) -> DataFrame:
    """Fresh view rows that hold one of the ``cap`` dearest lines."""
    plan = state.view.plan({"lineitem": state.changes.new("lineitem")}, state.changes.keys)
    index = OutlierSet(frozenset({"price_z"}), build_outlier_index(state.changes.new("lineitem").withColumn("w_lineitem", F.lit(1)), "price_z", ("l_orderkey", "l_seq"), cap=cap))
    return push_up(plan, {"lineitem": index}).records.select(*state.fresh.columns)


def compare(spark: SparkSession, sf_dir: str, z: float, cap: int = 100, m: float = RATIO, q: AggQuery = AggQuery("sum", "rev")) -> DataFrame:
    """One row: truth, and both estimators with and without the set."""
    s = build(spark, sf_dir, z, m)
    o = outlier_rows(s, cap)
    parts = [
        s.fresh.agg(q.value().alias("truth")),
        direct_estimate(s.fresh_s, q, m, "direct"),
        correction_estimate(s.stale, s.stale_s, s.fresh_s, q, m, "correction"),
        direct_with_outliers(s.fresh_s, o, q, m, s.view.keys).withColumnRenamed("estimate", "direct_out"),
        correction_with_outliers(s.stale, s.stale_s, s.fresh_s, o, q, m, s.view.keys).withColumnRenamed("estimate", "correction_out"),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.crossJoin(p)
    return out.select(F.lit(float(z)).alias("z"), F.lit(cap).alias("cap"), "*")


#: The complex views whose sums the index on the price serves.
VIEWS = ("v3", "v5", "v10", "v15")
METHODS = ("direct", "direct_out", "correction", "correction_out")


def skewed_view(name: str, prices: int) -> View:
    """A complex view with one sum a skewed price; ``at`` and ``least`` pass through its rows, so that an index can mark them."""
    view, columns = MAINTAINED[name], [f"price_{i}" for i in range(prices)]
    rows = view.rows
    if name == "v15":
        kept = tuple((c, c) for c in ("l_suppkey", *columns, "at", "least", "w_lineitem"))
        rows = lambda t: Project(t["lineitem"], (*kept, ("ship_month", "date_format(l_shipdate, 'yyyy-MM')")))
    sums = tuple((f"rev_{i}", f"cast({c} as decimal(24,2))") for i, c in enumerate(columns))
    return View(name, view.keys, (*sums, ("n", "1")), rows, view.tables)


def state(spark: SparkSession, sf_dir: str, name: str, zs: tuple[float, ...] = (4,), m: float = RATIO, frac: float = CHANGED) -> State:
    """One of the four views under whole orders that enter, with a sum a skew, so all skews share one refresh."""
    c = order_changes(spark, sf_dir, frac, more={t: T.load(spark, sf_dir, t) for t in ("customer", "supplier")})
    u = unit(["l_orderkey", "l_seq"])
    tails = {f"price_{i}": tailed(F.col("l_extendedprice"), u, z) for i, z in enumerate(zs)}
    unmarked = {x: F.lit(None).cast("int") for x in ("at", "least")}
    for side in (c.old, c.inserted, c.current):
        side["lineitem"] = side["lineitem"].withColumns(tails | unmarked)
    return state_of(skewed_view(name, len(zs)), c, m)


def outlier_keys(s: State, caps: tuple[int, ...]) -> DataFrame:
    """(key, at, least): by number of the price, the smallest of the caps whose index holds a line of the view row.

    Indexes of one price are nested, so only the largest is built, and its records (at most
    the cap) are ranked. They go up through the rows of the view, not to its sums.
    """
    lines = s.changes.new("lineitem")
    key, caps = ("l_orderkey", "l_seq"), sorted(c for c in caps if c)
    index = None
    for i in range(sum(n.startswith("rev_") for n, _ in s.view.sums)):
        top = build_outlier_index(lines, f"price_{i}", key, cap=caps[-1])
        rank = F.row_number().over(Window.orderBy(F.desc(f"price_{i}"), *key))
        least = F.coalesce(*[F.when(rank <= c, F.lit(c)) for c in caps])
        part = top.withColumns({"at": F.lit(i), "least": least})
        index = part if index is None else index.unionByName(part)
    frames = {t: s.changes.new(t) if t in s.changes.tables else s.changes.old[t] for t in s.view.tables}
    rows = s.view.rows(s.view.leaves(frames, keys=s.changes.keys))
    marked = push_up(rows, {"lineitem": OutlierSet(frozenset({"price_0"}), index.withColumn("w_lineitem", F.lit(1)))}).records
    return marked.groupBy(*s.view.keys, "at").agg(F.min("least").alias("least"))


def ranges(n: int, seed: int = 0) -> list[tuple[int, str, str]]:
    """(draw, low, high) of two hex digits of the key's hash; draw 0 is the whole view."""
    rng = random.Random(seed)
    return [(0, "00", "zz")] + [(k, f"{(low := rng.randrange(0, 120)):02x}", f"{low + rng.randrange(96, 136):02x}") for k in range(1, n)]


def errors(s: State, caps: tuple[int, ...] = (100,), salts: int = 20, n: int = 5, seed: int = 0) -> DataFrame:
    """One row a price, cap, salt and random query: relative errors of SUM(rev) by each estimator, without and with the set.

    The pairs of stale and fresh rows are made once; prices, salts and random subsets of the
    keys are small tables, so every repetition is part of one aggregate. Sums are exact.
    """
    keys, prices = list(s.view.keys), [n for n, _ in s.view.sums if n.startswith("rev_")]

    def side(df: DataFrame, name: str) -> DataFrame:
        return df.select(*keys, *[F.col(p).cast("decimal(28,2)").alias(f"{name}_{i}") for i, p in enumerate(prices)])

    values = [f"{x}_{i}" for x in "fs" for i in range(len(prices))]
    pairs = side(s.fresh, "f").join(side(s.stale, "s"), keys, "full_outer").na.fill(0, values)
    each = F.explode(F.array(*[F.struct(F.lit(i).alias("at"), F.coalesce(F.col(f"f_{i}"), F.lit(0).cast("decimal(28,2)")).alias("f"), F.coalesce(F.col(f"s_{i}"), F.lit(0).cast("decimal(28,2)")).alias("s")) for i in range(len(prices))]))
    pairs = pairs.select(*keys, each.alias("__v")).select(*keys, "__v.*")
    if any(caps):
        pairs = pairs.join(outlier_keys(s, caps), [*keys, "at"], "left")
    else:
        pairs = pairs.withColumn("least", F.lit(None).cast("int"))
    text = key_text(pairs, keys)
    spark = pairs.sparkSession
    tables = [spark.createDataFrame([(c,) for c in caps], "cap int"), spark.createDataFrame([(f"s{k}",) for k in range(1, salts + 1)], "salt string"), spark.createDataFrame(ranges(n, seed), "draw int, low string, high string")]
    digits = F.substring(F.md5(F.concat(F.lit("q|"), text)), 1, 2)
    rows = pairs.withColumns({"__key": text, "__digits": digits})
    for t in tables:
        rows = rows.crossJoin(F.broadcast(t))
    rows = rows.filter((F.col("__digits") >= F.col("low")) & (F.col("__digits") < F.col("high")))
    in_sample = F.substring(F.md5(F.concat("salt", F.lit("|"), "__key")), 1, 8) < hex8(s.m)
    kept = F.coalesce(F.col("least") <= F.col("cap"), F.lit(False))
    rows = rows.withColumns({"__in": in_sample, "__kept": kept})
    rest = F.col("__in") & ~F.col("__kept")

    def total(value: Column, when: Column | None = None) -> Column:
        return F.coalesce(F.sum(value if when is None else F.when(when, value)).cast("double"), F.lit(0.0))

    f, drift = F.col("f"), F.col("f") - F.col("s")
    sums = rows.groupBy("at", "cap", "salt", "draw").agg(
        total(f).alias("truth"), (total(f, F.col("__in")) / s.m).alias("direct"), (total(f, rest) / s.m + total(f, F.col("__kept"))).alias("direct_out"),
        (total(F.col("s")) + total(drift, F.col("__in")) / s.m).alias("correction"), (total(F.col("s")) + total(drift, rest) / s.m + total(drift, F.col("__kept"))).alias("correction_out"),
    )
    return sums.select("at", "cap", "salt", "draw", *[F.round(relative_error(F.col(x), F.col("truth")), 9).alias(f"err_{x}") for x in METHODS])


def _quantiles(df: DataFrame, *by: str) -> DataFrame:
    """75 % quantiles, and the gains of the set; rounded, so that no error is told from a rounding error."""
    q75 = [F.round(F.percentile(f"err_{x}", F.lit(0.75)), 7).alias(f"q75_{x}") for x in METHODS]
    gain = lambda x: F.round(F.try_divide(F.col(f"q75_{x}"), F.col(f"q75_{x}_out")), 3).alias(f"gain_{x}")
    return df.groupBy(*by).agg(*q75).select("*", gain("direct"), gain("correction"))


def z_sweep(spark: SparkSession, sf_dir: str, zs: tuple[float, ...] = (1, 2, 3, 4), cap: int = 100, m: float = RATIO, names: tuple[str, ...] = VIEWS, salts: int = 20) -> DataFrame:
    """75 % quantile of the errors over salts and random queries, by view and skew; a job a view, of a row a skew."""
    out, kind = [], ""
    for name in names:
        part = _quantiles(errors(state(spark, sf_dir, name, zs, m), (cap,), salts), "at")
        out += [(name, float(zs[at]), *r) for at, *r in part.collect()]
        kind = ", ".join(f"{c} double" for c in part.columns[1:])
    return spark.createDataFrame(out, f"view string, z double, {kind}")


def size_sweep(spark: SparkSession, sf_dir: str, caps: tuple[int, ...] = (0, 10, 100, 1000), z: float = 4, m: float = RATIO, name: str = "v3", salts: int = 20) -> DataFrame:
    """The same by size of the index."""
    return _quantiles(errors(state(spark, sf_dir, name, (z,), m), caps, salts), "cap")


def size_times(spark: SparkSession, sf_dir: str, caps: tuple[int, ...] = (0, 10, 100, 1000), z: float = 4, m: float = RATIO, name: str = "v3") -> DataFrame:
    """Seconds to refresh the sample, and to build and push up an index, by its size; beside the full refresh."""
    s = state(spark, sf_dir, name, (z,), m)

    def seconds(df: DataFrame) -> float:
        start = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        return time.perf_counter() - start

    full, part = seconds(s.fresh), seconds(s.fresh_s)
    rows = [(cap, full, part, seconds(outlier_keys(s, (cap,))) if cap else 0.0) for cap in caps]
    return spark.createDataFrame(rows, "cap int, full_s double, sample_s double, index_s double")


def errors_sql(line: str, sampled, names: tuple[str, ...], zs: tuple[float, ...], caps: tuple[int, ...], by: str, changed: str, m: float = RATIO, salts: int = 20, n: int = 5) -> str:
    """DuckDB: the sweep over views, prices, caps, salts and random queries; ``by`` is what a row stands for."""
    head = "(cast('0x' || substr(md5('z|' || l_orderkey || '|' || l_seq), 1, 8) as bigint) + 1) / 4294967296.0"
    prices = ", ".join(f"round(l_extendedprice * power({head}, {-(z - 1) / 4}), 2) as price_{i}" for i, z in enumerate(zs))
    aggs = ", ".join(f"sum(cast(price_{i} as decimal(24,2))) as rev_{i}" for i in range(len(zs)))
    tops = ", ".join(
        f"top_{i} as (select *, row_number() over (order by price_{i} desc, l_orderkey, l_seq) as rk from z order by price_{i} desc, l_orderkey, l_seq limit {max(caps)})" for i in range(len(zs))
    )
    least = "case " + " ".join(f"when rk <= {c} then {c}" for c in sorted(c for c in caps if c)) + " end"
    ctes, pairs = [], []
    for name in names:
        sql = VIEW_SQL[name][0].format(also="", where="")
        keys = ", ".join(MAINTAINED[name].keys)
        text = " || '|' || ".join(MAINTAINED[name].keys)
        on = lambda table, what, base="orders": re.sub(r"\borders\b", base, re.sub(r"\blineitem\b", table, sql)).replace(SUMMED, what)
        marks = " union all ".join(f"select {keys}, {i} as price_no, least from ({on(f'top_{i}', f'min({least}) as least')})" for i in range(len(zs)))
        ctes.append(f"{name}_t as ({on('z', aggs)}), {name}_s as ({on('old_z', aggs, 'old_orders')}), {name}_o as ({marks})")
        for i, z in enumerate(zs):
            pairs.append(
                f"select '{name}' as view, cast({z} as double) as z, {text} as k, coalesce(t.rev_{i}, 0) as f, coalesce(s.rev_{i}, 0) as s, o.least"
                f" from {name}_t t full join {name}_s s using ({keys}) left join (select * exclude (price_no) from {name}_o where price_no = {i}) o using ({keys})"
            )
    rows = ", ".join(f"({k}, '{a}', '{b}')" for k, a, b in ranges(n))
    amount = lambda x, when="true": f"coalesce(cast(sum({x}) filter (where {when}) as double), 0)"
    rest = "hit and not kept"
    estimates = {
        "direct": f"{amount('f', 'hit')} / {m}", "direct_out": f"{amount('f', rest)} / {m} + {amount('f', 'kept')}",
        "correction": f"{amount('s')} + {amount('f - s', 'hit')} / {m}", "correction_out": f"{amount('s')} + {amount('f - s', rest)} / {m} + {amount('f - s', 'kept')}",
    }
    return f"""with {line}, z as (select *, {prices} from line), old_z as (select * from z where substr(md5('d0|' || l_orderkey), 1, 8) >= '{changed}'),
 old_orders as (select * from orders where substr(md5('d0|' || o_orderkey), 1, 8) >= '{changed}'), {tops}, {", ".join(ctes)}, pairs as ({" union all ".join(pairs)}),
 caps(cap) as (values {", ".join(f"({c})" for c in caps)}), salts as (select 's' || i as salt from range(1, {salts + 1}) t(i)), draws(draw, low, high) as (values {rows}),
 r as (select *, {sampled('k', 'salt')} as hit, coalesce(least <= cap, false) as kept from pairs, caps, salts, draws where substr(md5('q|' || k), 1, 2) >= low and substr(md5('q|' || k), 1, 2) < high),
 g as (select view, z, cap, salt, draw, {amount('f')} as truth, {", ".join(f"{e} as {x}" for x, e in estimates.items())} from r group by all),
 e as (select view, z, cap, {", ".join(f"round(abs({x} - truth) / nullif(abs(truth), 0), 9) as err_{x}" for x in METHODS)} from g),
 q as (select {by}, {", ".join(f"round(quantile_cont(err_{x}, 0.75), 7) as q75_{x}" for x in METHODS)} from e group by {by})
 select *, {", ".join(f"round(q75_{x} / nullif(q75_{x}_out, 0), 3) as gain_{x}" for x in ("direct", "correction"))} from q"""
