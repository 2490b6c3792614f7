"""Aggregate queries on a stale view, answered from the stale and the fresh sample.

``direct`` scales the answer on the fresh sample; ``correction`` adds the estimated
drift to the answer on the stale view. Both answer by group where ``group_by`` is set.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LINEAR = ("sum", "count")
PLUG_IN = ("avg", "median", "percentile", "ratio", "var", "stddev")
#: Fewer qualifying sample rows than this make an answer unsafe.
SAFE_SAMPLE = 30


class UnsupportedEstimate(ValueError):
    """The aggregate has no sample estimator here."""


@dataclass(frozen=True)
class AggQuery:
    """``agg`` of SQL ``attr`` where SQL ``cond``; ``over`` is a ratio's denominator, ``p`` a percentile.

    ``accuracy``: 0 for exact percentiles, which gather a group's values in one place; else
    the accuracy of the approximate ones (error 1 / accuracy of the ranks), for large groups.
    """

    agg: str
    attr: str = "1"
    cond: str = "true"
    group_by: tuple[str, ...] = ()
    over: str = "1"
    p: float = 0.5
    accuracy: int = 0

    def __post_init__(self) -> None:
        if self.agg not in (*LINEAR, *PLUG_IN, "min", "max"):
            raise UnsupportedEstimate(f"{self.agg}: use an exact refresh of the touched groups")

    def value(self) -> Column:
        """The plain aggregate of qualifying rows."""
        hit = F.coalesce(F.expr(self.cond), F.lit(False))
        attr = F.when(hit, F.expr(self.attr).cast("double"))
        match self.agg:
            case "sum":
                return F.coalesce(F.sum(F.when(hit, F.expr(self.attr))).cast("double"), F.lit(0.0))
            case "count":
                return F.coalesce(F.sum(hit.cast("bigint")).cast("double"), F.lit(0.0))
            case "avg":
                return F.try_divide(F.sum(F.when(hit, F.expr(self.attr))).cast("double"), F.sum((hit & F.expr(self.attr).isNotNull()).cast("bigint")).cast("double"))
            case "median" | "percentile":
                p = 0.5 if self.agg == "median" else self.p
                return F.percentile_approx(attr, F.lit(p), F.lit(self.accuracy)) if self.accuracy else F.percentile(attr, F.lit(p))
            case "ratio":
                return F.try_divide(F.sum(F.when(hit, F.expr(self.attr))).cast("double"), F.sum(F.when(hit, F.expr(self.over))).cast("double"))
            case "var":
                return F.var_samp(attr)
            case "stddev":
                return F.stddev_samp(attr)
            case "min":
                return F.min(attr)
            case "max":
                return F.max(attr)
        raise UnsupportedEstimate(self.agg)

    def scale(self, m: float) -> float:
        return 1 / m if self.agg in LINEAR else 1.0

    def contribution(self, m: float) -> Column:
        """What a sample row adds to a total estimate."""
        hit = F.coalesce(F.expr(self.cond), F.lit(False))
        amount = F.coalesce(F.expr(self.attr).cast("double"), F.lit(0.0)) if self.agg != "count" else F.lit(1.0)
        return F.when(hit, amount / m).otherwise(F.lit(0.0))


def _by(df: DataFrame, q: AggQuery, name: str, scale: float = 1.0) -> DataFrame:
    return df.groupBy(*q.group_by).agg((q.value() * scale).alias(name)) if q.group_by else df.agg((q.value() * scale).alias(name))


def answer_exact(view: DataFrame, q: AggQuery, name: str = "value") -> DataFrame:
    return _by(view, q, name)


answer_stale = answer_exact


def direct_estimate(fresh_s: DataFrame, q: AggQuery, m: float, name: str = "estimate") -> DataFrame:
    """Groups without a sample row are absent (unseen)."""
    if q.agg in ("min", "max"):
        raise UnsupportedEstimate(f"{q.agg}: see extreme_estimate")
    return _by(fresh_s, q, name, q.scale(m))


def _tagged(stale_s: DataFrame, fresh_s: DataFrame) -> DataFrame:
    columns = [c for c in fresh_s.columns if c in stale_s.columns]
    return fresh_s.select(*columns, F.lit(1).alias("__side")).unionByName(stale_s.select(*columns, F.lit(-1).alias("__side")))


def drift_estimate(stale_s: DataFrame, fresh_s: DataFrame, q: AggQuery, m: float) -> DataFrame:
    """Estimated fresh answer less stale answer: one pass over both samples, tagged by side."""
    both = _tagged(stale_s, fresh_s)
    side = lambda s: AggQuery(q.agg, q.attr, f"({q.cond}) and __side = {s}", (), q.over, q.p, q.accuracy).value() * q.scale(m)
    fresh, stale = side(1), side(-1)
    drift = (F.coalesce(fresh, F.lit(0.0)) - F.coalesce(stale, F.lit(0.0))).alias("drift")
    return both.groupBy(*q.group_by).agg(drift) if q.group_by else both.agg(drift)


def correction_estimate(stale: DataFrame, stale_s: DataFrame, fresh_s: DataFrame, q: AggQuery, m: float, name: str = "estimate") -> DataFrame:
    """The stale answer plus the drift. A group in no sample keeps its stale answer."""
    if q.agg in ("min", "max"):
        raise UnsupportedEstimate(f"{q.agg}: see extreme_estimate")
    was, drift = _by(stale, q, "was"), drift_estimate(stale_s, fresh_s, q, m)
    joined = was.join(drift, list(q.group_by), "full_outer") if q.group_by else was.crossJoin(drift)
    return joined.select(*q.group_by, (F.coalesce("was", F.lit(0.0)) + F.coalesce("drift", F.lit(0.0))).alias(name))


def answers(stale: DataFrame, fresh: DataFrame, stale_s: DataFrame, fresh_s: DataFrame, q: AggQuery, m: float) -> DataFrame:
    """truth, stale, direct and correction, side by side (by group where there are groups)."""
    parts = [answer_exact(fresh, q, "truth"), answer_exact(stale, q, "stale"), direct_estimate(fresh_s, q, m, "direct"), correction_estimate(stale, stale_s, fresh_s, q, m, "correction")]
    out = parts[0]
    for p in parts[1:]:
        out = out.join(p, list(q.group_by), "full_outer") if q.group_by else out.crossJoin(p)
    return out


def answers_many(stale: DataFrame, fresh: DataFrame, stale_s: DataFrame, fresh_s: DataFrame, queries: list[tuple[str, AggQuery]], m: float, draws: DataFrame | None = None) -> DataFrame:
    """query_id, group_key, truth, stale, direct and correction of many queries, in one pass over the four frames.

    Each row becomes one row a query that it qualifies for, and all sums are by query and
    group. ``draws`` is a small table of parameters that the queries name as columns: every
    query is answered once a row of it, and its columns lead the result. Totals without
    a qualifying sample row are 0 by the direct estimator; other aggregates are null there.
    Sums are exact to six decimals.
    """
    frames = {"t": fresh, "s": stale, "d": fresh_s, "c": stale_s}
    shared = [c for c in fresh.columns if all(c in f.columns for f in frames.values())]
    tagged = None
    for tag, df in frames.items():
        part = df.select(*shared, F.lit(tag).alias("__frame"))
        tagged = part if tagged is None else tagged.unionByName(part)
    by = [] if draws is None else draws.columns
    if draws is not None:
        tagged = tagged.crossJoin(F.broadcast(draws))
    amount = lambda text: F.expr(text).cast("decimal(30,6)")
    hits = []
    for name, q in queries:
        key = F.concat_ws("|", *[F.col(g).cast("string") for g in q.group_by]) if q.group_by else F.lit("")
        over = amount(q.over) if q.agg == "ratio" else F.lit(None).cast("decimal(30,6)")
        row = F.struct(F.lit(name).alias("query_id"), key.alias("group_key"), amount("1" if q.agg == "count" else q.attr).alias("x"), over.alias("y"))
        hits.append(F.when(F.coalesce(F.expr(q.cond), F.lit(False)), row))
    rows = tagged.select(*by, "__frame", F.explode(F.array_compact(F.array(*hits))).alias("hit")).select(*by, "__frame", "hit.*")
    aggs = {name: q.agg for name, q in queries}
    ranks = {q.p if q.agg == "percentile" else 0.5 for _, q in queries if q.agg in ("median", "percentile")}
    sums = []
    for tag in frames:
        mine = lambda c, tag=tag: F.when(F.col("__frame") == tag, F.col(c))
        sums += [F.sum(mine("x")).alias(f"x_{tag}"), F.sum(mine("y")).alias(f"y_{tag}"), F.count(mine("x")).alias(f"n_{tag}")]
        sums += [F.percentile(mine("x").cast("double"), F.lit(p)).alias(f"p{int(p * 1000)}_{tag}") for p in sorted(ranks)]
    got = rows.groupBy(*by, "query_id", "group_key").agg(*sums)

    def value(tag: str) -> Column:
        x, y, n = (F.col(f"{c}_{tag}") for c in "xyn")
        out = F.lit(None).cast("double")
        for name, q in queries:
            if aggs[name] == "sum" or aggs[name] == "count":
                v = F.coalesce(x.cast("double"), F.lit(0.0))
            elif aggs[name] == "avg":
                v = F.try_divide(x.cast("double"), n.cast("double"))
            elif aggs[name] == "ratio":
                v = F.try_divide(x.cast("double"), y.cast("double"))
            elif aggs[name] in ("median", "percentile"):
                v = F.col(f"p{int((q.p if q.agg == 'percentile' else 0.5) * 1000)}_{tag}")
            else:
                raise UnsupportedEstimate(q.agg)
            out = F.when(F.col("query_id") == name, v * (q.scale(m) if tag in "dc" else 1.0)).otherwise(out)
        return out

    t, s, d, c = (value(tag) for tag in frames)
    known = F.coalesce(s, d).isNotNull()
    correction = F.when(known, F.coalesce(s, F.lit(0.0)) + F.coalesce(d, F.lit(0.0)) - F.coalesce(c, F.lit(0.0)))
    return got.select(*by, "query_id", "group_key", t.alias("truth"), s.alias("stale"), d.alias("direct"), correction.alias("correction"))


def paired_moments(stale_s: DataFrame, fresh_s: DataFrame, q: AggQuery, m: float, key: tuple[str, ...]) -> DataFrame:
    """Contributions by key on both sides (0 where a row is missing)."""
    both = _tagged(stale_s, fresh_s)
    c = q.contribution(m)
    return both.select(*key, F.when(F.col("__side") == 1, c).otherwise(0.0).alias("f"), F.when(F.col("__side") == -1, c).otherwise(0.0).alias("s")).groupBy(*key).agg(F.sum("f").alias("f"), F.sum("s").alias("s"))


def variance_report(stale_s: DataFrame, fresh_s: DataFrame, q: AggQuery, m: float, key: tuple[str, ...]) -> DataFrame:
    """One row: variances of both sides, covariance, variance of the differences, and sums of squares."""
    p = paired_moments(stale_s, fresh_s, q, m, key)
    f, s = F.col("f"), F.col("s")
    return p.agg(
        F.var_samp("f").alias("var_fresh"), F.var_samp("s").alias("var_stale"), F.covar_samp("f", "s").alias("cov"), F.var_samp(f - s).alias("var_diff"),
        F.sum(s * s).alias("ss"), F.sum(s * f).alias("sf"), F.sum(f * f).alias("ff"), F.count(F.lit(1)).alias("k"),
    )


def choose_estimator(stale_s: DataFrame, fresh_s: DataFrame, q: AggQuery, m: float, key: tuple[str, ...], sampling: str = "poisson") -> DataFrame:
    """``correction`` while var(stale) <= 2 cov(stale, fresh) (sums of squares and products for hash samples), else ``direct``."""
    report = variance_report(stale_s, fresh_s, q, m, key)
    better = F.col("ss") <= 2 * F.col("sf") if sampling == "poisson" else F.col("var_stale") <= 2 * F.col("cov")
    return report.select("var_stale", "var_fresh", "cov", "var_diff", F.when(better, "correction").otherwise("direct").alias("choice"))


def effective_sample_size(fresh_s: DataFrame, q: AggQuery) -> DataFrame:
    """Sample rows, selectivity, qualifying rows, and whether they are enough."""
    hit = F.coalesce(F.expr(q.cond), F.lit(False)).cast("bigint")
    sums = fresh_s.groupBy(*q.group_by) if q.group_by else fresh_s
    return sums.agg(F.count(F.lit(1)).alias("k"), F.avg(hit).alias("selectivity"), F.sum(hit).alias("k_eff")).withColumn("safe", F.col("k_eff") >= SAFE_SAMPLE)


def extreme_estimate(stale: DataFrame, stale_s: DataFrame, fresh_s: DataFrame, q: AggQuery, key: tuple[str, ...]) -> DataFrame:
    """Heuristic for min and max: the stale extreme moved by the largest keyed difference in the samples.

    ``exceed`` bounds by Cantelli's inequality the chance that one further row's difference
    is beyond the estimate's; without differences in the sample it is null.
    """
    sign = 1 if q.agg == "max" else -1
    hit = F.coalesce(F.expr(q.cond), F.lit(False))
    side = lambda df, n: df.filter(hit).select(*key, F.expr(q.attr).cast("double").alias(n))
    diff = side(fresh_s, "f").join(side(stale_s, "s"), list(key)).select((sign * (F.col("f") - F.col("s"))).alias("d"))
    move = diff.agg(F.max("d").alias("most"), F.avg("d").alias("mean"), F.var_samp("d").alias("var"))
    far = F.greatest(F.col("most") - F.col("mean"), F.lit(0.0))
    return answer_exact(stale, q, "was").crossJoin(move).select((F.col("was") + sign * F.greatest(F.coalesce("most", F.lit(0.0)), F.lit(0.0))).alias("estimate"), F.when(F.col("var").isNotNull(), F.try_divide(F.col("var"), F.col("var") + far * far)).alias("exceed"))


def lookup_exact(view_rows: DataFrame, key_values: dict[str, object], aggs: list[Column], group: tuple[str, ...]) -> DataFrame:
    """One view row, computed from the base rows of its key."""
    for k, v in key_values.items():
        view_rows = view_rows.filter(F.col(k).eqNullSafe(F.lit(v)))
    return view_rows.groupBy(*group).agg(*aggs)
