"""Bootstrap intervals in one job, without a driver loop and without random state.

Resampling with replacement is a Poisson(1) weight by row and replicate. The weight
comes from a hash of seed, replicate and key through a fixed ladder, so another engine
can repeat it. Rows are exploded by replicate only on the sample; linear aggregates are
sums of weight times value, medians are percentiles with the weight as frequency.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import key_text
from .estimate import AggQuery, UnsupportedEstimate, _tagged, correction_estimate, direct_estimate

REPLICATES = 100


def poisson_ladder(most: int = 8) -> list[str]:
    """Cumulative Poisson(1) probabilities as eight hex digits; the weight is how many of them the hash has reached."""
    total, term, out = 0.0, math.exp(-1), []
    for k in range(most):
        total += term
        out.append(f"{math.floor(total * 2**32):08x}")
        term /= k + 1
    return out


def poisson_weight(text: Column) -> Column:
    h = F.substring(F.md5(text), 1, 8)
    weight = F.lit(0)
    for bound in poisson_ladder():
        weight = weight + (h >= bound).cast("int")
    return weight


def replicate(sample: DataFrame, key: tuple[str, ...], replicates: int, seed: str, side: str = "") -> DataFrame:
    """Every row with replicate ``b`` and weight ``w``; rows of weight 0 are gone."""
    text = key_text(sample, list(key))
    drawn = sample.withColumn("__key", text).withColumn("b", F.explode(F.sequence(F.lit(1), F.lit(replicates))))
    return drawn.withColumn("w", poisson_weight(F.concat_ws("|", F.lit(seed + side), F.col("b").cast("string"), F.col("__key")))).filter("w > 0").drop("__key")


def percentile_udaf(p: float):
    """A grouped-aggregate Pandas function of value and weight, equal to ``percentile`` with a frequency.

    For measures that Spark has no weighted form of; one replicate's sampled rows must fit a
    Python worker, which the built-in aggregate does not ask.
    """

    @F.pandas_udf("double")
    def weighted(v: pd.Series, w: pd.Series) -> float:
        kept = v.notna() & w.notna()
        drawn = np.repeat(v[kept].to_numpy("float64"), w[kept].to_numpy("int64"))
        return float(np.percentile(drawn, 100 * p)) if drawn.size else None

    return weighted


def direct_replicates_udaf(fresh_s: DataFrame, q: AggQuery, key: tuple[str, ...], replicates: int = REPLICATES, seed: str = "b1") -> DataFrame:
    """Replicates of a median or percentile by the Pandas aggregate."""
    if q.agg not in ("median", "percentile"):
        raise UnsupportedEstimate(q.agg)
    rows = replicate(fresh_s, key, replicates, seed).filter(F.expr(q.cond))
    return rows.groupBy("b").agg(percentile_udaf(0.5 if q.agg == "median" else q.p)(F.expr(q.attr).cast("double"), F.col("w")).alias("v"))


def _weighted(q: AggQuery, m: float, cond: str) -> Column:
    hit = F.coalesce(F.expr(cond), F.lit(False))
    attr = F.expr(q.attr).cast("double")
    w = F.when(hit, F.col("w"))
    match q.agg:
        case "sum":
            return F.coalesce(F.sum(F.when(hit, attr * F.col("w"))), F.lit(0.0)) / m
        case "count":
            return F.coalesce(F.sum(w), F.lit(0)).cast("double") / m
        case "avg":
            return F.try_divide(F.sum(F.when(hit, attr * F.col("w"))), F.sum(w).cast("double"))
        case "ratio":
            return F.try_divide(F.sum(F.when(hit, attr * F.col("w"))), F.sum(F.when(hit, F.expr(q.over).cast("double") * F.col("w"))))
        case "median" | "percentile":
            return F.percentile(F.when(hit, attr), F.lit(0.5 if q.agg == "median" else q.p), F.coalesce(w, F.lit(0)))
    raise UnsupportedEstimate(q.agg)


def _interval(values: DataFrame, level: float) -> DataFrame:
    return values.agg(F.percentile("v", F.lit((1 - level) / 2)).alias("low"), F.percentile("v", F.lit((1 + level) / 2)).alias("high"), F.count("v").alias("replicates"))


def direct_replicates(fresh_s: DataFrame, q: AggQuery, m: float, key: tuple[str, ...], replicates: int = REPLICATES, seed: str = "b1") -> DataFrame:
    return replicate(fresh_s, key, replicates, seed).groupBy("b").agg(_weighted(q, m, q.cond).alias("v"))


def bootstrap_direct(fresh_s: DataFrame, q: AggQuery, m: float, key: tuple[str, ...], replicates: int = REPLICATES, level: float = 0.95, seed: str = "b1") -> DataFrame:
    """estimate, low, high, replicates."""
    return direct_estimate(fresh_s, q, m).crossJoin(_interval(direct_replicates(fresh_s, q, m, key, replicates, seed), level))


def correction_replicates(stale_s: DataFrame, fresh_s: DataFrame, q: AggQuery, m: float, key: tuple[str, ...], replicates: int = REPLICATES, seed: str = "b1", paired: bool = True) -> DataFrame:
    """Drift by replicate. Paired: one weight a key on both sides, which keeps their covariance; else each side draws its own."""
    if paired:
        both = replicate(_tagged(stale_s, fresh_s), key, replicates, seed)
    else:
        tagged = _tagged(stale_s, fresh_s)
        both = replicate(tagged.filter("__side = 1"), key, replicates, seed, "f").unionByName(replicate(tagged.filter("__side = -1"), key, replicates, seed, "s"))
    side = lambda s: F.coalesce(_weighted(q, m, f"({q.cond}) and __side = {s}"), F.lit(0.0))
    return both.groupBy("b").agg((side(1) - side(-1)).alias("v"))


def bootstrap_correction(stale: DataFrame, stale_s: DataFrame, fresh_s: DataFrame, q: AggQuery, m: float, key: tuple[str, ...], replicates: int = REPLICATES, level: float = 0.95, seed: str = "b1", paired: bool = True) -> DataFrame:
    """The corrected answer, and the stale answer moved by the percentiles of the drift."""
    from .estimate import answer_exact

    drift = _interval(correction_replicates(stale_s, fresh_s, q, m, key, replicates, seed, paired), level)
    base = correction_estimate(stale, stale_s, fresh_s, q, m).crossJoin(answer_exact(stale, q, "was"))
    return base.crossJoin(drift).select("estimate", (F.col("was") + F.col("low")).alias("low"), (F.col("was") + F.col("high")).alias("high"), "replicates")
