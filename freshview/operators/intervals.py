"""Confidence intervals from sample moments.

Variance forms: ``ht`` (default) is the Horvitz-Thompson variance of a total from a
sample of random size, which hash samples are; ``clt`` scales the half-width of the
mean contribution to the total; ``printed`` is the half-width of the mean contribution
itself, kept for fidelity and too narrow for totals; ``linearised`` is for ratios and
averages.
"""

from __future__ import annotations

from statistics import NormalDist

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .estimate import AggQuery, correction_estimate, direct_estimate, paired_moments

#: Tail factors of the two usual levels.
TAILS = {0.95: 1.96, 0.99: 2.57}


def tail(level: float) -> float:
    return TAILS.get(level) or NormalDist().inv_cdf(0.5 + level / 2)


def clt_interval(contributions: DataFrame, level: float = 0.95, column: str = "y") -> DataFrame:
    """Mean and half-width of the mean."""
    return contributions.agg(F.avg(column).alias("mean"), (tail(level) * F.stddev_samp(column) / F.sqrt(F.count(F.lit(1)))).alias("half_width"), F.count(F.lit(1)).alias("k"))


def contributions(sample: DataFrame, q: AggQuery, m: float, key: tuple[str, ...]) -> DataFrame:
    """Key and contribution; an average keeps its predicate and has no scale."""
    if q.agg == "avg":
        return sample.filter(q.cond).select(*key, F.expr(q.attr).cast("double").alias("y"))
    return sample.select(*key, q.contribution(m).alias("y"))


def keyed_difference(fresh: DataFrame, stale: DataFrame, key: tuple[str, ...]) -> DataFrame:
    """Fresh less stale contribution by key, missing as zero: a signed union summed by key."""
    both = fresh.select(*key, "y").unionByName(stale.select(*key, (-F.col("y")).alias("y")))
    return both.groupBy(*key).agg(F.sum("y").alias("y"))


def half_width(variance: str, level: float, m: float, y: str = "y") -> Column:
    """Over contributions that carry the scale 1/m."""
    g, v = tail(level), F.col(y)
    mean_width = g * F.stddev_samp(v) / F.sqrt(F.count(F.lit(1)))
    match variance:
        case "printed":
            return mean_width
        case "clt":
            return mean_width * F.count(F.lit(1))
        case "ht":
            return g * F.sqrt((1 - m) * F.sum(v * v))
    raise ValueError(variance)


def _clustered(c: DataFrame, cluster_by: tuple[str, ...]) -> DataFrame:
    return c.groupBy(*cluster_by).agg(F.sum("y").alias("y"))


def direct_interval(fresh_s: DataFrame, q: AggQuery, m: float, key: tuple[str, ...], level: float = 0.95, variance: str = "ht", cluster_by: tuple[str, ...] = ()) -> DataFrame:
    """estimate, half_width, low, high, k. With ``cluster_by`` (prefix sampling) contributions are summed by prefix first."""
    if q.agg in ("avg", "ratio"):
        return _ratio_interval(fresh_s, q, m, level)
    c = contributions(fresh_s, q, m, key)
    c = _clustered(c, cluster_by) if cluster_by else c
    return _bounds(c.agg(F.coalesce(F.sum("y"), F.lit(0.0)).alias("estimate"), F.coalesce(half_width(variance, level, m), F.lit(0.0)).alias("half_width"), F.count(F.lit(1)).alias("k")))


def _bounds(df: DataFrame) -> DataFrame:
    e, h = F.col("estimate"), F.col("half_width")
    return df.select("estimate", "half_width", (e - h).alias("low"), (e + h).alias("high"), "k")


def _ratio_interval(sample: DataFrame, q: AggQuery, m: float, level: float) -> DataFrame:
    """Linearised: residuals of the numerator on the denominator, over the denominator's total."""
    over = "1" if q.agg == "avg" else q.over
    rows = sample.filter(q.cond).select(F.expr(q.attr).cast("double").alias("y"), F.expr(over).cast("double").alias("x"))
    total = rows.agg(F.try_divide(F.sum("y"), F.sum("x")).alias("r"), F.sum("x").alias("sx"))
    e = F.col("y") - F.col("r") * F.col("x")
    sums = rows.crossJoin(F.broadcast(total)).agg(F.first("r").alias("estimate"), (tail(level) * F.sqrt((1 - m) * F.sum(e * e)) / F.first("sx")).alias("half_width"), F.count(F.lit(1)).alias("k"))
    return _bounds(sums)


def correction_interval(stale: DataFrame, stale_s: DataFrame, fresh_s: DataFrame, q: AggQuery, m: float, key: tuple[str, ...], level: float = 0.95, variance: str = "ht", cluster_by: tuple[str, ...] = ()) -> DataFrame:
    """As direct_interval, on the keyed differences, around the corrected answer."""
    d = keyed_difference(contributions(fresh_s, q, m, key), contributions(stale_s, q, m, key), key)
    d = _clustered(d, cluster_by) if cluster_by else d
    width = d.agg(F.coalesce(half_width(variance, level, m), F.lit(0.0)).alias("half_width"), F.count(F.lit(1)).alias("k"))
    return _bounds(correction_estimate(stale, stale_s, fresh_s, q, m).crossJoin(width))


def coverage_trial(stale: DataFrame, fresh: DataFrame, q: AggQuery, m: float, key: tuple[str, ...], salts: list[str], level: float = 0.95) -> DataFrame:
    """Per salt: truth, both estimates and half-widths, and whether they cover. One job: salts are exploded.

    Keys of the paired view are hashed once a salt, so the shuffle is by salt only (partial sums).
    """
    from ..functions.hashing import below, hash32, key_text

    pairs = paired_moments(stale, fresh, q, 1.0, key)
    text = key_text(pairs, list(key))
    totals = pairs.agg(F.sum("f").alias("truth"), F.sum("s").alias("was"))
    drawn = pairs.select("f", "s", F.explode(F.array(*[F.lit(s) for s in salts])).alias("salt"), text.alias("text"))
    kept = drawn.filter(below(F.substring(F.md5(F.concat("salt", F.lit("|"), "text")), 1, 8), m))
    f, d, g = F.col("f"), F.col("f") - F.col("s"), tail(level)
    by = kept.groupBy("salt").agg((F.sum("f") / m).alias("direct"), (F.sum(d) / m).alias("drift"), (g * F.sqrt((1 - m) * F.sum(f * f)) / m).alias("direct_width"), (g * F.sqrt((1 - m) * F.sum(d * d)) / m).alias("correction_width"))
    out = by.crossJoin(F.broadcast(totals)).withColumn("correction", F.col("was") + F.col("drift"))
    covers = lambda e, w: (F.abs(F.col(e) - F.col("truth")) <= F.col(w))
    return out.select("salt", "truth", F.col("was").alias("stale"), "direct", "direct_width", "correction", "correction_width", covers("direct", "direct_width").alias("direct_covers"), covers("correction", "correction_width").alias("correction_covers"))


bias_trial = coverage_trial
