"""Stale and fresh samples, their correspondence, and the naive ways that do not give a clean sample."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import SALT, Banded, in_sample, key_hash_filter
from ..sources.changes import ChangeSet
from .maintenance import delta_view, refresh
from .views import COUNT, View


def stale_sample(stale: DataFrame | Banded, key: tuple[str, ...], m: float, salt: str = SALT, family: str = "md5") -> DataFrame:
    if isinstance(stale, Banded):
        return stale.sample(key, m, salt, family)
    return key_hash_filter(stale, list(key), m, salt, family)


def check_correspondence(stale: DataFrame, fresh: DataFrame, stale_s: DataFrame, fresh_s: DataFrame, key: tuple[str, ...], m: float) -> DataFrame:
    """Four rows (clause, observed, expected, violations), from one pass over flags by key.

    uniform: sampled fresh keys against m times all; superfluous: sampled keys that are not
    fresh; missing: sampled new keys against m times all new; preserved: stale sampled keys
    that are fresh but not in the fresh sample.
    """
    frames = {"s": stale, "f": fresh, "ss": stale_s, "fs": fresh_s}
    tagged = None
    for name, df in frames.items():
        part = df.select(*key, *[F.lit(int(n == name)).alias(n) for n in frames])
        tagged = part if tagged is None else tagged.unionByName(part)
    flags = tagged.groupBy(*key).agg(*[F.max(n).alias(n) for n in frames])
    n = lambda cond: F.sum(F.expr(f"cast({cond} as bigint)"))
    sums = flags.agg(
        n("fs = 1").alias("fs"), n("f = 1").alias("f"), n("fs = 1 and f = 0").alias("bad_superfluous"), n("f = 1 and s = 0").alias("new"), n("fs = 1 and s = 0").alias("new_s"),
        n("ss = 1 and f = 1").alias("kept"), n("ss = 1 and f = 1 and fs = 0").alias("lost"),
    )
    none, double = F.lit(0).cast("bigint"), lambda c: F.col(c).cast("double")
    row = lambda clause, observed, expected, violations: F.struct(F.lit(clause).alias("clause"), observed.alias("observed"), expected.cast("double").alias("expected"), violations.alias("violations"))
    rows = F.array(
        row("uniform", double("fs"), F.col("f") * m, none),
        row("superfluous", F.lit(0.0), F.lit(0.0), F.col("bad_superfluous")),
        row("missing", double("new_s"), F.col("new") * m, none),
        row("preserved", (F.col("kept") - F.col("lost")).cast("double"), double("kept"), F.col("lost")),
    )
    return sums.select(F.inline(rows))


def refresh_then_sample(view: View, stale: DataFrame, changes: ChangeSet, m: float, salt: str = SALT) -> DataFrame:
    """Baseline: right, but the whole view is refreshed first.

    The row number is no part of the result: no filter moves below a column that depends on
    the order of rows, so every row of the fresh view is computed.
    """
    whole = refresh(view, stale, changes).withColumn("__row", F.monotonically_increasing_id())
    return whole.filter(in_sample(whole, list(view.keys), m, salt) & (F.col("__row") >= 0)).drop("__row")


def naive_row_sample_refresh(view: View, stale_s: DataFrame, changes: ChangeSet, m: float, salt: str = "r1") -> DataFrame:
    """Baseline: wrong. The changes are sampled by row, so every group is only partly refreshed."""
    some = ChangeSet(dict(changes.old), {t: key_hash_filter(f, list(changes.key_of(t)), m, salt) for t, f in changes.inserted.items()}, {t: key_hash_filter(f, list(changes.key_of(t)), m, salt) for t, f in changes.deleted.items()}, dict(changes.keys))
    names = [*[n for n, _ in view.sums], COUNT]
    delta = delta_view(view, some).lower().select(*view.keys, *names)
    return stale_s.select(*view.keys, *names).unionByName(delta).groupBy(*view.keys).agg(*[F.sum(n).alias(n) for n in names]).filter(F.col(COUNT) > 0)


def sample_base_then_view(rows: DataFrame, row_key: tuple[str, ...], group: tuple[str, ...], m: float, salt: str = SALT) -> DataFrame:
    """Counter-example: sampling base rows before grouping leaves partial counts."""
    return key_hash_filter(rows, list(row_key), m, salt).groupBy(*group).agg(F.count(F.lit(1)).alias("n"))


def rowwise_clean_only(stale_s: DataFrame, fresh: DataFrame, key: tuple[str, ...]) -> DataFrame:
    """Baseline: rows of the stale sample are corrected, but none appears; missing rows bias it."""
    return fresh.join(stale_s.select(*key), list(key), "left_semi")
