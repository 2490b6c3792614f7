"""Common parts of the workloads: change sets of the given tables, stale and fresh frames, results."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import SALT
from ..operators.cleaning import stale_sample
from ..operators.estimate import AggQuery, answers
from ..operators.maintenance import refresh, refresh_sample, stale_plan
from ..operators.metrics import with_errors
from ..operators.views import View
from ..sources import tables as T
from ..sources.changes import ChangeSet, split_hash
from ..functions.hashing import hex8

RATIO, CHANGED = 0.1, 0.1


@dataclass
class State:
    """A view before and after its changes, with both samples."""

    view: View
    changes: ChangeSet
    stale: DataFrame
    fresh: DataFrame
    stale_s: DataFrame
    fresh_s: DataFrame
    m: float

    def answers(self, q: AggQuery) -> DataFrame:
        return with_errors(answers(self.stale, self.fresh, self.stale_s, self.fresh_s, q, self.m))


def state_of(view: View, changes: ChangeSet, m: float = RATIO, salt: str = SALT, strategy: str = "signed_union", sample_key: tuple[str, ...] | None = None, stale: DataFrame | None = None) -> State:
    stale = stale_plan(view, changes).lower() if stale is None else stale
    return State(view, changes, stale, refresh(view, stale, changes, "recompute"), stale_sample(stale, sample_key or view.keys, m, salt), refresh_sample(view, stale, changes, m, salt, strategy, sample_key), m)


def line_changes(spark: SparkSession, sf_dir: str, inserted: float = CHANGED, deleted: float = 0.0, more: dict[str, DataFrame] | None = None, updated: bool = False) -> ChangeSet:
    """Changes of lines alone, by the hash of their key; an update adds 1 to the quantity and 10 % to the price."""
    tables = {"lineitem": T.lines(spark, sf_dir)} | (more or {})

    def change(df: DataFrame) -> DataFrame:
        return df.withColumn("l_quantity", F.col("l_quantity") + 1).withColumn("l_extendedprice", (T.money("l_extendedprice") * F.lit("1.1").cast("decimal(2,1)")).cast("decimal(12,2)").cast("double"))

    update = {"lineitem": (0.5, 0.55, change)} if updated else None
    return ChangeSet.from_split(tables, T.KEYS, {"lineitem": (inserted, deleted)}, update=update)


def order_changes(spark: SparkSession, sf_dir: str, inserted: float = CHANGED, deleted: float = 0.0, more: dict[str, DataFrame] | None = None) -> ChangeSet:
    """Whole orders with all their lines enter or leave: both join inputs change."""
    tables = {"lineitem": T.lines(spark, sf_dir), "orders": T.load(spark, sf_dir, "orders")} | (more or {})
    shares = {"lineitem": (inserted, deleted), "orders": (inserted, deleted)}
    out = ChangeSet.from_split(tables, T.KEYS, shares, by={"lineitem": ("l_orderkey",), "orders": ("o_orderkey",)})
    # inserted lines only meet inserted orders; deleted rows also meet the old ones, in terms that cancel
    out.together = () if deleted else (frozenset({"lineitem", "orders"}),)
    return out


def event_changes(spark: SparkSession, sf_dir: str, share: float = 0.2, events: DataFrame | None = None) -> ChangeSet:
    """The last ``share`` of the log's time span is pending; an event without a time is old.

    The cut is one timestamp from the span's ends, so it reaches the scan as a pushed filter.
    """
    events = T.load(spark, sf_dir, "events") if events is None else events
    first, last = events.agg(F.min("ts"), F.max("ts")).first()
    if first is None:
        return ChangeSet({"events": events}, {"events": events.limit(0)}, keys=T.KEYS)
    cut = F.lit(first + (last - first) * (1 - share)).cast(events.schema["ts"].dataType)
    return ChangeSet({"events": events.filter((F.col("ts") < cut) | F.col("ts").isNull())}, {"events": events.filter(F.col("ts") >= cut)}, keys=T.KEYS)


def change_share(df: DataFrame, key: tuple[str, ...], low: float, high: float) -> DataFrame:
    h = split_hash(df, list(key))
    return df.filter((h >= hex8(low)) & (h < hex8(high)))
