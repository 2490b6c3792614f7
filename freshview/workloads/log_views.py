"""Views over an activity log; the last part by time is pending."""

from __future__ import annotations

import random

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.estimate import AggQuery, answers_many
from ..operators.metrics import error_summary, with_errors
from ..operators.views import View
from ..plans.nodes import Node, Project
from ..sources import tables as T
from .base import RATIO, State, event_changes, state_of

VALUE = "cast(value as decimal(18,4))"
SESSION_GAP = "12 hours"


def _project(*items: tuple[str, str]):
    def rows(leaf: dict[str, Node]) -> Node:
        return Project(leaf["events"], (*items, ("value", "value"), ("ts", "ts"), ("w_events", "w_events")))

    return rows


DAY, HOUR = ("day", "cast(ts as date)"), ("hour", "date_trunc('HOUR', ts)")
USER, TYPE, PROP = ("user_id", "user_id"), ("event_type", "event_type"), ("k", "get_json_object(props, '$.k')")
COUNTS = (("n", "1"), ("total", VALUE))
VIEWS = {
    "l1": View("l1", ("user_id",), COUNTS, _project(USER), ("events",)),
    "l2": View("l2", ("user_id", "event_type"), COUNTS, _project(USER, TYPE), ("events",)),
    "l3": View("l3", ("user_id", "day"), COUNTS, _project(USER, DAY), ("events",)),
    "l4": View("l4", ("user_id", "day"), (("n", "1"), ("errors", "cast(event_type = 'error' as int)")), _project(USER, DAY, TYPE), ("events",)),
    "l5": View("l5", ("event_type", "hour_text"), COUNTS, _project(TYPE, ("hour_text", "date_format(ts, 'yyyy-MM-dd HH')")), ("events",)),
    "l6": View("l6", ("user_id", "session_day"), COUNTS, _project(USER, ("session_day", "cast(session_start as date)")), ("events",)),
    "l7": View("l7", ("k", "day"), COUNTS, _project(PROP, DAY), ("events",)),
}


def sessions(events: DataFrame, gap: str = SESSION_GAP) -> DataFrame:
    """``session_start``: a user's events with no gap of this length between them belong together."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    fresh = F.col("ts") - F.lag("ts").over(order) > F.expr(f"interval {gap}")
    marked = events.withColumn("__new", F.coalesce(fresh, F.lit(True)))
    start = F.last(F.when(F.col("__new"), F.col("ts")), ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, 0))
    return marked.withColumn("session_start", start).drop("__new")


def build(spark: SparkSession, sf_dir: str, name: str, m: float = RATIO, share: float = 0.2) -> State:
    events = T.load(spark, sf_dir, "events")
    return state_of(VIEWS[name], event_changes(spark, sf_dir, share, sessions(events) if name == "l6" else events), m)


def active_days(events: DataFrame) -> DataFrame:
    """Days on which each user was active: a nested aggregate that is keyed by user."""
    return events.groupBy("user_id", F.to_date("ts").alias("day")).agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.count(F.lit(1)).alias("days"), F.sum("n").alias("n"))


def queries(name: str, seed: int = 0, n: int = 20) -> list[tuple[str, AggQuery]]:
    """Random subsets of users or of time, with a random aggregate."""
    rng = random.Random(seed)
    out = []
    for i in range(n):
        agg = rng.choice(["sum", "count", "avg"])
        if "user_id" in VIEWS[name].keys:
            low = rng.randrange(100)
            cond = f"user_id % 100 between {low} and {low + rng.randrange(20, 60)}"
        else:
            cond = "n >= 1" if rng.random() < 0.5 else "n >= 2"
        attr = "errors" if name == "l4" else "total"
        out.append((f"{name}_{i}", AggQuery(agg, attr, cond)))
    return out


def run(spark: SparkSession, sf_dir: str, name: str, m: float = RATIO, share: float = 0.2, seed: int = 0, n: int = 20) -> DataFrame:
    """truth, stale, direct and correction of random queries on one view, in one pass."""
    s = build(spark, sf_dir, name, m, share)
    return with_errors(answers_many(s.stale, s.fresh, s.stale_s, s.fresh_s, queries(name, seed, n), m))


def accuracy(spark: SparkSession, sf_dir: str, m: float = RATIO, share: float = 0.2, seed: int = 0, n: int = 20, names: tuple[str, ...] = tuple(VIEWS)) -> DataFrame:
    """Median, 75 % and largest error by view and method."""
    out = None
    for name in names:
        rows = run(spark, sf_dir, name, m, share, seed, n).withColumn("view", F.lit(name))
        out = rows if out is None else out.unionByName(rows)
    return error_summary(out, by=("view",))
