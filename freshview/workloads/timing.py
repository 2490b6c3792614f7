"""Maintenance times: a stored stale view, cached changes, and what a refresh or a sample's refresh publishes.

The given tables are copied under shifted keys, so that rows and groups grow alike and
the fixed costs of a job do not hide the ratio. The stale view is stored by hash band;
both refreshes read it from there and write what they publish, so a sample costs its
share of the reading, the merge and the writing. Loading of changes is not counted.
"""

from __future__ import annotations

import threading
import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import SALT, Banded, below
from ..operators.cleaning import stale_sample
from ..operators.estimate import AggQuery, answer_exact, correction_estimate, direct_estimate
from ..operators.maintenance import refresh, refresh_sample, spj_refresh, stale_plan
from ..operators.views import View
from ..plans.nodes import Join, KeyHash, Project, Scan
from ..plans.pushdown import push
from ..sources import tables as T
from ..sources.changes import ChangeSet, split_hash
from . import cube, log_views
from .base import CHANGED, RATIO

#: Distance between the keys of two copies.
SHIFT = 100_000_000
FAMILY = "xxhash64"


@dataclass
class Stored:
    """A stored stale view and how to refresh it, whole or as a sample of a ratio."""

    name: str
    stale: Banded
    full: Callable[[], DataFrame]
    sample: Callable[[float], DataFrame]
    folder: str

    def publish(self, df: DataFrame) -> float:
        """Seconds to compute and store a frame."""
        start = time.perf_counter()
        df.write.mode("overwrite").parquet(f"{self.folder}/published")
        return time.perf_counter() - start

    def times(self, m: float, repeats: int = 2) -> tuple[float, float]:
        """Seconds of the full refresh and of the sample's; the best of some runs each."""
        return min(self.publish(self.full()) for _ in range(repeats)), min(self.publish(self.sample(m)) for _ in range(repeats))


def copied(df: DataFrame, copies: int, *keys: str) -> DataFrame:
    """``copies`` copies of the rows, told apart by shifted keys."""
    numbers = F.broadcast(df.sparkSession.range(copies).withColumnRenamed("id", "__copy"))
    out = df.crossJoin(numbers)
    return out.withColumns({k: F.col(k) + F.col("__copy") * SHIFT for k in keys}).drop("__copy")


def _kept(df: DataFrame, folder: str, name: str) -> DataFrame:
    df.write.mode("overwrite").parquet(f"{folder}/{name}")
    return df.sparkSession.read.parquet(f"{folder}/{name}")


#: Frames that runs of this thread have cached.
_own = threading.local()


def _cached(df: DataFrame) -> DataFrame:
    df = df.cache()
    df.count()
    _own.frames = [*getattr(_own, "frames", ()), df]
    return df


def free_cached() -> None:
    """Free the changes that this thread's states have cached; for when their times are taken."""
    for df in getattr(_own, "frames", ()):
        df.unpersist()
    _own.frames = []


def _banded(df: DataFrame, folder: str, key: tuple[str, ...]) -> Banded:
    T.write_banded(df, f"{folder}/stale", list(key), SALT, family=FAMILY)
    return Banded(df.sparkSession.read.parquet(f"{folder}/stale"), key, SALT, FAMILY)


def _order_split(spark: SparkSession, sf_dir: str, copies: int, frac: float) -> tuple[DataFrame, DataFrame, ChangeSet]:
    lines = copied(T.lines(spark, sf_dir), copies, "l_orderkey")
    orders = copied(T.load(spark, sf_dir, "orders"), copies, "o_orderkey", "o_custkey")
    split = lambda df, key: (df.filter(~below(split_hash(df, [key]), frac)), df.filter(below(split_hash(df, [key]), frac)))
    (old_l, new_l), (old_o, new_o) = split(lines, "l_orderkey"), split(orders, "o_orderkey")
    changes = ChangeSet({"lineitem": old_l, "orders": old_o}, {"lineitem": _cached(new_l), "orders": _cached(new_o)}, keys=T.KEYS, together=(frozenset({"lineitem", "orders"}),))
    return lines, orders, changes


def join_view_stored(spark: SparkSession, sf_dir: str, folder: str, copies: int = 1, frac: float = CHANGED) -> Stored:
    """The view of lines with their orders; whole orders enter. Sampled by the order, which filters both inputs."""
    _, _, c = _order_split(spark, sf_dir, copies, frac)
    on = (("l_orderkey", "o_orderkey"),)
    rows = lambda li, o: Join(Scan("lineitem", li, T.KEYS["lineitem"], "changes"), Scan("orders", o, T.KEYS["orders"], "changes"), on, "inner", "left")
    columns = tuple((x, x) for x in (*c.old["lineitem"].columns, *[x for x in c.old["orders"].columns if x != "o_orderkey"]))
    stale = _banded(Project(rows(c.old["lineitem"], c.old["orders"]), columns).lower(), folder, ("l_orderkey",))
    plan = spj_refresh(stale, Project(rows(c.inserted["lineitem"], c.inserted["orders"]), columns), None, ("l_orderkey", "l_seq"), "join_view")
    return Stored("join_view", stale, plan.lower, lambda m: push(KeyHash(plan, ("l_orderkey",), m, SALT, FAMILY))[0].lower(), folder)


def _view_stored(view: View, changes: ChangeSet, folder: str) -> Stored:
    stale = _banded(stale_plan(view, changes).lower(), folder, tuple(view.keys))
    return Stored(view.name, stale, lambda: refresh(view, stale, changes), lambda m: refresh_sample(view, stale, changes, m, SALT, family=FAMILY), folder)


def cube_stored(spark: SparkSession, sf_dir: str, folder: str, copies: int = 1, frac: float = CHANGED) -> Stored:
    """The fine base cube by customer, nation, region and part."""
    _, _, c = _order_split(spark, sf_dir, copies, frac)
    customers = _kept(copied(T.load(spark, sf_dir, "customer"), copies, "c_custkey"), folder, "customer")
    c.old |= {"customer": customers, "nation": T.load(spark, sf_dir, "nation"), "part": T.load(spark, sf_dir, "part")}
    return _view_stored(cube.view_of(cube.FINE), c, folder)


def log_stored(spark: SparkSession, sf_dir: str, folder: str, name: str, copies: int = 1, frac: float = CHANGED) -> Stored:
    """A log view over copies of the users; the last part by time is pending."""
    events = T.load(spark, sf_dir, "events")
    first, last = events.agg(F.min("ts"), F.max("ts")).first()
    many = copied(events, copies, "event_id", "user_id")
    cut = F.lit(first + (last - first) * (1 - frac)).cast(events.schema["ts"].dataType)
    changes = ChangeSet({"events": many.filter(F.col("ts") < cut)}, {"events": _cached(many.filter(F.col("ts") >= cut))}, keys=T.KEYS)
    return _view_stored(log_views.VIEWS[name], changes, folder)


def m_sweep(stored: Stored, ratios: tuple[float, ...] = (0.05, 0.1, 0.25, 0.5)) -> list[tuple[float, float, float]]:
    """(ratio, seconds of the full refresh, seconds of the sample's refresh)."""
    full = min(stored.publish(stored.full()) for _ in range(2))
    return [(m, full, min(stored.publish(stored.sample(m)) for _ in range(2))) for m in ratios]


def delta_sweep(make: Callable[[float], Stored], sizes: tuple[float, ...] = (0.025, 0.1, 0.2), m: float = RATIO) -> list[tuple[float, float, float]]:
    """(change size, seconds of the full refresh, seconds of the sample's refresh) of the states that ``make`` builds."""
    return [(size, *make(size).times(m)) for size in sizes]


def total_times(stored: Stored, q: AggQuery, m: float = RATIO) -> list[tuple[str, float, float]]:
    """(method, seconds of maintenance, seconds of one query) for a full refresh, the direct estimator and the correction."""
    spark = stored.stale.df.sparkSession
    full, part = stored.times(m)

    def query(df: DataFrame) -> float:
        best = None
        for _ in range(3):
            start = time.perf_counter()
            df.collect()
            best = min(best or 1e9, time.perf_counter() - start)
        return best

    stored.publish(stored.full())
    exact = query(answer_exact(spark.read.parquet(f"{stored.folder}/published"), q))
    stored.publish(stored.sample(m))
    fresh_s = spark.read.parquet(f"{stored.folder}/published")
    stale_s = stale_sample(stored.stale, stored.stale.key, m, SALT, FAMILY)
    direct, correction = query(direct_estimate(fresh_s, q, m)), query(correction_estimate(stored.stale.rows(), stale_s, fresh_s, q, m))
    return [("full", full, exact), ("direct", part, direct), ("correction", part, correction)]


def times_by_ratio(spark: SparkSession, sf_dir: str, folder: str, workload: str = "join_view", ratios: tuple[float, ...] = (0.05, 0.1, 0.25, 0.5)) -> DataFrame:
    make = {"join_view": join_view_stored, "cube": cube_stored}[workload]
    return spark.createDataFrame(m_sweep(make(spark, sf_dir, folder), ratios), "m double, full_s double, sample_s double")


def times_by_change(spark: SparkSession, sf_dir: str, folder: str, workload: str = "join_view", sizes: tuple[float, ...] = (0.025, 0.1, 0.2)) -> DataFrame:
    make = {"join_view": join_view_stored, "cube": cube_stored}[workload]
    return spark.createDataFrame(delta_sweep(lambda x: make(spark, sf_dir, folder, frac=x), sizes), "size double, full_s double, sample_s double")
