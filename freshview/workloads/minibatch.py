"""Mini-batch simulation over the log: throughput by batch size, and errors inside a refresh period."""

from __future__ import annotations

import math
import threading
import time
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.cleaning import stale_sample
from ..operators.estimate import AggQuery, correction_estimate
from ..operators.maintenance import refresh, refresh_sample, stale_plan
from ..operators.metrics import relative_error
from ..sources import tables as T
from ..sources.changes import ChangeSet
from .base import RATIO
from .log_views import VIEWS

LOG_VIEWS = ("l3", "l5")


def batches(events: DataFrame, size: int, start: float = 0.8) -> tuple[DataFrame, list[DataFrame]]:
    """The base part of the log and later events in batches of about ``size`` rows, by the range of their ids.

    Ids follow time, so no sort is needed; only two numbers reach the driver.
    """
    low, high = events.agg(F.min("event_id"), F.max("event_id")).first()
    cut = int(low + (high - low + 1) * start)
    base = events.filter(F.col("event_id") < cut)
    edges = [*range(cut, high + 1, size), high + 1]
    return base, [events.filter((F.col("event_id") >= a) & (F.col("event_id") < b)) for a, b in zip(edges, edges[1:])]


def refresh_seconds(spark: SparkSession, sf_dir: str, view: str, size: int, m: float | None = None, full: bool = True) -> dict[str, float]:
    """rows, seconds of a refresh over one batch, and samples made while it runs with their mean seconds.

    With ``m`` a second driver thread refreshes the sample over and over, in a pool of its
    own, until the refresh ends; ``full=False`` leaves the refresh out and makes one sample.
    The pools share the executors evenly where the session was started with
    ``spark.scheduler.mode`` FAIR; in the default mode the older job goes first.
    """
    base, rest = batches(T.load(spark, sf_dir, "events"), size)
    batch = rest[0].cache()
    rows = batch.count()
    v = VIEWS[view]
    c = ChangeSet({"events": base}, {"events": batch}, keys=T.KEYS)
    stale = stale_plan(v, c).lower().cache()
    stale.count()
    done, samples, seconds = threading.Event(), [], 0.0

    def timed(pool: str, df: DataFrame) -> float:
        spark.sparkContext.setLocalProperty("spark.scheduler.pool", pool)
        start = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        return time.perf_counter() - start

    def refresh_loop() -> float:
        try:
            return timed("refresh", refresh(v, stale, c)) if full else 0.0
        finally:
            done.set()

    def sample_loop() -> None:
        samples.append(timed("sample", refresh_sample(v, stale, c, m)))
        while not done.is_set():
            samples.append(timed("sample", refresh_sample(v, stale, c, m)))

    with ThreadPoolExecutor(2) as pool:
        work = [pool.submit(refresh_loop)] + ([pool.submit(sample_loop)] if m is not None else [])
        seconds = [w.result() for w in work][0]
    batch.unpersist()
    stale.unpersist()
    return {"rows": rows, "seconds": seconds, "samples": len(samples), "sample_s": sum(samples) / len(samples) if samples else 0.0}


def throughput(spark: SparkSession, sf_dir: str, shares: tuple[float, ...] = (0.01, 0.05, 0.2), views: tuple[str, ...] = LOG_VIEWS, m: float = RATIO) -> DataFrame:
    """Records a second of the refresh loop by view and batch size, alone and beside the sample loop."""
    total = T.load(spark, sf_dir, "events").count()
    rows = []
    refresh_seconds(spark, sf_dir, views[0], max(1, int(total * shares[0])), m)  # the first job also pays for loading classes
    for view in views:
        for share in shares:
            for loops in ("refresh", "both"):
                r = refresh_seconds(spark, sf_dir, view, max(1, int(total * share)), m if loops == "both" else None)
                rows.append((view, loops, r["rows"], r["seconds"], r["rows"] / r["seconds"], r["samples"], r["sample_s"]))
    return spark.createDataFrame(rows, "view string, loops string, batch_rows long, seconds double, records_per_s double, samples int, sample_s double")


def smallest_batch(rates: DataFrame, target: float | None = None) -> DataFrame:
    """Smallest batch that reaches a target rate, by view and loops; null where none does.

    Without a target it is half of the best rate that the refresh loop reaches alone, which
    small batches miss.
    """
    alone = F.max(F.when(F.col("loops") == "refresh", F.col("records_per_s")))
    goal = rates.groupBy("view").agg((alone / 2 if target is None else F.lit(float(target))).alias("target"))
    hit = F.when(F.col("records_per_s") >= F.col("target"), F.col("batch_rows"))
    return rates.join(goal, "view").groupBy("view", "loops", "target").agg(F.min(hit).alias("batch_rows"))


def measured_lags(spark: SparkSession, sf_dir: str, ratios: tuple[float, ...], ticks: int, view: str) -> dict[float, float]:
    """Ticks that a sample of each ratio takes beside a refresh, when a period is as long as one refresh."""
    size = max(1, int(T.load(spark, sf_dir, "events").count() * 0.2))
    period = refresh_seconds(spark, sf_dir, view, size)["seconds"]
    return {m: refresh_seconds(spark, sf_dir, view, size, m)["sample_s"] / (period / ticks) for m in ratios}


def period_errors(spark: SparkSession, sf_dir: str, ratios: tuple[float, ...] = (0.02, 0.05, 0.1), ticks: int = 4, view: str = "l3", cost: float | None = None) -> DataFrame:
    """Largest error inside a refresh period without and with the sample loop, by sampling ratio, and the best ratio.

    Changes arrive in ``ticks`` equal parts and the view is refreshed after the last. A
    sample takes some ticks, measured beside a refresh, or ``m * cost`` where a cost is
    given; between samples the correction of the last one is in use.
    """
    v, q = VIEWS[view], AggQuery("sum", "total")
    events = T.load(spark, sf_dir, "events")
    low, high = events.agg(F.min("event_id"), F.max("event_id")).first()
    step = max(1, math.ceil((high - low + 1) * 0.2 / ticks))
    base, rest = batches(events, step)
    lags = {m: m * cost for m in ratios} if cost is not None else measured_lags(spark, sf_dir, ratios, ticks, view)
    out = None
    for m in ratios:
        lag = max(1, math.ceil(lags[m]))
        for t in range(1, ticks + 1):
            seen = t - t % lag if lag <= t else 0
            truth = stale_plan(v, ChangeSet({"events": events.filter(F.col("event_id") <= low + (high - low + 1) * 0.8 + step * t)}, keys=T.KEYS)).lower().agg(q.value().alias("truth"))
            c = ChangeSet.from_batches("events", base, rest[:seen] or [base.limit(0)], T.KEYS["events"])
            c.keys = T.KEYS
            stale = stale_plan(v, c).lower()
            answer = correction_estimate(stale, stale_sample(stale, v.keys, m), refresh_sample(v, stale, c, m), q, m, "with_sample")
            row = truth.crossJoin(answer).crossJoin(stale.agg(q.value().alias("refresh_only")))
            row = row.select(F.lit(m).alias("m"), F.lit(lag).alias("lag"), F.lit(t).alias("tick"), relative_error(F.col("refresh_only"), F.col("truth")).alias("e1"), relative_error(F.col("with_sample"), F.col("truth")).alias("e2"))
            out = row if out is None else out.unionByName(row)
    worst = out.groupBy("m", "lag").agg(F.max("e1").alias("max_error_refresh_only"), F.max("e2").alias("max_error_with_sample"))
    gain = F.try_divide(F.col("max_error_refresh_only"), F.col("max_error_with_sample"))
    best = worst.agg(F.min_by("m", "max_error_with_sample").alias("best"))
    return worst.crossJoin(F.broadcast(best)).select("*", gain.alias("gain"), (F.col("m") == F.col("best")).alias("is_best")).drop("best")


def _task_seconds(spark: SparkSession) -> float:
    """Seconds spent in tasks on all executors since the application began."""
    executors = spark.sparkContext._jsc.sc().statusStore().executorList(True)
    return sum(executors.apply(i).totalDuration() for i in range(executors.size())) / 1000


def cpu_utilisation(spark: SparkSession, work, cores: int | None = None) -> float:
    """Share of all executor cores' time that is spent in tasks while ``work`` runs."""
    before, start = _task_seconds(spark), time.perf_counter()
    work()
    wall = time.perf_counter() - start
    time.sleep(0.2)  # task ends reach the status store a little later
    return (_task_seconds(spark) - before) / (wall * (cores or spark.sparkContext.defaultParallelism))


def utilisation(spark: SparkSession, sf_dir: str, view: str = "l3", m: float = RATIO) -> DataFrame:
    """CPU use of the refresh loop alone and with the sample loop beside it."""
    size = max(1, T.load(spark, sf_dir, "events").count() // 5)
    rows = [(loops, cpu_utilisation(spark, lambda r=ratio: refresh_seconds(spark, sf_dir, view, size, r))) for loops, ratio in (("refresh", None), ("both", m))]
    return spark.createDataFrame(rows, "loops string, cpu_share double")
