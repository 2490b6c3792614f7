"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Times of demand and of orders are wall clock of computing every row (no sink) with the
inputs of a refresh cached first; those of the join view, the cube and the log views read
the stale view as stored by hash band and write what the refresh publishes. Loading of
changes is not counted. Beside seconds it reports the ratios
that the published numbers are about: refresh against refresh-sample, and median errors.
"""

from __future__ import annotations

import json
import os
import shutil
import tempfile
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from freshview.operators.estimate import AggQuery, answer_exact, correction_estimate, direct_estimate
from freshview.operators.maintenance import refresh, refresh_plan, refresh_sample, stale_plan
from freshview.operators.metrics import error_summary, timed, work_report
from freshview.operators.views import View
from freshview.sources import tables as T
from freshview.sources.changes import ChangeSet
from freshview.workloads import cube, demand, join_view, log_views, outlier_sweep, timing

M = 0.1


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    out: dict[str, float] = {}
    extra: dict[str, float] = {}

    def run(name: str, df, times: int = 2) -> float:
        out[name] = round(min(timed(df) for _ in range(times)), 3)
        return out[name]

    def cached(df):
        df = df.cache()
        df.count()
        return df

    # demand per part: full refresh, refresh of the sample, query times
    s = demand.build(spark, sf_dir, M)
    stale = cached(s.stale)
    for t, f in list(s.changes.inserted.items()):
        s.changes.inserted[t] = cached(f)
    for t, f in list(s.changes.deleted.items()):
        s.changes.deleted[t] = cached(f)
    full = run("demand_full_refresh", refresh(demand.PLAIN, stale, s.changes), 3)
    part = run("demand_refresh_sample", refresh_sample(demand.PLAIN, stale, s.changes, M), 3)
    extra["demand_speedup"] = full / part
    work = work_report(refresh_plan(demand.PLAIN, stale, s.changes), M, demand.PLAIN.keys).agg((F.sum("rows") / F.sum("kept")).alias("x")).first()
    extra["demand_rows_ratio"] = work["x"]
    fresh, stale_s, fresh_s = cached(s.fresh), cached(s.stale_s), cached(s.fresh_s)
    q = AggQuery("sum", "v")
    run("query_exact", answer_exact(fresh, q), 3)
    run("query_direct", direct_estimate(fresh_s, q, M), 3)
    run("query_correction", correction_estimate(stale, stale_s, fresh_s, q, M), 3)

    # join view, fine base cube and log views: stored by hash band, refreshed and published, on copies under shifted keys
    copies = {"join_view": 16, "cube": 8, "log_l1": 60, "log_l3": 60} | {k: int(v) for k, v in (x.split("=") for x in os.environ.get("BENCH_COPIES_OF", "").split(",") if x)}
    with tempfile.TemporaryDirectory() as folder:
        make = {
            "join_view": lambda n: timing.join_view_stored(spark, sf_dir, f"{folder}/join_view", n),
            "cube": lambda n: timing.cube_stored(spark, sf_dir, f"{folder}/cube", n),
            "log_l1": lambda n: timing.log_stored(spark, sf_dir, f"{folder}/l1", "l1", n),
            "log_l3": lambda n: timing.log_stored(spark, sf_dir, f"{folder}/l3", "l3", n),
        }
        for name, n in copies.items():
            stored = make[name](n)
            extra[f"{name}_rows"] = stored.stale.df.count()
            ratios = (0.05, M, 0.25) if name in ("join_view", "cube") else (M,)
            for m, full, part in timing.m_sweep(stored, ratios):
                suffix = "" if m == M else f"_m{m}"
                out[f"{name}_refresh_sample{suffix}"] = round(part, 3)
                extra[f"{name}_speedup{suffix}"] = full / part
            out[f"{name}_full_refresh"] = round(full, 3)
            spark.catalog.clearCache()
            shutil.rmtree(f"{folder}/{name.removeprefix('log_')}", ignore_errors=True)

    # accuracy: all templates over 4 draws, all roll-ups of the base cube (those without customers apart), all log views
    gains: dict[str, list[float]] = {}
    start = time.perf_counter()
    for r in join_view.accuracy(spark, sf_dir, M, n=4).collect():
        gains.setdefault(r["query_id"], {})[r["method"]] = r["median"]
    out["join_view_accuracy"] = round(time.perf_counter() - start, 3)
    for other in ("stale", "direct"):
        rates = [g[other] / g["correction"] for g in gains.values() if g[other] is not None and g["correction"]]
        extra[f"join_view_gain_over_{other}"] = sum(rates) / len(rates)
        extra[f"join_view_median_gain_over_{other}"] = sorted(rates)[len(rates) // 2]
    start = time.perf_counter()
    errors = cached(cube.rollups(cube.build(spark, sf_dir, M), "sum"))
    for what, rows in (("cube", errors), ("cube_coarse", errors.filter("query_id not like '%o_custkey%'"))):
        for r in error_summary(rows).collect():
            extra[f"{what}_{r['method']}_median_error"], extra[f"{what}_{r['method']}_max_error"] = r["median"], r["worst"]
    out["cube_rollups"] = round(time.perf_counter() - start, 3)
    start = time.perf_counter()
    means = [r["mean"] for r in log_views.accuracy(spark, sf_dir, M).collect() if r["method"] == "correction"]
    extra["log_views_mean_error"] = sum(means) / len(means)
    out["log_accuracy"] = round(time.perf_counter() - start, 3)

    # a view with many groups on copies of the lines, so that fixed costs do not hide the ratio
    copies = int(os.environ.get("BENCH_COPIES", "20"))
    many = T.lines(spark, sf_dir).crossJoin(spark.range(copies)).withColumn("l_orderkey", F.col("l_orderkey") + F.col("id") * 100_000_000).select("l_orderkey", "l_seq", "l_extendedprice")
    orders = View("order_revenue", ("l_orderkey",), (("rev", demand.PRICE), ("n", "1")), lambda leaf: leaf["lineitem"], ("lineitem",))
    changes = ChangeSet.from_split({"lineitem": many}, T.KEYS, {"lineitem": (M, 0.0)})
    many_stale = cached(stale_plan(orders, changes).lower())
    changes.inserted["lineitem"] = cached(changes.inserted["lineitem"])
    full = run(f"orders_x{copies}_full_refresh", refresh(orders, many_stale, changes), 3)
    for family in ("md5", "xxhash64"):
        part = run(f"orders_x{copies}_refresh_sample_{family}", refresh_sample(orders, many_stale, changes, M, family=family), 3)
        extra[f"orders_x{copies}_speedup_{family}"] = full / part
    extra[f"orders_x{copies}_groups"] = many_stale.count()
    spark.catalog.clearCache()

    # outlier set at the strongest skew: 75 % quantile over salts and random queries
    start = time.perf_counter()
    for r in outlier_sweep.z_sweep(spark, sf_dir, (4,), names=("v3", "v15")).collect():
        extra |= {f"outlier_{r['view']}_z4_{k}": r[k] for k in r.asDict() if k.startswith(("q75", "gain"))}
    out["outlier_z4"] = round(time.perf_counter() - start, 3)

    print(json.dumps({"metric": "headline_queries_total", "value": round(sum(out.values()), 3), "unit": "sec", "queries": out, "sf": os.path.basename(sf_dir.rstrip("/")), "ratios": {k: round(v, 5) if v is not None else None for k, v in extra.items()}}))
    spark.stop()


if __name__ == "__main__":
    main()
