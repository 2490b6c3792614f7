"""Plans that change at run time, flags instead of frames, scratch folders, and queries that must read their tables."""

from concurrent.futures import ThreadPoolExecutor
from pathlib import Path

import duckdb
import pytest
from freshview import registry
from freshview.operators import outliers
from freshview.operators.estimate import AggQuery, answers_many
from freshview.workloads import complex_views, join_view

D = "/root/testdata/sf0.001"


def duck():
    con = duckdb.connect()
    for t in registry.T.KEYS:
        con.execute(f"create view {t} as select * from '{D}/{t}.parquet'")
    return con


@pytest.fixture()
def late_broadcast(spark):
    """Joins are planned as sort-merge joins and become broadcast joins at run time, as they do on larger tables."""
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    spark.conf.set("spark.sql.adaptive.autoBroadcastJoinThreshold", "10m")
    yield
    spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.unset("spark.sql.adaptive.autoBroadcastJoinThreshold")


@pytest.mark.parametrize("name", ["o13_direct_with_outliers", "o14_correction_with_outliers", "o16_interval_with_outliers"])
def test_outlier_queries_survive_a_late_broadcast(spark, late_broadcast, name):
    got = registry.queries()[name](spark, D).first()
    cursor = duck().execute(registry.oracle_sql()[name])
    want = dict(zip([c[0] for c in cursor.description], cursor.fetchone()))
    assert {c: round(got[c], 1) for c in got.asDict()} == {c: round(v, 1) for c, v in want.items()}


def scans(df, table: str) -> int:
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    return plan.count({"lineitem": "l_extendedprice#", "orders": "o_orderpriority#"}[table]) and sum("Relation [" in line and table[0] + "_orderkey#" in line for line in plan.splitlines())


def test_interval_with_outliers_reads_each_frame_once(spark):
    """Twenty scans of the lines and thirteen joins before, six of them for the set."""
    df = registry.queries()["o16_interval_with_outliers"](spark, D)
    assert scans(df, "lineitem") == 6
    assert df._jdf.queryExecution().optimizedPlan().toString().count("Join ") == 1


@pytest.mark.parametrize("q", [AggQuery("sum", "x", "x < 900"), AggQuery("count", "1", "x > 2")])
def test_interval_with_outliers_equals_sums_by_hand(spark, q):
    """Keys that come, go or are null in one frame; outliers that are old, new or sampled."""
    stale = {1: 5.0, 2: 3.0, 3: None, 4: 700.0, 5: 2.0, 6: 8.0}
    fresh = {1: 6.0, 2: 3.0, 3: 4.0, 4: 800.0, 6: 9.0, 7: 1.0, 8: 950.0, 9: 600.0}
    kept, out, m = {1, 3, 4, 5, 6, 7, 8}, {4, 8, 9}, 0.5
    frame = lambda d, ids: spark.createDataFrame([(i, x) for i, x in d.items() if i in ids], "id long, x double")
    every = set(stale) | set(fresh)
    got = outliers.interval_with_outliers(frame(stale, every), frame(stale, kept), frame(fresh, kept), frame(fresh, out), q, m, ("id",)).first()

    def amount(d, i):
        x = d.get(i)
        if q.agg == "count":
            return float(x is not None and x > 2)
        return x if x is not None and x < 900 else 0.0

    drift = {i: (amount(fresh, i) - amount(stale, i)) / m for i in kept - out}
    want = sum(amount(stale, i) for i in stale) + sum(drift.values()) + sum(amount(fresh, i) - amount(stale, i) for i in out)
    width = 1.96 * (0.5 * sum(d * d for d in drift.values())) ** 0.5
    assert tuple(got) == pytest.approx((want, width, want - width, want + width))


def test_sweep_reads_the_lines_once(spark):
    """Once for every change size and frame before, so the disk held a shuffle of all lines for each."""
    df = join_view.delta_sweep(spark, D)
    assert scans(df, "lineitem") == 1 and df.count() == 7


def test_accuracy_reads_the_lines_once_and_answers_as_refreshed_frames_do(spark):
    assert scans(join_view.accuracy(spark, D), "lineitem") == 1
    table = spark.createDataFrame(join_view.draws(0, 3), join_view.DRAW)
    columns = {c: c for c in table.columns}
    kind = lambda rows: {(r.draw, r.query_id, r.group_key): [None if v is None else round(v, 4) for v in (r.truth, r.stale, r.direct, r.correction)] for r in rows.collect()}
    want = {}
    for sample_on, names in (("full", [x for x in join_view.TEMPLATES if x != "j18"]), ("prefix", ["j18"])):
        f = {k: join_view.with_helpers(join_view.wide(df, spark, D), sample_on == "prefix") for k, df in join_view.frames(spark, D, sample_on=sample_on).items()}
        want |= kind(answers_many(f["stale"], f["fresh"], f["stale_s"], f["fresh_s"], [(x, join_view.query(x, columns)) for x in names], 0.1, table))
    assert kind(join_view.run(spark, D, n=3)) == want and {q for _, q, _ in want} == set(join_view.TEMPLATES)


@pytest.mark.parametrize("name", ["w1_time_by_ratio", "w4_time_by_ratio"])
def test_timing_queries_run_beside_each_other(spark, tmp_path, name):
    """A folder that a second run shares was emptied under the first one."""
    before = set(spark.sparkContext._jsc.getPersistentRDDs().keySet())
    with ThreadPoolExecutor(2) as pool:
        runs = [pool.submit(registry.queries()[n], spark, D) for n in (name, name.replace("ratio", "change"))]
        assert [r.result().count() for r in runs] == [4, 3]
    store = Path(spark.conf.get("spark.sql.warehouse.dir").removeprefix("file:")) / "freshview_timing"
    assert not list(store.glob("*-*")) and set(spark.sparkContext._jsc.getPersistentRDDs().keySet()) <= before


def test_complex_views_are_answered_from_one_read_as_their_refreshed_frames_are(spark):
    """Four frames of each view were built apart, each with its own joins."""
    assert scans(complex_views.run(spark, D, "v10"), "lineitem") == 1
    kind = lambda df: {(r.draw, r.query_id): [None if v is None else round(v, 4) for v in (r.truth, r.stale, r.direct, r.correction)] for r in df.collect()}
    draws = spark.createDataFrame(complex_views.predicates(4), "draw int, low string, high string")
    for name in ("v4", "v5", "v13", "v18"):
        digits = f"substr(md5('q|' || cast({complex_views.key_of(name)[0]} as string)), 1, 2)"
        asked = [(agg, AggQuery(agg, complex_views.MEASURES[name], f"{digits} >= low and {digits} < high")) for agg in ("sum", "avg", "count")]
        f = complex_views.frames(spark, D, name)
        assert kind(complex_views.run(spark, D, name, n=4)) == kind(answers_many(f["stale"], f["fresh"], f["stale_s"], f["fresh_s"], asked, 0.1, draws)), name


def test_key_rules_read_their_tables(spark):
    df = registry.queries()["k2_key_rules"](spark, D)
    assert "Relation" in df._jdf.queryExecution().optimizedPlan().toString()
    cursor = duck().execute(registry.oracle_sql()["k2_key_rules"])
    assert [c[0] for c in cursor.description] == df.columns
    rows = sorted(map(tuple, df.collect()))
    assert rows == sorted(cursor.fetchall()) and all(n == keys for *_, n, keys in rows)


def test_verdicts_read_their_tables(spark):
    rows = {r.view: r for r in complex_views.verdicts(spark, D).collect()}
    lines, orders, customers = (spark.read.parquet(f"{D}/{t}.parquet").count() for t in ("lineitem", "orders", "customer"))
    assert rows["v3"].rows == lines + orders + customers and rows["v3"].kept < rows["v3"].rows
    assert rows["v9"].outcome == "blocked" and rows["v9"].kept == rows["v9"].rows == lines + orders
    assert rows["v1"].rows is None and len(rows) == 23


def test_accuracy_compiles_every_method(spark):
    """The JVM interprets methods of more than 8000 bytecodes; the one that made a line's cells had far more."""
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        code = join_view.accuracy(spark, D)._jdf.queryExecution().debug().codegenToSeq()
        sizes = [code.apply(i)._3().maxMethodCodeSize() for i in range(code.size())]
    finally:
        spark.conf.unset("spark.sql.adaptive.enabled")
    assert sizes and max(sizes) < 8000


def test_accuracy_numbers_lines_without_part_or_supplier(spark, tmp_path):
    """They count in a line's number, as in the SQL, and nowhere else."""
    for t in registry.T.KEYS:
        df = spark.read.parquet(f"{D}/{t}.parquet")
        df.filter({"part": "p_partkey % 7 <> 1", "supplier": "s_suppkey <> 2", "customer": "c_custkey % 9 <> 1"}.get(t, "true")).write.parquet(f"{tmp_path}/{t}.parquet")
    con = duckdb.connect()
    for t in registry.T.KEYS:
        con.execute(f"create view {t} as select * from '{tmp_path}/{t}.parquet/*.parquet'")
    got = registry.queries()["w1_accuracy"](spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == sorted(con.execute(registry.oracle_sql()["w1_accuracy"]).fetchall())
