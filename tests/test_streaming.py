from freshview.catalog import ViewManager, answer
from freshview.functions.hashing import Banded, key_hash_filter
from freshview.operators import cleaning
from freshview.operators.estimate import AggQuery
from freshview.operators.maintenance import refresh_sample, stale_plan
from freshview.sources import tables as T
from freshview.sources.changes import ChangeSet
from freshview.streaming import loops
from freshview.workloads import demand, log_views, timing
from pyspark.sql import functions as F

D = "/root/testdata/sf0.001"


def split_log(spark, tmp_path):
    events = T.load(spark, D, "events")
    base = events.filter("event_id < 800")
    for i in range(4):
        events.filter(f"event_id >= {800 + 50 * i} and event_id < {850 + 50 * i}").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    return events, base


def test_sample_loop_equals_batch(spark, tmp_path):
    events, base = split_log(spark, tmp_path)
    view = log_views.VIEWS["l3"]
    manager = ViewManager(spark, str(tmp_path / "views"))
    manager.register(view, ChangeSet({"events": base}, keys={"events": ("event_id",)}), 0.3)
    loop = loops.FreshSampleLoop(manager, "l3", "events", base, str(tmp_path / "log"))
    for _ in range(2):  # the second start finds nothing new in the checkpoint
        loop.start(T.stream(spark, str(tmp_path / "in"), events.schema), str(tmp_path / "check")).awaitTermination()
    whole = stale_plan(view, ChangeSet({"events": events}, keys={"events": ("event_id",)})).lower()
    want = key_hash_filter(whole, list(view.keys), 0.3)
    stale_s, fresh_s = manager.samples("l3")
    fresh_s = fresh_s.select(*want.columns)
    assert want.exceptAll(fresh_s).isEmpty() and fresh_s.exceptAll(want).isEmpty()
    assert manager.describe().first().epoch == 1
    truth = whole.agg(F.sum("total")).first()[0]
    r = answer(manager, "l3", AggQuery("sum", "total")).first()
    assert r.method == "correction" and abs(r.estimate - float(truth)) / float(truth) < 0.1
    assert answer(manager, "l3", AggQuery("median", "total")).first().epoch == 1
    manager.refresh("l3", new_salt="s9")
    now = manager.current("l3").select(*whole.columns)
    assert now.exceptAll(whole).isEmpty() and manager.entries["l3"].epoch == 2
    manager.expose("l3")
    assert spark.sql("select count(*) from l3_stale_sample").first()[0] < whole.count()
    manager.drop("l3")


def test_refresh_loop_with_sample_loop(spark, tmp_path):
    events, base = split_log(spark, tmp_path)
    view = log_views.VIEWS["l1"]
    manager = ViewManager(spark, str(tmp_path / "views"))
    manager.register(view, ChangeSet({"events": base}, keys={"events": ("event_id",)}), 0.4)
    loop = loops.RefreshLoop(manager, "l1", "events", base, str(tmp_path / "log"), every=2)
    loop.start(T.stream(spark, str(tmp_path / "in"), events.schema), str(tmp_path / "check")).awaitTermination()
    whole = stale_plan(view, ChangeSet({"events": events}, keys={"events": ("event_id",)})).lower()
    assert manager.current("l1").select(*whole.columns).exceptAll(whole).isEmpty()
    assert (manager.entries["l1"].epoch, manager.entries["l1"].applied) == (3, 3)
    more = events.filter("event_id < 30").withColumn("event_id", F.col("event_id") + 5000)
    sampler = loops.FreshSampleLoop(manager, "l1", "events", base, str(tmp_path / "log"))
    sampler.on_batch(more, 4)
    both = stale_plan(view, ChangeSet({"events": events.unionByName(more)}, keys={"events": ("event_id",)})).lower()
    want = key_hash_filter(both, list(view.keys), 0.4)
    assert manager.samples("l1")[1].select(*want.columns).exceptAll(want).isEmpty()


def test_windows_and_sampled_state(spark, tmp_path):
    events, _ = split_log(spark, tmp_path)

    def run(df, name, mode):
        q = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.table(name)

    source = lambda: T.stream(spark, str(tmp_path / "in"), events.schema, 10).withColumn("ts", F.col("ts").cast("timestamp"))
    late = events.filter("event_id >= 800")
    got = run(loops.sampled_counts(source(), 0.5), "sampled", "complete")
    want = key_hash_filter(late, ["user_id"], 0.5).groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()
    assert run(loops.tumbling(source()), "tumbling", "update").agg(F.sum("n")).first()[0] >= late.count()
    assert run(loops.distinct_events(source()), "distinct_events", "append").count() == late.count()
    assert run(loops.sliding(source()), "sliding", "update").count() > 0 and run(loops.sessions(source()), "sessions", "append").count() >= 0


def test_eager_and_thresholds(spark, tmp_path):
    c = demand.changes(spark, D)
    manager = ViewManager(spark, str(tmp_path / "views"))
    manager.register(demand.PLAIN, c, 0.2)
    manager.apply("demand_plain", c, mode="eager")
    fresh = stale_plan(demand.PLAIN, ChangeSet({"lineitem": c.new("lineitem")}, keys=c.keys)).lower()
    assert manager.current("demand_plain").select(*fresh.columns).exceptAll(fresh).isEmpty()
    assert manager.retune_outliers("demand_plain", c.old["lineitem"], "l_extendedprice", k=10) > 0


def _partition_filters(df):
    plan = df._jdf.queryExecution().executedPlan().toString()
    return [line for line in plan.split("\n") if "FileScan" in line and "/root/testdata" not in line]


def test_samples_read_bands_only(spark, tmp_path):
    """Every scan of the stored view under a sample is bound by hash band; a restarted manager goes on."""
    d = "/root/testdata/sf0.001"
    s = demand.build(spark, d)
    manager = ViewManager(spark, str(tmp_path / "views"))
    manager.register(demand.PLAIN, s.changes, 0.1)
    stale_s, _ = manager.samples("demand_plain")
    fresh_s = refresh_sample(demand.PLAIN, manager.stored("demand_plain"), s.changes, 0.1)
    for df in (stale_s, fresh_s):
        scans = _partition_filters(df)
        assert scans and all("hash_band" in x.split("PartitionFilters: ")[1].split("]")[0] and "<= 25" in x for x in scans), scans
    assert fresh_s.exceptAll(s.fresh_s.select(*fresh_s.columns)).isEmpty() and s.fresh_s.select(*fresh_s.columns).exceptAll(fresh_s).isEmpty()
    manager.apply("demand_plain", s.changes)
    again = ViewManager(spark, str(tmp_path / "views"))
    again.load(demand.PLAIN)
    old, new = manager.entries["demand_plain"], again.entries["demand_plain"]
    assert (old.version, old.sample_version, old.epoch, old.pointer, old.m, old.salt) == (new.version, new.sample_version, new.epoch, new.pointer, new.m, new.salt)
    new.pending = [s.changes]
    again.refresh("demand_plain")
    fresh = s.fresh.select("l_partkey", "n", "v")
    assert again.current("demand_plain").select("l_partkey", "n", "v").exceptAll(fresh).isEmpty()
    # a pointer that was not finished is not read
    (tmp_path / "views" / "demand_plain" / "pointer" / "n=99").mkdir()
    manager.load(demand.PLAIN)
    assert manager.entries["demand_plain"].version == again.entries["demand_plain"].version


def test_refresh_then_sample_refreshes_all(spark):
    s = demand.build(spark, "/root/testdata/sf0.001")
    plan = cleaning.refresh_then_sample(demand.PLAIN, s.stale, s.changes, 0.1)._jdf.queryExecution().optimizedPlan().toString()
    filters = [line for line in plan.split("\n") if "s1|" in line]
    assert len(filters) == 1 and "__row" in filters[0]


def test_other_families_band_alike(spark, tmp_path):
    from freshview.sources.tables import write_banded

    df = spark.range(5000).withColumnRenamed("id", "k")
    for family in ("md5", "xxhash64"):
        write_banded(df, str(tmp_path / family), ["k"], "s1", family=family, parts=2)
        stored = Banded(spark.read.parquet(str(tmp_path / family)), ("k",), "s1", family)
        for m in (0.01, 0.1, 0.5):
            want = {r.k for r in key_hash_filter(df, ["k"], m, "s1", family).collect()}
            assert {r.k for r in stored.sample(("k",), m, "s1", family).collect()} == want
            assert {r.k for r in stored.sample(("k",), m, "s2", family).collect()} == {r.k for r in key_hash_filter(df, ["k"], m, "s2", family).collect()}


def test_stored_workloads(spark, tmp_path):
    """The timed refreshes publish the same rows as a plain recomputation."""
    d = "/root/testdata/sf0.001"
    for make in (timing.join_view_stored, timing.cube_stored, lambda s, x, f: timing.log_stored(s, x, f, "l3")):
        stored = make(spark, d, str(tmp_path))
        full, part = stored.full(), stored.sample(0.25)
        want = Banded(full, stored.stale.key, "s1", timing.FAMILY).df
        want = key_hash_filter(want, list(stored.stale.key), 0.25, "s1", timing.FAMILY)
        assert 0 < part.count() < full.count()
        assert part.select(*want.columns).exceptAll(want).isEmpty() and want.exceptAll(part.select(*want.columns)).isEmpty()
        assert timing.m_sweep(stored, (0.1,))[0][2] > 0
    lines = spark.read.parquet(f"{d}/lineitem.parquet").count()
    assert timing.join_view_stored(spark, d, str(tmp_path), copies=2).full().count() == 2 * lines
