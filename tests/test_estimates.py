import pytest
from freshview.functions import hashing as H
from freshview.operators import bootstrap, cleaning, estimate, intervals, maintenance, metrics, outliers, staleness
from freshview.operators.estimate import AggQuery, UnsupportedEstimate
from freshview.plans.nodes import Difference, Scan
from freshview.workloads import base, demand, outlier_sweep
from pyspark.sql import functions as F

D = "/root/testdata/sf0.01"
KEY = ("l_partkey",)


@pytest.fixture(scope="module")
def state(spark):
    s = demand.build(spark, D)
    for name in ("stale", "fresh", "stale_s", "fresh_s"):
        setattr(s, name, getattr(s, name).cache())
    return s


def test_golden_numbers(state):
    """Counts and sums that were computed apart from this code."""
    got = {n: tuple(getattr(state, n).agg(F.count(F.lit(1)), F.sum("n"), F.sum("v"), F.count_if(F.col("n") > 32)).first()) for n in ("stale", "fresh", "stale_s", "fresh_s")}
    assert [(a, b, str(c), d) for a, b, c, d in got.values()] == [(2000, 53935, "2866076882.62", 292), (2000, 58775, "3119399795.38", 544), (193, 5157, "274557809.75", 25), (193, 5622, "299459722.71", 47)]
    a = state.answers(AggQuery("sum", "v")).first()
    assert (round(a.direct, 2), round(a.correction, 2)) == (2994597227.10, 3115096012.22)
    assert [state.answers(AggQuery("count", "1", "n > 32")).first()[i] for i in range(4)] == [544, 292, 470, 512]
    assert {r["class"]: r.n for r in staleness.staleness_profile(state.stale, state.fresh, KEY).collect()} == {"incorrect": 1950, "unchanged": 50}


def test_worked_arithmetic(spark):
    """Stale answer 45, four hits in the fresh and two in the stale 5 % sample: 80 directly, 85 corrected."""
    stale = spark.range(45).select("id", F.lit(200).alias("n"))
    fresh_s, stale_s = stale.limit(4), stale.limit(2)
    q = AggQuery("count", "1", "n > 100")
    assert estimate.direct_estimate(fresh_s, q, 0.05).first()[0] == 80
    assert estimate.drift_estimate(stale_s, fresh_s, q, 0.05).first()[0] == 40
    assert estimate.correction_estimate(stale, stale_s, fresh_s, q, 0.05).first()[0] == 85


def test_strategies_agree(spark, state):
    for strategy in ("change_table", "recompute"):
        other = maintenance.refresh_sample(demand.PLAIN, state.stale, state.changes, 0.1, strategy=strategy).select(*state.fresh_s.columns)
        assert other.exceptAll(state.fresh_s).isEmpty() and state.fresh_s.exceptAll(other).isEmpty()
    whole = H.key_hash_filter(state.fresh, list(KEY), 0.1).select(*state.fresh_s.columns)
    assert whole.exceptAll(state.fresh_s).isEmpty()
    rows = {r.clause: r for r in cleaning.check_correspondence(state.stale, state.fresh, state.stale_s, state.fresh_s, KEY, 0.1).collect()}
    assert rows["superfluous"].violations == rows["preserved"].violations == 0
    naive = cleaning.naive_row_sample_refresh(demand.PLAIN, state.stale_s, state.changes, 0.1).agg(F.sum("n")).first()[0]
    assert naive != state.fresh_s.agg(F.sum("n")).first()[0]


def test_edges(spark, state):
    """Ratio 1 gives the exact answer with no width; no changes leave the stale answer."""
    q = AggQuery("sum", "v")
    r = intervals.correction_interval(state.stale, state.stale, state.fresh, q, 1.0, KEY).first()
    assert abs(r.estimate - state.fresh.agg(F.sum("v")).first()[0].__float__()) < 1 and r.half_width == 0
    assert estimate.correction_estimate(state.stale, state.stale_s, state.stale_s, q, 0.1).first()[0] == float(state.stale.agg(F.sum("v")).first()[0])
    with pytest.raises(UnsupportedEstimate):
        AggQuery("count_distinct", "v")
    c = demand.changes(spark, D, 0.0, 0.0)
    assert not c.is_stale() and demand.changes(spark, D).is_stale()
    with pytest.raises(ValueError):
        base.split_hash(state.stale, list(KEY), H.SALT)
    with pytest.raises(TypeError):
        H.key_hash_filter(spark.sql("select 1.5D as x"), "x", 0.5)


def test_coverage_and_bias(state):
    rows = intervals.coverage_trial(state.stale, state.fresh, AggQuery("sum", "v"), 0.1, KEY, [f"t{i}" for i in range(200)]).toPandas()
    for m in ("direct", "correction"):
        assert 0.90 <= rows[f"{m}_covers"].mean() <= 0.99
        assert abs(rows[m].mean() - rows["truth"][0]) < 3.5 * rows[m].std() / 200**0.5
    error = {m: (abs(rows[m] - rows["truth"]) / rows["truth"]).mean() for m in ("stale", "direct", "correction")}
    assert error["correction"] < error["direct"] < error["stale"]


def test_choice_flips(spark):
    """When most of the base has gone, the stale sample says little about the fresh one."""
    choices = []
    for inserted, deleted in ((0.05, 0.0), (0.0, 0.8)):
        s = base.state_of(demand.PLAIN, base.line_changes(spark, D, inserted, deleted), 0.3)
        choices.append(estimate.choose_estimator(s.stale_s, s.fresh_s, AggQuery("sum", "v"), 0.3, KEY).first().choice)
    assert choices == ["correction", "direct"]


def test_bootstrap(state):
    q = AggQuery("sum", "v")
    exact = intervals.correction_interval(state.stale, state.stale_s, state.fresh_s, q, 0.1, KEY).first()
    paired = bootstrap.bootstrap_correction(state.stale, state.stale_s, state.fresh_s, q, 0.1, KEY).first()
    loose = bootstrap.bootstrap_correction(state.stale, state.stale_s, state.fresh_s, q, 0.1, KEY, paired=False).first()
    assert 0.5 < (paired.high - paired.low) / (exact.high - exact.low) < 2
    assert loose.high - loose.low > paired.high - paired.low
    median = bootstrap.bootstrap_correction(state.stale, state.stale_s, state.fresh_s, AggQuery("median", "v"), 0.1, KEY).first()
    assert median.low <= median.estimate <= median.high


def test_staleness_classes(spark):
    stale = spark.createDataFrame([(1, "a"), (2, "b"), (3, None), (5, "c")], "k int, v string")
    fresh = spark.createDataFrame([(1, "a"), (2, "B"), (3, None), (4, "d")], "k int, v string")
    got = {r.k: r["class"] for r in staleness.classify_staleness(stale, fresh, ("k",)).collect()}
    assert got == {1: "unchanged", 2: "incorrect", 3: "unchanged", 4: "missing", 5: "superfluous"}


def test_key_encoding(spark):
    df = spark.createDataFrame([("a|b", "c"), ("a", "b|c"), ("", None), (None, ""), ("\\N", None), ("\\", "|")], "x string, y string")
    assert df.select(H.key_text(df, ["x", "y"]).alias("t")).distinct().count() == 6
    small, large = H.key_hash_filter(spark.range(5000), "id", 0.1), H.key_hash_filter(spark.range(5000), "id", 0.25)
    assert small.exceptAll(large).isEmpty() and H.key_hash_filter(spark.range(9), "id", 0).isEmpty() and H.key_hash_filter(spark.range(9), "id", 1).count() == 9
    H.register_sql_functions(spark)
    spark.range(5000).createOrReplaceTempView("r")
    assert spark.sql("select id from r where in_sample(cast(id as string), 0.1D, 's1')").exceptAll(small).isEmpty()
    for family in H.FAMILIES:
        share = spark.range(5000).filter(H.in_sample(spark.range(5000), ["id"], 0.2, family=family)).count() / 5000
        assert abs(share - 0.2) < 0.03, (family, share)


def test_outliers(spark):
    df = spark.range(1, 11).select("id", F.col("id").cast("double").alias("x"))
    ids = lambda o: sorted(r.id for r in o.collect())
    assert ids(outliers.build_outlier_index(df, "x", ("id",), 6, 3)) == [8, 9, 10]
    assert ids(outliers.build_outlier_index(df, "x", ("id",), (3, 8), 2, "both")) == [1, 2, 9, 10]
    index = outliers.build_outlier_index(df, "x", ("id",), 6, 3)
    more = spark.createDataFrame([(20, 9.5), (21, 1.0)], "id long, x double")
    assert ids(outliers.update_outlier_index(index, more, df.filter("id = 10"), "x", ("id",), 6, 3)) == [8, 9, 20]
    rest = spark.createDataFrame([(1, 1.0), (2, 2.0), (3, 3.0), (4, 4.0)], "id long, x double")
    top = spark.createDataFrame([(9, 100.0)], "id long, x double")
    whole = rest.unionByName(top)
    assert outliers.direct_with_outliers(whole, top, AggQuery("sum", "x"), 1.0, ("id",)).first()[0] == 110
    assert outliers.direct_with_outliers(whole, top, AggQuery("avg", "x"), 1.0, ("id",)).first()[0] == 22
    assert outliers.tag_outliers(whole, top, ("id",)).filter("is_outlier").count() == 1
    # a record that the right input removes although its capped index lacks it
    left, right = Scan("l", whole, ("id",)), Scan("r", top, ("id",))
    sets = {"l": outliers.OutlierSet(frozenset("x"), top), "r": outliers.OutlierSet(frozenset("x"), top.limit(0))}
    assert outliers.push_up(Difference(left, right), sets).records.isEmpty()
    assert not outliers.push_up(Difference(left, right), sets, safe=False).records.isEmpty()


def test_outliers_help_at_strong_skew(spark):
    s = outlier_sweep.build(spark, D, 4)
    o = outlier_sweep.outlier_rows(s, 100)
    assert o.join(s.fresh, list(s.view.keys), "left_anti").isEmpty() and 0 < o.count() <= 100
    q = AggQuery("sum", "rev")
    wide = intervals.correction_interval(s.stale, s.stale_s, s.fresh_s, q, 0.1, s.view.keys).first().half_width
    assert outliers.interval_with_outliers(s.stale, s.stale_s, s.fresh_s, o, q, 0.1, s.view.keys).first().half_width < wide
    none = outliers.correction_with_outliers(s.stale, s.stale_s, s.fresh_s, o.limit(0), q, 0.1, s.view.keys).first()[0]
    plain = estimate.correction_estimate(s.stale, s.stale_s, s.fresh_s, q, 0.1).first()[0]
    assert abs(none - plain) < 1e-6 * abs(plain)


def test_metrics(spark):
    df = spark.createDataFrame([(10.0, 8.0, 9.0, 10.0), (0.0, 1.0, 1.0, 1.0), (-4.0, -5.0, -4.0, -4.0)], "truth double, stale double, direct double, correction double")
    rows = {r.method: r for r in metrics.error_summary(metrics.with_errors(df)).collect()}
    assert rows["stale"].worst == 0.25 and rows["stale"].n == 2 and abs(rows["stale"].median - 0.225) < 1e-12


def test_udaf_bootstrap_equals_built_in(state):
    q = AggQuery("percentile", "v", "n > 1", p=0.9)
    one = {r.b: r.v for r in bootstrap.direct_replicates_udaf(state.fresh_s, q, KEY, 8).collect()}
    two = {r.b: r.v for r in bootstrap.direct_replicates(state.fresh_s, q, 0.1, KEY, 8).collect()}
    assert one.keys() == two.keys() and all(abs(one[b] - two[b]) < 1e-6 for b in one)


def test_set_helps_more_with_size_and_skew(spark):
    r = {x.cap: x for x in outlier_sweep.size_sweep(spark, D, (0, 20, 100), salts=6).collect()}
    assert r[0].gain_direct in (1.0, None) and r[100].q75_direct_out <= r[20].q75_direct_out <= r[0].q75_direct_out


def test_outlier_correction_sums_exact_amounts(spark):
    """Summed as doubles row by row, the small amounts were lost beside the large ones."""
    frame = lambda *xs: spark.createDataFrame([(i, x) for i, x in enumerate(xs)], "id long, x string").select("id", F.col("x").cast("decimal(34,2)").alias("x")).coalesce(1)
    stale, fresh = frame("5.00"), frame("0.00", "9007199254740992.00", "1.00", "1.00", "-9007199254740992.00", "7.00")
    got = outliers.correction_with_outliers(stale, stale, fresh, fresh.filter("id = 5"), AggQuery("sum", "x"), 1.0, ("id",)).first()[0]
    assert got == 9.0


def test_outlier_interval_lies_around_the_exact_correction(spark):
    frame = lambda *xs: spark.createDataFrame([(i, x) for i, x in enumerate(xs)], "id long, x string").select("id", F.col("x").cast("decimal(34,2)").alias("x")).coalesce(1)
    stale, fresh = frame("5.00"), frame("0.00", "9007199254740992.00", "1.00", "1.00", "-9007199254740992.00", "7.00")
    got = outliers.interval_with_outliers(stale, stale, fresh, fresh.filter("id = 5"), AggQuery("sum", "x"), 1.0, ("id",)).first()
    assert tuple(got) == (9.0, 0.0, 9.0, 9.0)
