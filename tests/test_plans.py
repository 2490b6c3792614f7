import pytest
from freshview.plans import keys
from freshview.plans.nodes import Aggregate, Difference, Distinct, Intersect, Join, KeyHash, Project, Scan, Select, Union, Windowed
from freshview.plans.pushdown import explain_pushdown, push, same_sample
from freshview.sources import tables as T
from freshview.workloads import complex_views, demand

D = "/root/testdata/sf0.001"


def scan(spark, t):
    return Scan(t, T.lines(spark, D) if t == "lineitem" else T.load(spark, D, t), T.KEYS[t])


def test_keys(spark):
    line, order = scan(spark, "lineitem"), scan(spark, "orders")
    joined = Join(line, order, (("l_orderkey", "o_orderkey"),), "inner", "left")
    assert keys.infer_key(joined) == ("l_orderkey", "l_seq", "o_orderkey")
    assert keys.infer_key(joined, reduce_fk=True) == ("l_orderkey", "l_seq")
    counts = Aggregate(joined, ("o_custkey",), (("n", "count(1)"),))
    assert keys.infer_key(Select(counts, "n > 1")) == ("o_custkey",)
    with pytest.raises(keys.KeyDropped):
        keys.infer_key(Project(counts, (("n", "n"),)))
    assert keys.infer_key(keys.repair_key(Project(counts, (("n", "n"),)))) == ("o_custkey",)
    assert keys.infer_key(Aggregate(line, (), (("n", "count(1)"),))) == ()
    named = Project(order, (("id", "o_orderkey"), ("c", "o_custkey")))
    assert keys.infer_key(named) == ("id",) and keys.infer_key(Union(named, named)) == ("id",) and keys.infer_key(Difference(named, named)) == ("id",)
    assert keys.infer_key(Distinct(named)) == ("id", "c")
    other = Project(order, (("other", "o_orderkey"), ("id", "o_custkey")))
    with pytest.raises(ValueError):
        keys.infer_key(Intersect(named, other))
    with pytest.raises(ValueError):
        keys.infer_key(Scan("keyless", order.df))
    for node in (line, joined, counts):
        assert keys.audit_key(node.lower(), keys.infer_key(node)).first().n_repeated == 0


def plans(spark):
    order, cust = scan(spark, "orders"), scan(spark, "customer")
    some = lambda s: Project(Select(order, f"o_orderstatus = '{s}'"), (("o_custkey", "o_custkey"),))
    counts = lambda s, n: Aggregate(Select(order, f"o_orderstatus = '{s}'"), ("o_custkey",), ((n, "count(1)"),))
    on = (("c_custkey", "o_custkey"),)
    return {
        "union": (Union(some("F"), some("O")), ("o_custkey",)),
        "bag": (Union(some("F"), some("O"), bag=True), ("o_custkey",)),
        "intersect": (Intersect(some("F"), some("O")), ("o_custkey",)),
        "difference": (Difference(some("F"), some("P")), ("o_custkey",)),
        "full": (Join(counts("F", "f"), counts("P", "p"), (("o_custkey", "o_custkey"),), "full"), ("o_custkey",)),
        "left": (Join(cust, order, on, "left"), ("c_custkey",)),
        "right": (Join(order, cust, (("o_custkey", "c_custkey"),), "right"), ("c_custkey",)),
        "semi": (Join(cust, order, on, "left_semi"), ("c_custkey",)),
        "anti": (Join(cust, Select(order, "o_totalprice > 300000"), on, "left_anti"), ("c_custkey",)),
        "window": (Windowed(order, ("o_custkey",), (("r", "rank() over (partition by o_custkey order by o_orderkey)"),)), ("o_custkey",)),
        "distinct": (Distinct(some("F")), ("o_custkey",)),
    }


def test_same_sample_for_every_rule(spark):
    for name, (plan, key) in plans(spark).items():
        steps = explain_pushdown(plan, key, 0.3)
        assert not [s for s in steps if s.outcome == "blocked"], (name, steps)
        assert all(s.outcome != "reached" or s.detail for s in steps)
        assert same_sample(plan, key, 0.3), name


def test_blocked_and_workload_plans(spark):
    blocked = {n for n, (p, k) in demand.expressions(spark, D).items() if any(s.outcome == "blocked" for s in explain_pushdown(p, k, 0.3))}
    assert blocked == {"cartesian", "group_by_count"}
    views = complex_views.views(complex_views.scans(spark, D))
    stuck = {n for n, (p, k) in views.items() if any(s.outcome == "blocked" for s in explain_pushdown(p, k, 0.3))}
    assert stuck == {"v5", "v9", "v13_histogram", "v15", "v22"}, stuck
    for name in ("v3", "v13", "v13_histogram", "v21", "v22"):
        assert same_sample(*views[name], 0.3), name


def test_filter_reaches_both_inputs_in_catalyst(spark):
    plan, key = plans(spark)["intersect"]
    text = push(KeyHash(plan, key, 0.3))[0].lower()._jdf.queryExecution().optimizedPlan().toString()
    assert text.count("md5") == 2
