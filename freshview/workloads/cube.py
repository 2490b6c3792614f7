"""Base cube of revenue over customer, nation, region and brand (or part), its roll-ups, and their medians."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.estimate import LINEAR, AggQuery
from ..operators.metrics import error_summary, with_errors
from ..operators.views import View
from ..plans.nodes import Join, Node
from ..sources import tables as T
from .base import CHANGED, RATIO, State, order_changes, state_of
from .join_view import REV

DIMENSIONS = ("o_custkey", "c_nationkey", "n_regionkey", "p_brand")
FINE = ("o_custkey", "c_nationkey", "n_regionkey", "l_partkey")


def _rows(leaf: dict[str, Node]) -> Node:
    sales = Join(leaf["lineitem"], leaf["orders"], (("l_orderkey", "o_orderkey"),), "inner", "left")
    buyer = Join(sales, leaf["customer"], (("o_custkey", "c_custkey"),), "inner", "left")
    place = Join(buyer, leaf["nation"], (("c_nationkey", "n_nationkey"),), "inner", "left", small="right")
    return Join(place, leaf["part"], (("l_partkey", "p_partkey"),), "inner", "left")


def view_of(dimensions: tuple[str, ...] = DIMENSIONS) -> View:
    return View("cube", dimensions, (("rev", REV), ("n", "1")), _rows, ("lineitem", "orders", "customer", "nation", "part"))


def build(spark: SparkSession, sf_dir: str, m: float = RATIO, frac: float = CHANGED, dimensions: tuple[str, ...] = DIMENSIONS) -> State:
    static = {t: T.load(spark, sf_dir, t) for t in ("customer", "nation", "part")}
    return state_of(view_of(dimensions), order_changes(spark, sf_dir, frac, more=static), m)


def rollup_sets(dimensions: tuple[str, ...] = DIMENSIONS) -> list[tuple[str, ...]]:
    """All proper roll-ups, the grand total included."""
    return [s for n in range(len(dimensions)) for s in combinations(dimensions, n)]


def rollups(state: State, agg: str = "sum", sets: list[tuple[str, ...]] | None = None, accuracy: int = 0) -> DataFrame:
    """Answers with errors for every group of every roll-up: grouping sets over one tagged union of the four frames.

    ``accuracy``: 0 for exact medians, else that of ``percentile_approx``.
    """
    frames = {"t": state.fresh, "s": state.stale, "d": state.fresh_s, "c": state.stale_s}
    dims = state.view.keys
    tagged = None
    for tag, df in frames.items():
        part = df.select(*dims, "rev", F.lit(tag).alias("__frame"))
        tagged = part if tagged is None else tagged.unionByName(part)
    wanted = rollup_sets(dims) if sets is None else sets
    scale = 1 / state.m if agg in LINEAR else 1.0
    of = lambda tag: AggQuery(agg, "rev", f"__frame = '{tag}'", accuracy=accuracy).value()
    rows = lambda tag: F.count(F.when(F.col("__frame") == tag, F.lit(1))) > 0
    sums = tagged.groupingSets([[F.col(c) for c in s] for s in wanted], *[F.col(c) for c in dims]).agg(
        *[F.when(rows(tag), of(tag)).alias(f"v_{tag}") for tag in frames], *[F.grouping(c).alias(f"g_{c}") for c in dims]
    )
    named = F.concat_ws(",", *[F.when(F.col(f"g_{c}") == 0, F.lit(c)) for c in dims])
    group = F.concat_ws("|", *[F.col(c).cast("string") for c in dims])
    t, s, d, c = (F.col(f"v_{tag}") for tag in frames)
    correction = F.when(F.coalesce(s, d).isNotNull(), F.coalesce(s, F.lit(0.0)) + (F.coalesce(d, F.lit(0.0)) - F.coalesce(c, F.lit(0.0))) * scale)
    return with_errors(sums.select(named.alias("query_id"), group.alias("group_key"), t.alias("truth"), s.alias("stale"), (d * scale).alias("direct"), correction.alias("correction")))


def rollup_errors(state: State, agg: str = "sum", sets: list[tuple[str, ...]] | None = None) -> DataFrame:
    """Median, 75 % and largest group error by roll-up and method."""
    return error_summary(rollups(state, agg, sets), by=("query_id",))


def exact_cube(state: State) -> DataFrame:
    """Truth of all roll-ups in one pass, by grouping sets."""
    return state.fresh.cube(*state.view.keys).agg(F.sum("rev").alias("rev"), F.sum("n").alias("n"), F.grouping_id().alias("gid"))
