"""Outlier sets: records in the tail of an attribute, carried up to the view and always kept.

Building is a top-k with per-partition heaps. An index is a frame of base records; its
way up the tree follows one rule a node kind. At the view it is a set of keys, whose
rows are taken whole and count with ratio 1; the sample without them keeps ratio m.
The cap bounds base records only: on its way up an indexed dimension row meets all its
facts, so no side is broadcast by hint; the optimiser decides by size.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.nodes import Aggregate, Difference, Distinct, Intersect, Join, KeyHash, Node, Project, Scan, Select, Union, Windowed
from ..plans.pushdown import sampled_leaves
from .estimate import AggQuery, answer_exact
from .intervals import contributions, half_width, keyed_difference

CAP = 100


def threshold_topk(df: DataFrame, attr: str, k: int = CAP) -> DataFrame:
    """One row: the k-th largest value."""
    return df.select(attr).filter(F.col(attr).isNotNull()).orderBy(F.desc(attr)).limit(k).agg(F.min(attr).alias("threshold"))


def threshold_sigma(df: DataFrame, attr: str, c: float = 3.0) -> DataFrame:
    """One row: c standard deviations over the mean."""
    return df.agg((F.avg(attr) + c * F.stddev_pop(attr)).alias("threshold"))


def build_outlier_index(df: DataFrame, attr: str, key: tuple[str, ...], threshold=None, cap: int = CAP, tails: str = "upper") -> DataFrame:
    """At most ``cap`` records a tail beyond the threshold, the most extreme ones, ties by key.

    ``threshold`` is a number, a (low, high) pair for both tails, or None for the top ``cap``.
    """
    low, high = threshold if isinstance(threshold, tuple) else (threshold, threshold)
    parts = []
    if tails in ("upper", "both"):
        part = df if high is None else df.filter(F.col(attr) > high)
        parts.append(part.filter(F.col(attr).isNotNull()).orderBy(F.desc(attr), *key).limit(cap))
    if tails in ("lower", "both"):
        part = df if low is None else df.filter(F.col(attr) < low)
        parts.append(part.filter(F.col(attr).isNotNull()).orderBy(F.asc(attr), *key).limit(cap))
    return parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1]).distinct()


def update_outlier_index(index: DataFrame, inserted: DataFrame, deleted: DataFrame | None, attr: str, key: tuple[str, ...], threshold=None, cap: int = CAP) -> DataFrame:
    """The index after a batch of changes: one pass over cap + changes rows.

    After deletes it may hold fewer than the cap; records evicted before do not come back
    until it is built anew.
    """
    kept = index if deleted is None else index.join(deleted.select(*key), list(key), "left_anti").select(*index.columns)
    return build_outlier_index(kept.unionByName(inserted.select(*index.columns)), attr, key, threshold, cap)


@dataclass(frozen=True)
class OutlierSet:
    """Indexed attributes and the records, in terms of some node's columns."""

    attributes: frozenset[str]
    records: DataFrame = field(compare=False)


def eligible_indexes(plan: Node, key: tuple[str, ...], indexes: dict[str, OutlierSet]) -> dict[str, OutlierSet]:
    """Only indexes on tables that the filter of the view's key reaches."""
    reached = sampled_leaves(plan, key)
    return {t: i for t, i in indexes.items() if t in reached}


def push_up(node: Node, indexes: dict[str, OutlierSet], complete: bool = True, safe: bool = True) -> OutlierSet | None:
    """Carry indexes of base tables to a node; None where no record arrives.

    ``complete`` keeps, at joins of two indexed inputs, outliers whose partner is
    ordinary; ``safe`` tests differences against the whole right input.
    """
    up = lambda n: push_up(n, indexes, complete, safe)
    match node:
        case Scan():
            return indexes.get(node.name)
        case Select() | Distinct() | KeyHash() | Windowed():
            below = up(node.child)
            if below is None or not isinstance(node, Select):
                return below
            return OutlierSet(below.attributes, below.records.filter(node.condition))
        case Project():
            below = up(node.child)
            if below is None:
                return None
            names = {e: n for n, e in node.items}
            records = Project(Scan("outliers", below.records), node.items).lower()
            return OutlierSet(frozenset(names[a] for a in below.attributes if a in names), records)
        case Join():
            left, right = up(node.left), up(node.right)
            if left is None and right is None:
                return None
            join = lambda a, b: Join(Scan("l", a), Scan("r", b), node.on, "inner", node.fact, node.condition).lower()
            attributes = (left.attributes if left else frozenset()) | (right.attributes if right else frozenset())
            if left is None:
                return OutlierSet(attributes, join(node.left.lower(), right.records))
            if right is None:
                return OutlierSet(attributes, join(left.records, node.right.lower()))
            if not complete:
                return OutlierSet(attributes, join(left.records, right.records))
            one = join(left.records, node.right.lower())
            return OutlierSet(attributes, one.unionByName(join(node.left.lower(), right.records).select(*one.columns)).distinct())
        case Aggregate():
            below = up(node.child)
            if below is None:
                return None
            groups = below.records.select(*node.keys).distinct()
            whole = node.child.lower().join(groups, list(node.keys), "left_semi")
            return OutlierSet(frozenset(n for n, _ in node.aggs), Aggregate(Scan("rows", whole), node.keys, node.aggs).lower())
        case Union():
            left, right = up(node.left), up(node.right)
            if left is None or right is None:
                return left or right
            return OutlierSet(left.attributes & right.attributes, left.records.unionByName(right.records).distinct())
        case Intersect():
            left, right = up(node.left), up(node.right)
            if left is None or right is None:
                return None
            return OutlierSet(left.attributes & right.attributes, left.records.intersect(right.records.select(*left.records.columns)))
        case Difference():
            left, right = up(node.left), up(node.right)
            if left is None:
                return None
            other = node.right.lower() if safe or right is None else right.records
            return OutlierSet(left.attributes | (right.attributes if right else frozenset()), left.records.subtract(other.select(*left.records.columns)))
    raise TypeError(node)


def tag_outliers(sample: DataFrame, outliers: DataFrame, key: tuple[str, ...]) -> DataFrame:
    """Sample and outliers with ``is_outlier``; a row in both is an outlier only."""
    kept = sample.join(outliers.select(*key), list(key), "left_anti").select(*sample.columns)
    return kept.withColumn("is_outlier", F.lit(False)).unionByName(outliers.select(*sample.columns).withColumn("is_outlier", F.lit(True)))


def _without(df: DataFrame, outliers: DataFrame, key: tuple[str, ...]) -> DataFrame:
    return df.join(outliers.select(*key), list(key), "left_anti").select(*df.columns)


def _within(df: DataFrame, outliers: DataFrame, key: tuple[str, ...]) -> DataFrame:
    return df.join(outliers.select(*key), list(key), "left_semi").select(*df.columns)


def merge_strata(parts: DataFrame, kind: str) -> DataFrame:
    """``parts``: one row reg, out, n_total, n_out. Totals add; means weigh by the rows that each part stands for."""
    if kind == "total":
        return parts.select((F.coalesce("reg", F.lit(0.0)) + F.coalesce("out", F.lit(0.0))).alias("estimate"))
    share = F.coalesce(F.try_divide(F.col("n_out"), F.col("n_total")), F.lit(0.0))
    return parts.select((F.coalesce((1 - share) * F.col("reg"), F.lit(0.0)) + F.coalesce(share * F.col("out"), F.lit(0.0))).alias("estimate"))


def direct_with_outliers(fresh_s: DataFrame, outliers: DataFrame, q: AggQuery, m: float, key: tuple[str, ...]) -> DataFrame:
    """Ordinary sample rows scaled by 1/m, outliers as they are; for an average the rows of the fresh view are estimated."""
    rest = _without(fresh_s, outliers, key)
    count = AggQuery("count", "1", q.cond)
    parts = answer_exact(rest, q, "reg").crossJoin(answer_exact(outliers, q, "out")).crossJoin(answer_exact(rest, count, "k")).crossJoin(answer_exact(outliers, count, "n_out"))
    parts = parts.select((F.col("reg") * q.scale(m)).alias("reg"), "out", (F.col("k") / m + F.col("n_out")).alias("n_total"), "n_out")
    return merge_strata(parts, "total" if q.agg in ("sum", "count") else "mean")


def _by_key(stale: DataFrame, stale_s: DataFrame, fresh_s: DataFrame, outliers: DataFrame, q: AggQuery, key: tuple[str, ...]) -> DataFrame:
    """One row a key of any frame: its amount in each, in the attribute's own type, and ``__is_out``.

    A union summed by key: every frame is read once and none is joined with another.
    """
    hit = F.coalesce(F.expr(q.cond), F.lit(False))
    amount = hit.cast("bigint") if q.agg == "count" else F.when(hit, F.expr(q.attr))
    parts = None
    for name, df in (("__was", stale), ("__s", stale_s), ("__f", fresh_s), ("__o", outliers)):
        part = df.select(*key, amount.alias("__amount"), F.lit(name).alias("__of"))
        parts = part if parts is None else parts.unionByName(part)
    sums = [F.sum(F.when(F.col("__of") == n, F.col("__amount"))).alias(n) for n in ("__was", "__s", "__f", "__o")]
    return parts.groupBy(*key).agg(*sums, F.max(F.col("__of") == "__o").alias("__is_out"))


def _corrected(m: float) -> Column:
    """The corrected total over _by_key: exact amounts only become doubles as sums."""
    total = lambda name, cond="true": F.coalesce(F.sum(F.when(F.expr(cond), F.col(name))).cast("double"), F.lit(0.0))
    return total("__was") + (total("__f", "not __is_out") - total("__s", "not __is_out")) * (1 / m) + total("__o") - total("__was", "__is_out")


def correction_with_outliers(stale: DataFrame, stale_s: DataFrame, fresh_s: DataFrame, outliers: DataFrame, q: AggQuery, m: float, key: tuple[str, ...]) -> DataFrame:
    """Totals: stale answer, plus the scaled drift of ordinary sample rows, plus the exact drift of the outliers' keys."""
    if q.agg not in ("sum", "count"):
        direct = direct_with_outliers(fresh_s, outliers, q, m, key).withColumnRenamed("estimate", "fresh")
        before = direct_with_outliers(stale_s, _within(stale, outliers, key), q, m, key).withColumnRenamed("estimate", "before")
        return answer_exact(stale, q, "was").crossJoin(direct).crossJoin(before).select((F.col("was") + F.col("fresh") - F.col("before")).alias("estimate"))
    return _by_key(stale, stale_s, fresh_s, outliers, q, key).agg(_corrected(m).alias("estimate"))


def interval_with_outliers(stale: DataFrame, stale_s: DataFrame, fresh_s: DataFrame, outliers: DataFrame, q: AggQuery, m: float, key: tuple[str, ...], level: float = 0.95) -> DataFrame:
    """Outliers add nothing to the width. A total and its width come from one pass by key."""
    e, h = F.col("estimate"), F.col("half_width")
    width = F.coalesce(half_width("ht", level, m), F.lit(0.0)).alias("half_width")
    if q.agg in ("sum", "count"):
        scaled = lambda name: F.coalesce(F.col(name).cast("double"), F.lit(0.0)) / m
        d = _by_key(stale, stale_s, fresh_s, outliers, q, key).withColumn("y", F.when(~F.col("__is_out"), scaled("__f") - scaled("__s")))
        both = d.agg(_corrected(m).alias("estimate"), width)
    else:
        d = keyed_difference(contributions(_without(fresh_s, outliers, key), q, m, key), contributions(_without(stale_s, outliers, key), q, m, key), key)
        both = correction_with_outliers(stale, stale_s, fresh_s, outliers, q, m, key).crossJoin(d.agg(width))
    return both.select("estimate", "half_width", (e - h).alias("low"), (e + h).alias("high"))
