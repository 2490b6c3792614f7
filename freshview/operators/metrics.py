"""Accuracy and cost measures."""

from __future__ import annotations

import time

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F


def relative_error(estimate: Column, truth: Column) -> Column:
    """Absolute difference over the absolute truth; null for truth 0."""
    return F.abs(estimate - truth) / F.nullif(F.abs(truth), F.lit(0.0))


def with_errors(answers: DataFrame, truth: str = "truth", methods: tuple[str, ...] = ("stale", "direct", "correction")) -> DataFrame:
    return answers.select("*", *[relative_error(F.col(m), F.col(truth)).alias(f"err_{m}") for m in methods])


def error_summary(errors: DataFrame, methods: tuple[str, ...] = ("stale", "direct", "correction"), by: tuple[str, ...] = ()) -> DataFrame:
    """One row a method: median, 75 % quantile, maximum, mean, rows, and the gain over the first method (ratio of medians)."""
    grouped = errors.groupBy(*by) if by else errors
    stats = grouped.agg(*[F.struct(F.percentile(f"err_{m}", F.lit(0.5)).alias("median"), F.percentile(f"err_{m}", F.lit(0.75)).alias("q75"), F.max(f"err_{m}").alias("worst"), F.avg(f"err_{m}").alias("mean"), F.count(f"err_{m}").alias("n")).alias(m) for m in methods])
    rows = F.array(*[F.struct(F.lit(m).alias("method"), F.col(f"{m}.median").alias("median"), F.col(f"{m}.q75").alias("q75"), F.col(f"{m}.worst").alias("worst"), F.col(f"{m}.mean").alias("mean"), F.col(f"{m}.n").alias("n"), F.try_divide(F.col(f"{methods[0]}.median"), F.col(f"{m}.median")).alias("gain")) for m in methods])
    return stats.select(*by, F.inline(rows))


def break_even(by_size: DataFrame, size: str = "size") -> DataFrame:
    """First swept change size at which the median error of the correction exceeds the direct estimator's."""
    return by_size.filter(F.col("correction") > F.col("direct")).agg(F.min(size).alias("break_even"))


def timed(df: DataFrame) -> float:
    """Seconds to compute every row; loading of changes is not counted if they were cached before."""
    start = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def observed_rows(df: DataFrame, name: str) -> tuple[DataFrame, Observation]:
    """Counts the rows that pass here when the plan runs."""
    seen = Observation(name)
    return df.observe(seen, F.count(F.lit(1)).alias("rows")), seen


def work_report(plan, m: float, key: tuple[str, ...], salt: str = "s1") -> DataFrame:
    """Rows of each leaf before and after the pushed filter: the work saved, independent of the machine."""
    from ..plans.nodes import KeyHash, Scan
    from ..plans.pushdown import push

    pushed = push(KeyHash(plan, key, m, salt))[0]
    out = None

    def walk(node, above=None):
        nonlocal out
        if isinstance(node, Scan):
            kept = (above.around(node) if isinstance(above, KeyHash) else node).lower()
            row = node.lower().agg(F.count(F.lit(1)).alias("rows")).crossJoin(kept.agg(F.count(F.lit(1)).alias("kept"))).select(F.lit(node.label()).alias("leaf"), "rows", "kept")
            out = row if out is None else out.unionByName(row)
        for c in node.children():
            walk(c, node)

    walk(pushed)
    return out
