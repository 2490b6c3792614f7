"""Joins that Spark has no operator for: by range, by interval, as of a time; and top-k by group."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(df: DataFrame, value: str, boxes: DataFrame, low: str, high: str, width: float) -> DataFrame:
    """Rows with every box [low, high) that holds their value.

    A box is listed under each bucket of ``width`` that it touches, so the join is an
    equality join on buckets plus the comparison; choose the width near a box's length.
    """
    bucket = F.floor(F.col(value) / width)
    listed = boxes.withColumn("__bucket", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    joined = df.withColumn("__bucket", bucket).join(listed, "__bucket")
    return joined.filter((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("__bucket")


def _micros(c: Column) -> Column:
    return F.unix_micros(c.cast("timestamp"))


def interval_join(left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, seconds: int) -> DataFrame:
    """Pairs of one key whose right time lies in (left, left + seconds].

    Time is cut into buckets of that length; a left row looks into its own bucket and the
    next, so a hot key spreads over its buckets.
    """
    span = seconds * 1_000_000
    b = F.floor(_micros(F.col(right_ts)) / span)
    own = F.floor(_micros(F.col(left_ts)) / span)
    looked = left.withColumn("__b", F.explode(F.array(own, own + 1)))
    joined = looked.join(right.withColumn("__b", b), [key, "__b"])
    gap = _micros(F.col(right_ts)) - _micros(F.col(left_ts))
    return joined.filter((gap > 0) & (gap <= span)).drop("__b")


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, values: list[str], tie: str) -> DataFrame:
    """Each left row with the values of the latest right row of its key at or before its time.

    One union and one window with ``last`` over non-null structs; no search by row. Right
    rows of equal time are ordered by ``tie``; a left row sees right rows of its own time.
    """
    names = [c for c in left.columns if c not in (key, ts)]
    a = left.select(key, ts, F.struct(*names).alias("__row"), F.lit(None).cast(right.select(F.struct(*values).alias("v")).schema["v"].dataType).alias("__seen"), F.lit(1).alias("__side"), F.lit(None).cast("long").alias("__tie"))
    b = right.select(key, ts, F.lit(None).cast(a.schema["__row"].dataType).alias("__row"), F.struct(*values).alias("__seen"), F.lit(0).alias("__side"), F.col(tie).cast("long").alias("__tie"))
    order = Window.partitionBy(key).orderBy(ts, "__side", "__tie").rowsBetween(Window.unboundedPreceding, 0)
    out = a.unionByName(b).withColumn("__last", F.last("__seen", ignorenulls=True).over(order)).filter("__side = 1")
    return out.select(key, ts, "__row.*", *[F.col(f"__last.{v}").alias(f"asof_{v}") for v in values])


def top_per_group(df: DataFrame, group: list[str], by: str, k: int, tie: list[str]) -> DataFrame:
    """The k largest rows of each group, ties by key. Spark keeps k rows a task and group before the shuffle."""
    return df.withColumn("place", F.row_number().over(Window.partitionBy(*group).orderBy(F.desc(by), *tie))).filter(F.col("place") <= k)
