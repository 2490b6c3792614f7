"""Incorrect, missing and superfluous rows of a stale view."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def classify_staleness(stale: DataFrame, fresh: DataFrame, key: tuple[str, ...]) -> DataFrame:
    """Key and class of every row of either: incorrect, missing, superfluous or unchanged (null-safe)."""
    values = [c for c in fresh.columns if c not in key]
    old = stale.select(*[F.col(k).alias(f"o_{k}") for k in key], F.struct(*values).alias("old"), F.lit(True).alias("in_old"))
    new = fresh.select(*key, F.struct(*values).alias("new"), F.lit(True).alias("in_new"))
    same_key = None
    for k in key:
        test = F.col(k).eqNullSafe(F.col(f"o_{k}"))
        same_key = test if same_key is None else same_key & test
    kind = F.when(F.col("in_old").isNull(), "missing").when(F.col("in_new").isNull(), "superfluous").when(F.col("old").eqNullSafe(F.col("new")), "unchanged").otherwise("incorrect")
    return new.join(old, same_key, "full_outer").select(*[F.when(F.col("in_new").isNull(), F.col(f"o_{k}")).otherwise(F.col(k)).alias(k) for k in key], kind.alias("class"))


def staleness_profile(stale: DataFrame, fresh: DataFrame, key: tuple[str, ...]) -> DataFrame:
    counts = classify_staleness(stale, fresh, key).groupBy("class").agg(F.count(F.lit(1)).alias("n"))
    total = counts.agg(F.sum("n").alias("total"))
    return counts.crossJoin(F.broadcast(total)).select("class", "n", (F.col("n") / F.col("total")).alias("share"))
