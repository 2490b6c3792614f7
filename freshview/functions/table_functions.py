"""``answer_fresh`` as a SQL table function over prepared sample contributions."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..operators.estimate import AggQuery, paired_moments


@udtf(returnType="method string, estimate double, low double, high double")
class AnswerFresh:
    """Both estimators with 95 % intervals from rows (m, was, f, s, ff, dd): one row of sums, so nothing is held."""

    def eval(self, row: Row):
        for method, estimate, squares in (("direct", row["f"], row["ff"]), ("correction", row["was"] + row["f"] - row["s"], row["dd"])):
            width = 1.96 * math.sqrt(max(0.0, (1 - row["m"]) * squares))
            yield method, estimate, estimate - width, estimate + width


def prepared(stale: DataFrame, stale_s: DataFrame, fresh_s: DataFrame, q: AggQuery, m: float, key: tuple[str, ...]) -> DataFrame:
    """The one-row frame that the function takes."""
    p = paired_moments(stale_s, fresh_s, q, m, key)
    d = F.col("f") - F.col("s")
    sums = p.agg(F.sum("f").alias("f"), F.sum("s").alias("s"), F.sum(F.col("f") * F.col("f")).alias("ff"), F.sum(d * d).alias("dd"))
    return stale.agg(q.value().alias("was")).crossJoin(sums).select(F.lit(m).alias("m"), "was", "f", "s", "ff", "dd")


def register(spark: SparkSession) -> None:
    spark.udtf.register("answer_fresh", AnswerFresh)


def answer_fresh(spark: SparkSession, one_row: DataFrame, name: str = "prepared_answer") -> DataFrame:
    register(spark)
    one_row.createOrReplaceTempView(name)
    return spark.sql(f"SELECT * FROM answer_fresh(TABLE({name}))")
