"""Tables with fixed schemas, the sequence key of keyless tables, versioned and banded sinks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import hash_band

_STAR = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
}
KEYS = {"region": ("r_regionkey",), "nation": ("n_nationkey",), "customer": ("c_custkey",), "supplier": ("s_suppkey",), "part": ("p_partkey",), "orders": ("o_orderkey",), "lineitem": ("l_orderkey", "l_seq"), "events": ("event_id",), "documents": ("doc_id",), "labels": ("doc_id",)}
LINE_ORDER = ["l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]


def plain_unions(spark: SparkSession) -> None:
    """Unions of this session do not claim the partitioning of their inputs.

    Spark 4.1 lets them, but when it plans anew at run time an input may change (a join
    becomes a broadcast one) and the claim is void: a join above then fails on unequal numbers
    of partitions. Without the claim sums above a union are shuffled as partial sums.
    """
    spark.conf.set("spark.sql.unionOutputPartitioning", "false")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; the file's own schema decides the types, the fixed one is for streams and other formats."""
    plain_unions(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def schema_of(spark: SparkSession, sf_dir: str, name: str):
    """The schema that a stream over this table needs."""
    return load(spark, sf_dir, name).schema


def load_any(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options) -> DataFrame:
    """CSV, JSON, ORC or Parquet with a given schema; nothing is inferred from text formats."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def stream(spark: SparkSession, path: str, schema, max_files: int = 1, fmt: str = "parquet") -> DataFrame:
    """A file stream that takes at most ``max_files`` new files a batch."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).format(fmt).load(path)


def add_sequence_key(df: DataFrame, partition_by: list[str], order_by: list[str], name: str = "seq") -> DataFrame:
    """A key for a keyless table: number rows inside ``partition_by``; never a global sort. Equal rows get different numbers."""
    return df.withColumn(name, F.row_number().over(Window.partitionBy(*partition_by).orderBy(*order_by)))


def add_one_shot_key(df: DataFrame, name: str = "seq") -> DataFrame:
    """A key without a shuffle, not stable from one read to the next; only for data that is read once."""
    return df.withColumn(name, F.monotonically_increasing_id())


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``lineitem`` with its key (l_orderkey, l_seq)."""
    return add_sequence_key(load(spark, sf_dir, "lineitem"), ["l_orderkey"], LINE_ORDER, "l_seq")


def money(column: str | Column, digits: int = 12) -> Column:
    """A double with two decimals as an exact number, so that sums do not depend on their order."""
    return (F.col(column) if isinstance(column, str) else column).cast(f"decimal({digits},2)")


def revenue() -> Column:
    """Price less discount of a line, exact to four decimals."""
    return (money("l_extendedprice") * (F.lit(1).cast("decimal(4,2)") - F.col("l_discount").cast("decimal(4,2)"))).cast("decimal(18,4)")


def write_banded(df: DataFrame, path: str, key: list[str], salt: str, bands_changed_only: bool = False, family: str = "md5", parts: int = 1) -> None:
    """Write a view or sample partitioned by hash band; with ``bands_changed_only`` other bands stay as they are.

    ``parts``: tasks and files a band, for views of which one of 256 bands is too much for a task.
    """
    banded = df.withColumn("hash_band", hash_band(df, key, salt, family))
    banded = banded.repartition("hash_band", *[F.pmod(F.xxhash64(*key), F.lit(parts))][: parts > 1])
    writer = banded.write.mode("overwrite").partitionBy("hash_band")
    if bands_changed_only:
        writer = writer.option("partitionOverwriteMode", "dynamic")
    writer.parquet(path)


def run_to_nothing(df: DataFrame) -> None:
    """Compute every row and throw it away; for timing."""
    df.write.format("noop").mode("overwrite").save()
