"""Helpers shared by the training-data operators."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, from ``spark.checkpoint.dir``; in local mode a new one where none is named."""
    context = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not named:
        if not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="freshview-"))
        named = context.getCheckpointDir()
    return named.rstrip("/")


def _path(spark: SparkSession, path: str):
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    return hadoop, hadoop.getFileSystem(spark._jsc.hadoopConfiguration())


#: Rows and bytes of an Arrow batch on its way to a Python worker, and of a slice of one: what a worker turns into objects at once.
BATCH_ROWS, BATCH_BYTES = 2000, 16 << 20


@contextmanager
def batch_bounds(spark: SparkSession):
    """The session's Arrow batches are no larger than ours while a job of ours runs; then its settings are back."""
    settings = {"spark.sql.execution.arrow.maxRecordsPerBatch": str(BATCH_ROWS), "spark.sql.execution.arrow.maxBytesPerBatch": str(BATCH_BYTES)}
    before = {k: spark.conf.get(k) for k in settings}
    try:
        for k, v in settings.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)


def materialise(df: DataFrame, partition_by: tuple[str, ...] = ()) -> DataFrame:
    """Cut the lineage by writing a table into the shared folder and reading it back.

    The table is removed when the driver ends, or by ``discard`` before.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/table-{uuid.uuid4().hex}"
    with batch_bounds(spark):
        df.write.parquet(path, partitionBy=list(partition_by) or None)
    folder, files = _path(spark, path)
    files.deleteOnExit(folder)
    out = spark.read.schema(df.schema).parquet(path)
    out._table_path = path
    return out


def discard(df: DataFrame) -> None:
    """Remove a table that ``materialise`` wrote and that no frame still in use reads."""
    if path := getattr(df, "_table_path", None):
        folder, files = _path(df.sparkSession, path)
        files.delete(folder, True)


def slices(batches: Iterable[pa.RecordBatch], rows: int = BATCH_ROWS, size: int = BATCH_BYTES) -> Iterator[pa.RecordBatch]:
    """The batches in slices of at most ``rows`` rows and about ``size`` bytes (one row at least), without a copy."""
    for batch in batches:
        for begin in range(0, batch.num_rows, rows):
            stack = [batch.slice(begin, rows)]
            while stack:
                part = stack.pop()
                half = part.num_rows // 2
                if half and part.nbytes > size:
                    stack += [part.slice(half), part.slice(0, half)]
                else:
                    yield part


#: A key with more than this share of the rows is hot, so there are fewer hot keys than its inverse.
HOT_SHARE = 1 / 256


def hot_keys(rows: DataFrame, key: str, share: float = HOT_SHARE) -> list[tuple]:
    """(value, parts) of each hot key: as many parts as it holds shares of the rows. Values and parts are at most ``1 / share`` in all each."""
    least = max(1.0, rows.count() * share)
    counts = rows.filter(F.col(key).isNotNull()).groupBy(key).agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > least)
    return [(r[0], int(r["n"] / least) + 1) for r in counts.collect()]


def salted_join(many: DataFrame, one: DataFrame, key: str, spread: list[str], hot: list[tuple], how: str = "inner", written: bool = False) -> DataFrame:
    """``many`` joined with ``one`` by ``key``; rows of a hot key meet in several parts instead of one place.

    A hot row of ``many`` goes by a hash of the columns ``spread``; the rows of ``one`` with
    a hot key are repeated, once a part. Other keys join as they are. The list of hot keys
    is broadcast; its size is bounded by ``hot_keys``. ``written``: the repeated rows are
    written first, so that their size is known and Spark spares ``many`` the shuffle where it is small.
    """
    if not hot:
        return many.join(one, key, how)
    kind = one.schema[key].dataType.simpleString()
    parts = F.broadcast(many.sparkSession.createDataFrame(hot, f"`{key}` {kind}, __parts int"))
    n = F.coalesce("__parts", F.lit(1))
    split = many.join(parts, key, "left").withColumn("__part", F.pmod(F.xxhash64(*spread), n).cast("int")).drop("__parts")
    repeated = one.join(parts, key, "left").withColumn("__part", F.explode(F.sequence(F.lit(0), n - 1))).drop("__parts")
    return split.join(materialise(repeated) if written else repeated, [key, "__part"], how).drop("__part")
