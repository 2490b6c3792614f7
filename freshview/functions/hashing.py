"""Key-hash filter: a deterministic, Bernoulli-like sample by the hash of a key.

The hash is 32 bits. The default family compares the first eight hex digits of an md5
as text, which equals a numeric comparison and which any SQL engine can repeat. A row
is kept below ``ceil(m * 2**32)``, so samples of one salt are nested in m. The filter is
one deterministic expression without Python, so Catalyst can push it to the scan.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SALT = "s1"
FAMILIES = ("md5", "sha2_256", "xxhash64", "crc32", "linear", "sdbm")
#: A prime over 2**31, multiplier and offset of the linear family; the factor of the sdbm recurrence.
LINEAR_PRIME, LINEAR_A, LINEAR_B, SDBM = 4294967311, 2654435761, 97, 65599
BANDS = 256


def encode_key(columns: list[Column | str], types: dict[str, str] | None = None) -> Column:
    """One text for a key: parts joined by ``|``, null as ``\\N``, ``|`` and ``\\`` escaped in texts."""
    parts = []
    for c in columns:
        kind = (types or {}).get(c) if isinstance(c, str) else None
        if kind in ("double", "float", "timestamp"):
            raise TypeError(f"{c}: {kind} values print differently in different engines and cannot be part of a hashed key")
        text = F.col(c).cast("string") if isinstance(c, str) else c.cast("string")
        if kind is None or kind == "string":
            text = F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("|"), F.lit("\\|"))
        parts.append(F.coalesce(text, F.lit("\\N")))
    return parts[0] if len(parts) == 1 else F.concat_ws("|", *parts)


def key_text(df: DataFrame, key: list[str]) -> Column:
    return encode_key(list(key), dict(df.dtypes))


def hex8(share: float) -> str:
    """The exclusive bound of a share as eight hex digits (a share of 1 has none)."""
    return f"{math.ceil(share * 2**32):08x}"


def hash32(text: Column, salt: str = SALT, family: str = "md5") -> Column:
    """Hash of a key text: eight hex digits for md5 and sha2_256, else a long in 0..2**32-1."""
    salted = F.concat(F.lit(f"{salt}|"), text)
    if family == "md5":
        return F.substring(F.md5(salted), 1, 8)
    if family == "sha2_256":
        return F.substring(F.sha2(salted, 256), 1, 8)
    if family == "xxhash64":
        return F.shiftrightunsigned(F.xxhash64(salted), 32)
    if family == "crc32":
        return F.crc32(salted)
    if family == "linear":
        mixed = F.crc32(salted).cast("decimal(20,0)") * F.lit(LINEAR_A).cast("decimal(20,0)") + LINEAR_B
        return F.pmod(mixed % LINEAR_PRIME, F.lit(2**32)).cast("long")
    if family == "sdbm":
        points = F.transform(F.split(F.hex(F.encode(salted, "UTF-8")), "(?<=\\G..)"), lambda h: F.coalesce(F.conv(h, 16, 10).cast("long"), F.lit(0)))
        # the last characters only reach the low bits, so a multiplication spreads them
        spread = lambda h: F.pmod(F.pmod(h, F.lit(2**31)) * F.lit(LINEAR_A), F.lit(2**32))
        return F.aggregate(points, F.lit(0).cast("long"), lambda h, c: F.pmod(h * SDBM + c, F.lit(2**32)), spread)
    raise ValueError(f"unknown family {family}")


def below(value: Column, share: float, family: str = "md5") -> Column:
    bound = math.ceil(share * 2**32)
    if bound >= 2**32:
        return F.lit(True)
    return value < (F.lit(hex8(share)) if family in ("md5", "sha2_256") else F.lit(bound))


def in_sample(df: DataFrame, key: list[str], m: float, salt: str = SALT, family: str = "md5") -> Column:
    if not 0 <= m <= 1:
        raise ValueError("the ratio must be between 0 and 1")
    return below(hash32(key_text(df, key), salt, family), m, family)


def key_hash_filter(df: DataFrame, key: list[str] | str, m: float, salt: str = SALT, family: str = "md5") -> DataFrame:
    """Rows whose key hash is below m. Ratio 1 keeps all without a predicate, 0 keeps none."""
    key = [key] if isinstance(key, str) else list(key)
    if m >= 1:
        return df
    return df.filter(in_sample(df, key, m, salt, family))


def hash_band(df: DataFrame, key: list[str], salt: str = SALT, family: str = "md5") -> Column:
    """First byte of the key hash: the partition column of views and samples."""
    h = hash32(key_text(df, key), salt, family)
    return F.conv(F.substring(h, 1, 2), 16, 10).cast("int") if family in ("md5", "sha2_256") else F.shiftrightunsigned(h, 24).cast("int")


def band_filter(df: DataFrame, key: list[str], m: float, salt: str = SALT, band: str = "hash_band", family: str = "md5") -> DataFrame:
    """The exact filter plus the band bound, which prunes partitions of a banded table."""
    if m >= 1:
        return df
    return df.filter(F.col(band) <= math.floor(m * BANDS)).filter(in_sample(df, key, m, salt, family))


@dataclass(frozen=True)
class Banded:
    """A stored table whose partition column ``hash_band`` is the first byte of its key hash."""

    df: DataFrame
    key: tuple[str, ...]
    salt: str = SALT
    family: str = "md5"

    def rows(self) -> DataFrame:
        return self.df.drop("hash_band")

    def sample(self, key: tuple[str, ...], m: float, salt: str, family: str) -> DataFrame:
        """The key-hash filter; by bands where it is the filter that the table is banded by."""
        if (tuple(key), salt, family) == (self.key, self.salt, self.family):
            return band_filter(self.df, list(key), m, salt, family=family).drop("hash_band")
        return key_hash_filter(self.rows(), list(key), m, salt, family)


def refine(df: DataFrame, key: list[str], m_from: float, m_to: float, salt: str = SALT) -> DataFrame:
    """The rows that a sample of ratio m_from lacks to become one of ratio m_to."""
    return df.filter(in_sample(df, key, m_to, salt) & ~in_sample(df, key, m_from, salt))


def hash_uniformity(df: DataFrame, key: list[str], buckets: int = 16, salt: str = SALT) -> DataFrame:
    """Rows by equal hash bucket, with the expected count and the bucket's chi-square term."""
    number = F.conv(hash32(key_text(df, list(key)), salt), 16, 10).cast("long")
    counts = df.select(F.floor(number * buckets / 2**32).cast("int").alias("bucket")).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))
    total = counts.agg(F.sum("n").alias("total"))
    expected = F.col("total") / buckets
    return counts.crossJoin(F.broadcast(total)).select("bucket", "n", expected.alias("expected"), ((F.col("n") - expected) * (F.col("n") - expected) / expected).alias("chi2"))


def register_sql_functions(spark: SparkSession) -> None:
    """``key_hash(key, salt)`` and ``in_sample(key, m, salt)`` as SQL functions, which Catalyst inlines."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION key_hash(k STRING, salt STRING) RETURNS STRING RETURN substr(md5(concat(salt, '|', k)), 1, 8)")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION in_sample(k STRING, m DOUBLE, salt STRING) RETURNS BOOLEAN "
        "RETURN m >= 1 OR substr(md5(concat(salt, '|', k)), 1, 8) < lpad(lower(hex(CAST(ceil(m * 4294967296) AS BIGINT))), 8, '0')"
    )
