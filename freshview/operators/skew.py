"""Long tails derived inside a query, since the given tables are read-only and uniform."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.hashing import encode_key


def unit(key: list[str], salt: str = "z") -> Column:
    """A value in (0, 1] by the hash of a key."""
    head = F.substring(F.md5(F.concat(F.lit(f"{salt}|"), encode_key([F.col(k) for k in key]))), 1, 8)
    return (F.conv(head, 16, 10).cast("double") + 1) / 2**32


def tailed(value: Column, u: Column, z: float) -> Column:
    """A power tail; z = 1 leaves the value as it is."""
    return F.round(value * F.pow(u, F.lit(-(z - 1) / 4)), 2)


def popular(keys: int, u: Column, z: float) -> Column:
    """A key in 0..keys-1 whose popularity falls with the key."""
    return F.floor(F.lit(keys) * F.pow(u, F.lit(float(z)))).cast("bigint")
