"""Immutable node trees for view definitions and refresh plans.

Expressions are SQL text over column names. The tree exists because neither keys nor
foreign keys of files are known to Catalyst, and outlier sets travel along it; lowering
gives a lazy DataFrame, and everything below is left to Catalyst.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import SALT, Banded, key_hash_filter
from ..sources.tables import plain_unions


@dataclass(frozen=True)
class Node:
    def children(self) -> tuple[Node, ...]:
        return tuple(v for v in vars(self).values() if isinstance(v, Node))

    def lower(self) -> DataFrame:
        raise NotImplementedError

    def columns(self) -> list[str]:
        return self.lower().columns

    def label(self) -> str:
        return type(self).__name__.lower()


@dataclass(frozen=True)
class Scan(Node):
    """A leaf; a banded table is read whole here, and by bands under a filter on its key."""

    name: str
    df: DataFrame | Banded = field(compare=False, repr=False)
    key: tuple[str, ...] = ()
    kind: str = "base"

    def lower(self) -> DataFrame:
        return self.df.rows() if isinstance(self.df, Banded) else self.df

    def label(self) -> str:
        return f"scan {self.kind} {self.name}"


@dataclass(frozen=True)
class Select(Node):
    child: Node
    condition: str

    def lower(self) -> DataFrame:
        return self.child.lower().filter(self.condition)


@dataclass(frozen=True)
class Project(Node):
    child: Node
    items: tuple[tuple[str, str], ...]

    def lower(self) -> DataFrame:
        return self.child.lower().select(*[F.expr(e).alias(n) for n, e in self.items])

    def source_of(self, name: str) -> str | None:
        """The child's column that an output column renames; None if it is computed."""
        expression = dict(self.items).get(name)
        return expression if expression in self.child.columns() else None


@dataclass(frozen=True)
class Join(Node):
    """Equality join on pairs of columns (one output column where both names are equal), or on a condition.

    ``fact`` names the side that holds a foreign key to the other side's key.
    """

    left: Node
    right: Node
    on: tuple[tuple[str, str], ...] = ()
    how: str = "inner"
    fact: str | None = None
    condition: str | None = None
    small: str | None = None

    def lower(self) -> DataFrame:
        left, right = self.left.lower(), self.right.lower()
        if self.small == "right":
            right = F.broadcast(right)
        if not self.on:
            return left.crossJoin(right) if self.condition is None else left.crossJoin(right).filter(self.condition)
        if all(a == b for a, b in self.on):
            return left.join(right, [a for a, _ in self.on], self.how)
        condition = None
        for a, b in self.on:
            test = left[a] == right[b]
            condition = test if condition is None else condition & test
        return left.join(right, condition, self.how)

    def label(self) -> str:
        return f"{self.how} join"


@dataclass(frozen=True)
class Aggregate(Node):
    child: Node
    keys: tuple[str, ...]
    aggs: tuple[tuple[str, str], ...]

    def lower(self) -> DataFrame:
        return self.child.lower().groupBy(*self.keys).agg(*[F.expr(e).alias(n) for n, e in self.aggs])


@dataclass(frozen=True)
class Distinct(Node):
    child: Node

    def lower(self) -> DataFrame:
        return self.child.lower().distinct()


@dataclass(frozen=True)
class Windowed(Node):
    """The child plus computed columns over windows that share their partition columns."""

    child: Node
    partition: tuple[str, ...]
    items: tuple[tuple[str, str], ...]

    def lower(self) -> DataFrame:
        df = self.child.lower()
        return df.select("*", *[F.expr(e).alias(n) for n, e in self.items])


@dataclass(frozen=True)
class Union(Node):
    left: Node
    right: Node
    bag: bool = False

    def lower(self) -> DataFrame:
        both = self.left.lower().unionByName(self.right.lower())
        plain_unions(both.sparkSession)
        return both if self.bag else both.distinct()


@dataclass(frozen=True)
class Intersect(Node):
    left: Node
    right: Node
    bag: bool = False

    def lower(self) -> DataFrame:
        left = self.left.lower()
        right = self.right.lower().select(*left.columns)
        return left.intersectAll(right) if self.bag else left.intersect(right)


@dataclass(frozen=True)
class Difference(Node):
    left: Node
    right: Node
    bag: bool = False

    def lower(self) -> DataFrame:
        left = self.left.lower()
        right = self.right.lower().select(*left.columns)
        return left.exceptAll(right) if self.bag else left.subtract(right)


@dataclass(frozen=True)
class KeyHash(Node):
    child: Node
    key: tuple[str, ...]
    m: float
    salt: str = SALT
    family: str = "md5"

    def lower(self) -> DataFrame:
        if isinstance(self.child, Scan) and isinstance(self.child.df, Banded):
            return self.child.df.sample(self.key, self.m, self.salt, self.family)
        return key_hash_filter(self.child.lower(), list(self.key), self.m, self.salt, self.family)

    def around(self, child: Node, key: tuple[str, ...] | None = None) -> KeyHash:
        return KeyHash(child, key or self.key, self.m, self.salt, self.family)
