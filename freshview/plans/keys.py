"""Keys of view rows, their audit, and the provenance of rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .nodes import Aggregate, Difference, Distinct, Intersect, Join, KeyHash, Node, Project, Scan, Select, Union, Windowed


class KeyDropped(ValueError):
    """A projection leaves out a key column."""


def infer_key(node: Node, reduce_fk: bool = False) -> tuple[str, ...]:
    """Columns that identify a row. A global aggregate has the empty key: it is one row."""
    of = lambda n: infer_key(n, reduce_fk)
    match node:
        case Scan():
            if not node.key:
                raise ValueError(f"{node.name} has no key; add a sequence key")
            return node.key
        case Select() | KeyHash() | Windowed():
            return of(node.child)
        case Project():
            names = {e: n for n, e in reversed(node.items)}
            missing = [k for k in of(node.child) if k not in names]
            if missing:
                raise KeyDropped(f"the projection drops {', '.join(missing)}")
            return tuple(names[k] for k in of(node.child))
        case Distinct():
            return tuple(node.columns())
        case Aggregate():
            return node.keys
        case Join():
            if node.how in ("left_semi", "left_anti"):
                return of(node.left)
            if reduce_fk and node.fact in ("left", "right"):
                return of(node.left if node.fact == "left" else node.right)
            left = of(node.left)
            return left + tuple(k for k in of(node.right) if k not in left)
        case Union():
            left = of(node.left)
            return left + tuple(k for k in of(node.right) if k not in left)
        case Intersect():
            both = tuple(k for k in of(node.left) if k in of(node.right))
            if not both:
                raise ValueError("the inputs of an intersection share no key column")
            return both
        case Difference():
            return of(node.left)
    raise TypeError(node)


def repair_key(node: Node) -> Node:
    """Add the dropped key columns back to every projection on the way."""
    match node:
        case Project():
            child = repair_key(node.child)
            have = {e for _, e in node.items}
            more = tuple((k, k) for k in infer_key(child) if k not in have)
            return Project(child, more + node.items)
        case Select():
            return Select(repair_key(node.child), node.condition)
    return node


def audit_key(df: DataFrame, key: tuple[str, ...]) -> DataFrame:
    """One row: rows, distinct keys, and keys that occur more than once."""
    counts = df.groupBy(*key).agg(F.count(F.lit(1)).alias("n")) if key else df.agg(F.count(F.lit(1)).alias("n"))
    return counts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_rows"), F.count(F.lit(1)).alias("n_keys"), F.coalesce(F.sum((F.col("n") > 1).cast("long")), F.lit(0)).alias("n_repeated"))


def lineage(node: Node, keys: DataFrame, leaf: str) -> DataFrame:
    """Rows of a base table that the view rows with the given key values come from.

    The key values reach the leaf as a semi join by the names that key columns have there.
    """
    match node:
        case Scan():
            shared = [c for c in keys.columns if c in node.df.columns]
            return node.df.join(keys.select(*shared).distinct(), shared, "left_semi") if shared and node.name == leaf else node.df
        case Select():
            return lineage(node.child, keys, leaf).filter(node.condition) if not _is_scan_of(node.child, leaf) else lineage(node.child, keys, leaf).filter(node.condition)
        case Project():
            renamed = [(n, e) for n, e in node.items if n in keys.columns and node.source_of(n)]
            return lineage(node.child, keys.select(*[F.col(n).alias(e) for n, e in renamed]), leaf)
        case Join():
            pairs = {a: b for a, b in node.on} | {b: a for a, b in node.on}
            side = node.left if _holds(node.left, leaf) else node.right
            columns = side.columns()
            renamed = {c: c if c in columns else pairs.get(c) for c in keys.columns}
            return lineage(side, keys.select(*[F.col(c).alias(t) for c, t in renamed.items() if t in columns]), leaf)
        case Union() | Intersect() | Difference():
            return lineage(node.left if _holds(node.left, leaf) else node.right, keys, leaf)
    return lineage(node.children()[0], keys, leaf)


def _is_scan_of(node: Node, leaf: str) -> bool:
    return isinstance(node, Scan) and node.name == leaf


def _holds(node: Node, leaf: str) -> bool:
    return _is_scan_of(node, leaf) or any(_holds(c, leaf) for c in node.children())
