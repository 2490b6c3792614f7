"""Change sets: inserts and deletes of base tables, as frames with a weight of +1 or -1.

An update is a delete and an insert. Deterministic splits take a table as the universe
and decide by the hash of its key what is inserted, deleted or updated. The salt of the
split must differ from the sampling salt, or samples would hold all or no changes.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import SALT, hash32, hex8, key_text

CHANGE_SALT = "d0"


def split_hash(df: DataFrame, key: list[str], salt: str = CHANGE_SALT) -> Column:
    if salt == SALT:
        raise ValueError("the change split must not use the sampling salt")
    return hash32(key_text(df, list(key)), salt)


@dataclass
class ChangeSet:
    """Old tables and their pending changes; a table without changes is static."""

    old: dict[str, DataFrame]
    inserted: dict[str, DataFrame] = field(default_factory=dict)
    deleted: dict[str, DataFrame] = field(default_factory=dict)

    @property
    def tables(self) -> list[str]:
        return [t for t in self.old if t in self.inserted or t in self.deleted]

    def delta(self, table: str) -> DataFrame:
        """Changes of a table with column ``w_<table>``: +1 inserted, -1 deleted."""
        parts = [f[table].withColumn(f"w_{table}", F.lit(w)) for f, w in ((self.inserted, 1), (self.deleted, -1)) if table in f]
        return parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])

    def new(self, table: str) -> DataFrame:
        """The table with its changes applied."""
        if table in self.current:
            return self.current[table]
        out = self.old[table]
        if table in self.deleted:
            out = out.join(self.deleted[table].select(*self.key_of(table)), list(self.key_of(table)), "left_anti").select(*out.columns)
        return out.unionByName(self.inserted[table]) if table in self.inserted else out

    keys: dict[str, tuple[str, ...]] = field(default_factory=dict)
    #: Groups of tables whose changes only join with each other's (whole orders with their lines).
    together: tuple[frozenset[str], ...] = ()
    #: Tables with their changes applied, where they are at hand and need not be put together.
    current: dict[str, DataFrame] = field(default_factory=dict)

    def key_of(self, table: str) -> tuple[str, ...]:
        return self.keys[table]

    def is_stale(self) -> bool:
        """Whether some change relation holds a row."""
        return any(not f.isEmpty() for part in (self.inserted, self.deleted) for f in part.values())

    @classmethod
    def from_split(cls, tables: dict[str, DataFrame], key: dict[str, tuple[str, ...]], shares: dict[str, tuple[float, float]], by: dict[str, tuple[str, ...]] | None = None, update: dict[str, tuple] | None = None) -> ChangeSet:
        """``shares`` has (inserted, deleted) by table; ``by`` the columns whose hash decides (the key by default).

        ``update`` has (from, to, function) by table: rows with a hash there are deleted and
        inserted as the function returns them.
        """
        out = cls(dict(tables), keys=dict(key))
        for t, (inserted, deleted) in shares.items():
            df = tables[t]
            h = split_hash(df, list((by or {}).get(t, key[t])))
            if inserted > 0:
                out.inserted[t] = df.filter(h < hex8(inserted))
                out.old[t] = df.filter(h >= hex8(inserted))
            if deleted > 0:
                out.deleted[t] = df.filter(h >= hex8(1 - deleted))
            if t not in (update or {}):
                out.current[t] = df.filter((h < hex8(inserted)) | (h < hex8(1 - deleted))) if deleted > 0 else df
        for t, (low, high, change) in (update or {}).items():
            df = tables[t]
            h = split_hash(df, list(key[t]))
            hit = df.filter((h >= hex8(low)) & (h < hex8(high)))
            out.deleted[t] = out.deleted[t].unionByName(hit) if t in out.deleted else hit
            out.inserted[t] = out.inserted[t].unionByName(change(hit)) if t in out.inserted else change(hit)
        return out

    @classmethod
    def from_time(cls, table: str, df: DataFrame, key: tuple[str, ...], ts: str, cut) -> ChangeSet:
        """Rows before the cut are the base, later ones are inserted."""
        return cls({table: df.filter(F.col(ts) < cut)}, {table: df.filter(F.col(ts) >= cut)}, keys={table: key})

    @classmethod
    def from_batches(cls, table: str, base: DataFrame, batches: list[DataFrame], key: tuple[str, ...]) -> ChangeSet:
        out = cls({table: base}, keys={table: key})
        if batches:
            whole = batches[0]
            for b in batches[1:]:
                whole = whole.unionByName(b)
            out.inserted[table] = whole
        return out
