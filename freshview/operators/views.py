"""View definitions: additive aggregates or row views over a select-project-join part.

``rows`` builds the select-project-join tree from leaves by table name. Leaves of
changing tables carry a weight column ``w_<table>`` (1 for plain rows, -1 for deleted
ones); the product of the weights is a row's weight, so the same tree serves base rows
and changes.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.nodes import Aggregate, Node, Scan
from ..sources.changes import ChangeSet

COUNT = "__cnt"


@dataclass(frozen=True)
class View:
    """``sums``: (name, SQL over the rows) to be summed by ``keys``; (name, "1") counts. A row view has no sums."""

    name: str
    keys: tuple[str, ...]
    sums: tuple[tuple[str, str], ...]
    rows: Callable[[dict[str, Node]], Node]
    tables: tuple[str, ...]

    def leaves(self, frames: dict[str, DataFrame], kinds: dict[str, str] | None = None, keys: dict[str, tuple[str, ...]] | None = None) -> dict[str, Node]:
        out = {}
        for t in self.tables:
            df = frames[t]
            if f"w_{t}" not in df.columns:
                df = df.withColumn(f"w_{t}", F.lit(1))
            out[t] = Scan(t, df, (keys or {}).get(t, ()), (kinds or {}).get(t, "base"))
        return out

    def weight(self) -> str:
        return " * ".join(f"w_{t}" for t in self.tables)

    def signed(self, rows: Node) -> Node:
        """Weighted sums of rows by key, with the hidden row count."""
        weight = self.weight()
        aggs = tuple((n, f"sum(({e}) * ({weight}))") for n, e in self.sums)
        return Aggregate(rows, self.keys, (*aggs, (COUNT, f"sum({weight})")))

    def plan(self, frames: dict[str, DataFrame], keys: dict[str, tuple[str, ...]] | None = None) -> Node:
        return self.signed(self.rows(self.leaves(frames, keys=keys)))

    def visible(self, df: DataFrame) -> DataFrame:
        return df.drop(COUNT)


def new_tables(view: View, changes: ChangeSet) -> dict[str, DataFrame]:
    return {t: changes.new(t) for t in view.tables}
