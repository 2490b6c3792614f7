"""Refresh of views: recomputation, change tables, signed union, row views, touched groups."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame

from ..functions.hashing import Banded
from ..plans.nodes import Aggregate, Join, KeyHash, Node, Project, Scan, Select, Union
from ..plans.pushdown import push
from ..sources.changes import ChangeSet
from .views import COUNT, View, new_tables


def recompute(view: View, changes: ChangeSet) -> Node:
    """The definition over the changed tables."""
    return view.plan(new_tables(view, changes), changes.keys)


def stale_plan(view: View, changes: ChangeSet) -> Node:
    """The definition over the old tables."""
    return view.plan(changes.old, changes.keys)


def join_delta(view: View, changes: ChangeSet) -> list[Node]:
    """Change rows of the select-project-join part: one term for every non-empty set of changed tables.

    Two changed inputs give three terms: old with changes, changes with old, changes with
    changes. Of tables whose changes only join with each other, the terms with some of them
    are empty and left out.
    """
    changed = [t for t in view.tables if t in changes.tables]
    terms = []
    for n in range(1, len(changed) + 1):
        for some in combinations(changed, n):
            if any(0 < len(g & set(some)) < len(g & set(changed)) for g in changes.together):
                continue
            frames = {t: changes.delta(t) if t in some else changes.old[t] for t in view.tables}
            terms.append(view.rows(view.leaves(frames, {t: "changes" for t in some}, changes.keys)))
    return terms


def delta_view(view: View, changes: ChangeSet) -> Node:
    """The view's signed aggregates over the changes alone."""
    parts = [view.signed(rows) for rows in join_delta(view, changes)]
    whole = parts[0]
    for p in parts[1:]:
        whole = Union(whole, p, bag=True)
    if len(parts) == 1:
        return whole
    return Aggregate(whole, view.keys, tuple((n, f"sum({n})") for n in [*[n for n, _ in view.sums], COUNT]))


def _stale_leaf(view: View, stale: DataFrame | Banded) -> Node:
    return Scan(view.name, stale, view.keys, "stale")


def signed_union_refresh(view: View, stale: DataFrame, changes: ChangeSet) -> Node:
    """Stale aggregates and signed change aggregates, summed again by key; groups without rows go."""
    names = [*[n for n, _ in view.sums], COUNT]
    items = tuple((c, c) for c in (*view.keys, *names))
    both = Project(_stale_leaf(view, stale), items)
    for rows in join_delta(view, changes):
        both = Union(both, Project(view.signed(rows), items), bag=True)
    return Select(Aggregate(both, view.keys, tuple((n, f"sum({n})") for n in names)), f"{COUNT} > 0")


def change_table_refresh(view: View, stale: DataFrame, changes: ChangeSet) -> Node:
    """Full outer join of the stale view with the view of the changes; null counts as zero."""
    names = [*[n for n, _ in view.sums], COUNT]
    delta = Project(delta_view(view, changes), tuple((k, k) for k in view.keys) + tuple((f"d_{n}", n) for n in names))
    merged = Join(_stale_leaf(view, stale), delta, tuple((k, k) for k in view.keys), "full")
    added = Project(merged, tuple((k, k) for k in view.keys) + tuple((n, f"coalesce({n}, 0) + coalesce(d_{n}, 0)") for n in names))
    return Select(added, f"{COUNT} > 0")


def spj_refresh(stale: DataFrame | Banded, inserted: DataFrame | Node, deleted_keys: DataFrame | None, key: tuple[str, ...], name: str = "view") -> Node:
    """A view without aggregates: deleted keys leave, inserted rows (a frame, or a tree of the view's columns) are appended."""
    on = tuple((k, k) for k in key)
    kept = Scan(name, stale, key, "stale")
    if not isinstance(inserted, Node):
        inserted = Scan("inserted", inserted.select(*kept.columns()), key, "changes")
    if deleted_keys is not None:
        kept = Join(kept, Scan("deleted", deleted_keys.select(*key), key, "changes"), on, "left_anti")
    return Union(kept, inserted, bag=True)


def touched_group_refresh(keys: tuple[str, ...], aggs: tuple[tuple[str, str], ...], stale: DataFrame, new_rows: DataFrame, changed_rows: DataFrame, name: str = "view") -> Node:
    """For min, max, median, distinct counts: groups with a changed row are computed anew from the base."""
    on = tuple((k, k) for k in keys)
    touched = Aggregate(Scan("changes", changed_rows, keys, "changes"), keys, (("__n", "count(1)"),))
    names = Project(touched, tuple((k, k) for k in keys))
    again = Aggregate(Join(Scan("rows", new_rows, keys, "base"), names, on, "left_semi"), keys, aggs)
    kept = Join(Scan(name, stale, keys, "stale"), names, on, "left_anti")
    columns = tuple((c, c) for c in (*keys, *[n for n, _ in aggs]))
    return Union(Project(kept, columns), Project(again, columns), bag=True)


STRATEGIES = {"signed_union": signed_union_refresh, "change_table": change_table_refresh}


def refresh_plan(view: View, stale: DataFrame, changes: ChangeSet, strategy: str = "signed_union") -> Node:
    return recompute(view, changes) if strategy == "recompute" else STRATEGIES[strategy](view, stale, changes)


def refresh(view: View, stale: DataFrame | Banded, changes: ChangeSet, strategy: str = "signed_union") -> DataFrame:
    return refresh_plan(view, stale, changes, strategy).lower()


def refresh_sample(view: View, stale: DataFrame | Banded, changes: ChangeSet, m: float, salt: str = "s1", strategy: str = "signed_union", sample_key: tuple[str, ...] | None = None, family: str = "md5") -> DataFrame:
    """The fresh sample: the refresh plan with the key-hash filter pushed from its root to its leaves."""
    plan = KeyHash(refresh_plan(view, stale, changes, strategy), sample_key or view.keys, m, salt, family)
    return push(plan)[0].lower()
