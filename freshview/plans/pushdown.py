"""Push-down of the key-hash filter: one rule a node kind.

Each rule either names the children that get the filter, with the key as it is called
there, or says why the filter stays above. Catalyst knows many of these moves itself;
the rewriter adds the right sides of set operations, semi and anti joins, both sides of
full outer joins, and foreign keys. The sample is the same rows either way.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from .nodes import Aggregate, Difference, Distinct, Intersect, Join, KeyHash, Node, Project, Scan, Select, Union, Windowed


@dataclass(frozen=True)
class Blocked:
    reason: str


@dataclass(frozen=True)
class Pushed:
    """Child field -> key columns there."""

    to: dict[str, tuple[str, ...]]
    rule: str


@dataclass(frozen=True)
class Step:
    node: str
    outcome: str
    detail: str


def rule_select(node: Select, key):
    return Pushed({"child": key}, "selection")


def rule_project(node: Project, key):
    names = [node.source_of(k) for k in key]
    if None in names:
        return Blocked(f"{key[names.index(None)]} is computed or not projected")
    return Pushed({"child": tuple(names)}, "projection")


def rule_aggregate(node: Aggregate, key):
    outside = [k for k in key if k not in node.keys]
    return Blocked(f"{outside[0]} is not a grouping column") if outside else Pushed({"child": key}, "aggregation")


def rule_distinct(node: Distinct, key):
    return Pushed({"child": key}, "distinct")


def rule_window(node: Windowed, key):
    outside = [k for k in key if k not in node.partition]
    return Blocked(f"{outside[0]} does not partition the window") if outside else Pushed({"child": key}, "window")


def rule_union(node: Union, key):
    return Pushed({"left": key, "right": key}, "union")


def rule_intersect(node: Intersect, key):
    return Pushed({"left": key, "right": key}, "intersection")


def rule_difference(node: Difference, key):
    return Pushed({"left": key, "right": key}, "difference")


def rule_join_equi(node: Join, key):
    """The key consists of join columns: both inputs."""
    to_right = {a: b for a, b in node.on}
    to_left = {b: a for a, b in node.on}
    same = all(a == b for a, b in node.on)
    if node.how == "inner" or (node.how == "full" and same):
        if all(k in to_right or k in to_left for k in key):
            return Pushed({"left": tuple(k if k in to_right else to_left[k] for k in key), "right": tuple(to_right.get(k, k) for k in key)}, "equality join")
    if node.how == "left" and all(k in to_right for k in key):
        return Pushed({"left": key, "right": tuple(to_right[k] for k in key)}, "equality join")
    if node.how == "right" and all(k in to_left for k in key):
        return Pushed({"left": tuple(to_left[k] for k in key), "right": key}, "equality join")
    return None


def rule_semi_anti(node: Join, key):
    if node.how not in ("left_semi", "left_anti"):
        return None
    to_right = {a: b for a, b in node.on}
    if all(k in to_right for k in key):
        return Pushed({"left": key, "right": tuple(to_right[k] for k in key)}, "semi or anti join")
    return Pushed({"left": key}, "semi or anti join, left input only")


def rule_join_fk(node: Join, key):
    """A foreign key stands in for the dimension's key, so the fact side can be filtered."""
    if node.fact not in ("left", "right") or node.how != "inner":
        return None
    pairs = {b: a for a, b in node.on} if node.fact == "left" else {a: b for a, b in node.on}
    fact = node.left if node.fact == "left" else node.right
    names = tuple(pairs.get(k, k) for k in key)
    return Pushed({node.fact: names}, "foreign key join") if set(names) <= set(fact.columns()) else None


def rule_join_one_side(node: Join, key):
    left, right = set(node.left.columns()), set(node.right.columns())
    if set(key) <= left and node.how in ("inner", "left"):
        return Pushed({"left": key}, "key of one input")
    if set(key) <= right and node.how in ("inner", "right"):
        return Pushed({"right": key}, "key of one input")
    return None


def rule_join_block(node: Join, key):
    return Blocked("the key needs both inputs of a join")


def rule_join(node: Join, key):
    for rule in (rule_semi_anti, rule_join_equi, rule_join_fk, rule_join_one_side):
        if (found := rule(node, key)) is not None:
            return found
    return rule_join_block(node, key)


RULES = {Select: rule_select, Project: rule_project, Aggregate: rule_aggregate, Distinct: rule_distinct, Windowed: rule_window, Union: rule_union, Intersect: rule_intersect, Difference: rule_difference, Join: rule_join}


def push(plan: Node, h: KeyHash | None = None) -> tuple[Node, list[Step]]:
    """Move key-hash filters of a plan down as far as the rules allow; the new plan and a report by node."""
    if isinstance(plan, KeyHash) and h is None:
        return push(plan.child, plan)
    steps: list[Step] = []
    if h is None:
        changed = {}
        for name, value in vars(plan).items():
            if isinstance(value, Node):
                changed[name], more = push(value)
                steps += more
        return (replace(plan, **changed) if changed else plan), steps
    if isinstance(plan, Scan):
        return h.around(plan), [Step(plan.label(), "reached", ", ".join(h.key))]
    if isinstance(plan, KeyHash):
        inner, steps = push(plan.child, h)
        return plan.around(inner), steps
    outcome = RULES[type(plan)](plan, h.key)
    if isinstance(outcome, Blocked):
        below, steps = push(plan)
        return h.around(below), [Step(plan.label(), "blocked", outcome.reason), *steps]
    changed = {}
    for name, key in outcome.to.items():
        changed[name], more = push(getattr(plan, name), h.around(plan, key))
        steps += more
    return replace(plan, **changed), [Step(plan.label(), "pushed", outcome.rule), *steps]


def explain_pushdown(plan: Node, key: tuple[str, ...], m: float, salt: str = "s1") -> list[Step]:
    return push(KeyHash(plan, key, m, salt))[1]


def same_sample(plan: Node, key: tuple[str, ...], m: float, salt: str = "s1") -> bool:
    """Whether the sample is the same rows before and after the push-down."""
    whole = KeyHash(plan, key, m, salt)
    above, below = whole.lower(), push(whole)[0].lower()
    below = below.select(*above.columns)
    return above.exceptAll(below).isEmpty() and below.exceptAll(above).isEmpty()


def sampled_leaves(plan: Node, key: tuple[str, ...], m: float = 0.5, salt: str = "s1") -> set[str]:
    """Names of the base tables that the filter reaches: the eligible ones for an outlier index."""
    return {s.node.split(" ", 2)[2] for s in explain_pushdown(plan, key, m, salt) if s.outcome == "reached"}
