"""The leakage guard: validity must be decided below any ranking or limit.

The optimized logical plan is walked as a tree. A filter or join condition on a validity
column opens a watch on the inputs that this column comes from; a limit or a top-k rank
found below it means that rows were chosen before their validity was. Ranks that only
number rows are no choice. What a cached relation was made of is not part of the plan."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame

VALIDITY = ("effective_at", "retired_at")
CUTS = {"GlobalLimit", "LocalLimit", "WindowGroupLimit", "Tail", "Offset", "Sample"}
RANKS = {"RowNumber", "Rank", "DenseRank", "NTile", "PercentRank"}


class LeakyPlan(Exception):
    pass


def _each(seq) -> Iterator:
    """The members of a Scala collection."""
    it = seq.iterator()
    while it.hasNext():
        yield it.next()


def _kind(node) -> str:
    return node.getClass().getSimpleName()


def _names(attributes) -> dict[str, str]:
    """Expression id to name."""
    return {str(a.exprId().id()): a.name() for a in _each(attributes)}


def _condition(node):
    """The condition of a filter or join, or None."""
    if _kind(node) == "Filter":
        return node.condition()
    if _kind(node) == "Join" and node.condition().isDefined():
        return node.condition().get()
    return None


def _ranked(node, found: set[str]) -> set[str]:
    """Ids of the rank columns that windows in this tree make."""
    if _kind(node) == "Window":
        for e in _each(node.windowExpressions()):
            if any(f"{r.lower()}(" in e.sql().lower().replace("_", "") for r in RANKS):
                found.add(str(e.exprId().id()))
    for child in _each(node.children()):
        _ranked(child, found)
    return found


def _sources(node, ids: set[str], columns: tuple[str, ...]) -> list:
    """The inputs of node that these columns come from; all, if none shows them."""
    below = list(_each(node.children()))
    shown = [c for c in below if ids & set(_names(c.output())) or set(columns) & set(_names(c.output()).values())]
    return shown or below


def _walk(node, watched: bool, ranks: set[str], columns: tuple[str, ...]) -> None:
    kind, condition = _kind(node), _condition(node)
    used = _names(condition.references()) if condition is not None else {}
    if watched and (kind in CUTS or kind == "Filter" and ranks & set(used)):
        raise LeakyPlan(f"validity is decided above {node.nodeName()}: {node.simpleStringWithNodeId()[:200]}")
    validity = {i for i, name in used.items() if name in columns}
    if validity:
        sides = _sources(node, validity, columns)
        for child in _each(node.children()):
            _walk(child, watched or any(child.equals(s) for s in sides), ranks, columns)
        return
    for child in _each(node.children()):
        _walk(child, watched, ranks, columns)


def assert_guard(df: DataFrame, columns: tuple[str, ...] = VALIDITY) -> DataFrame:
    """df itself, unless its plan decides validity above a limit or a top-k rank."""
    plan = df._jdf.queryExecution().optimizedPlan()
    _walk(plan, False, _ranked(plan, set()), columns)
    return df


def physical(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()
