"""Rewrites of the logical plan: cheap predicates first, NL filters in rank order and below NL joins."""

from __future__ import annotations

from dataclasses import replace

from .nodes import NLFilter, NLJoin, NLProject, Node, Source, Where, with_child


def _rank(f: NLFilter) -> float:
    """Cost per row removed; lower goes first."""
    return f.cost / max(1 - f.selectivity, 1e-9)


def _swap(upper: Node) -> Node | None:
    """The same two steps the other way round, where that is right and cheaper."""
    if not isinstance(upper, Where | NLFilter):
        return None
    lower = upper.child
    if isinstance(upper, Where) and isinstance(lower, NLFilter):
        return with_child(lower, with_child(upper, lower.child))
    if isinstance(lower, NLProject) and lower.out not in upper.reads():
        return with_child(lower, with_child(upper, lower.child))
    if isinstance(upper, NLFilter) and isinstance(lower, NLFilter) and _rank(upper) < _rank(lower):
        return with_child(lower, with_child(upper, lower.child))
    if isinstance(lower, NLJoin) and upper.reads() and upper.reads() <= set(lower.left_only):
        return replace(lower, left=with_child(upper, lower.left))
    return None


def rewrite(node: Node) -> Node:
    """Apply the swaps until none is left."""
    if isinstance(node, Source):
        return node
    if isinstance(node, NLJoin):
        return replace(node, left=rewrite(node.left), right=rewrite(node.right))
    node = with_child(node, rewrite(node.child))
    swapped = _swap(node)
    return rewrite(swapped) if swapped is not None else node
