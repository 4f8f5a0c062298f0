"""Evaluate a view tree under a ring: partial sums per table, then joins and sums up to the root."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..plans.tree import ViewNode, ViewTree
from .rings import Ring, View


def leaf_view(node: ViewNode, tree: ViewTree, ring: Ring, df: DataFrame) -> View:
    """Rows of a table, or of its delta, summed by its join variables."""
    return ring.leaf(tree.spec.rows(node.alias, df), node.keys, node.attrs)


def leaf_rows(node: ViewNode, tree: ViewTree, ring: Ring, df: DataFrame) -> View:
    """The same unsummed: sums wait for those of the view above."""
    return ring.single(tree.spec.rows(node.alias, df), node.keys, node.attrs)


def inner_view(node: ViewNode, ring: Ring, children: list[View], broadcast_first: bool = False) -> View:
    """The children joined and multiplied, then summed to the node's keys."""
    return ring.combined(children, node.keys, "a" if broadcast_first else None)


def evaluate(tree: ViewTree, tables: dict[str, DataFrame], ring: Ring, at: ViewNode | None = None) -> View:
    """The root's payload (or another view's), from the tables, as one lazy plan."""
    node = at or tree.root
    if node.alias is not None:
        return leaf_view(node, tree, ring, tables[node.alias])
    return inner_view(node, ring, [evaluate(tree, tables, ring, c) for c in node.children])
