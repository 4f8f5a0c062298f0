"""Query results kept factorised over the views of a tree, and read from them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.tree import ViewNode, ViewTree
from .rings import CountRing, ListingRing
from .evaluate import evaluate


def factorised_views(tree: ViewTree, tables: dict[str, DataFrame], listed: tuple[str, ...]) -> dict[str, DataFrame]:
    """alias -> keys, listed attributes, mult: each table's distinct tuples without those that are in no result row.

    Going up, a view keeps the keys under which all tables below it join; going down, those of its children that
    join with what is alive above and with each other. The subtrees of a view share nothing but its keys and
    variable, so what is left is exactly what the result has, for cyclic joins too. Together the tables stand
    for the result, which is never joined out.
    """
    ring = ListingRing(tree.spec, listed)
    views = {n.alias: evaluate(tree, tables, ring, n).df for n in tree.nodes() if n.alias is not None}
    met: dict[str, DataFrame] = {}
    found: dict[str, DataFrame] = {}
    for node in tree.nodes():
        if node.alias is not None:
            found[node.name] = views[node.alias].select(*node.keys).distinct()
            continue
        out, seen = found[node.children[0].name], set(node.children[0].keys)
        for c in node.children[1:]:
            out = out.join(found[c.name], [k for k in c.keys if k in seen])
            seen |= set(c.keys)
        met[node.name] = out
        found[node.name] = out.select(*node.keys).distinct()

    def down(node: ViewNode, alive: DataFrame | None) -> None:
        if node.alias is not None:
            if alive is not None:
                views[node.alias] = views[node.alias].join(alive, list(node.keys), "left_semi")
            return
        kept = met[node.name] if alive is None or not node.keys else met[node.name].join(alive, list(node.keys), "left_semi")
        for c in node.children:
            down(c, kept.select(*c.keys).distinct())

    down(tree.root, None)
    return views


def factorised_size(views: dict[str, DataFrame]) -> int:
    return sum(v.count() for v in views.values())


def result_count(tree: ViewTree, tables: dict[str, DataFrame]) -> DataFrame:
    """c: number of result rows, from counts alone."""
    return evaluate(tree, tables, CountRing(tree.spec)).df


def enumerate_result(tree: ViewTree, tables: dict[str, DataFrame], listed: tuple[str, ...], views: dict[str, DataFrame] | None = None) -> DataFrame:
    """The listed attributes of all result rows with multiplicity, joined top-down from the factorised views."""
    views = views or factorised_views(tree, tables, listed)

    def down(node: ViewNode) -> list[str]:
        return [node.alias] if node.alias is not None else [a for c in node.children for a in down(c)]

    todo, out = down(tree.root), None
    keys_of = {n.alias: n.keys for n in tree.nodes() if n.alias is not None}
    seen: set[str] = set()
    while todo:
        alias = next((a for a in todo if seen & set(keys_of[a])), todo[0])
        todo.remove(alias)
        v = views[alias].withColumnRenamed("mult", f"__m_{alias}")
        out = v if out is None else out.join(v, [k for k in keys_of[alias] if k in seen])
        seen |= set(keys_of[alias])
    mult = None
    for a in keys_of:
        mult = F.col(f"__m_{a}") if mult is None else mult * F.col(f"__m_{a}")
    return out.select(*[a for a in sorted(listed)], mult.alias("mult"))


def is_member(views: dict[str, DataFrame], row: dict[str, object]) -> bool:
    """Whether some result row has these attribute values: each view that lists one must still have it, joined on their keys."""
    out = None
    for v in views.values():
        some = v
        for name, value in row.items():
            if name in v.columns:
                some = some.where(F.col(name).eqNullSafe(F.lit(value)))
        keys = [c for c in some.columns if out is not None and c in out.columns and c != "mult"]
        some = some.drop("mult").distinct()
        out = some if out is None else (out.join(some, keys) if keys else out)
    return out is not None and not out.isEmpty()
