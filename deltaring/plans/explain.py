"""What a view tree will do: its views, their SQL, the path of an update, and moment cells for display."""

from __future__ import annotations

import uuid
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.evaluate import evaluate
from ..operators.rings import CountRing
from .spec import CAT, QuerySpec
from .tree import ViewNode, ViewTree


def _dense_leaf(spec: QuerySpec, node: ViewNode, ring: str) -> list[str]:
    value = {a.name: a.sql for a in spec.attributes}
    attrs = sorted(node.attrs)
    out = ["CAST(SUM(mult) AS BIGINT) AS c"]
    if ring == "moments":
        x = lambda a: f"CAST({value[a]} AS DOUBLE)"
        out += [f"SUM(mult * {x(a)}) AS s_{a}" for a in attrs]
        out += [f"SUM(mult * {x(a)} * {x(b)}) AS q_{a}__{b}" for i, a in enumerate(attrs) for b in attrs[i:]]
    return out


def _dense_inner(node: ViewNode, ring: str, at: dict[str, str]) -> list[str]:
    count = lambda cs: " * ".join(f"{at[c.name]}.c" for c in cs) or "1"
    of = {a: c for c in node.children for a in c.attrs}
    rest = lambda *skip: [f"{at[c.name]}.c" for c in node.children if c not in skip]
    out = [f"CAST(SUM({count(node.children)}) AS BIGINT) AS c"]
    if ring == "moments":
        attrs = sorted(node.attrs)
        out += [f"SUM({' * '.join([f'{at[of[a].name]}.s_{a}', *rest(of[a])])}) AS s_{a}" for a in attrs]
        for i, a in enumerate(attrs):
            for b in attrs[i:]:
                first = [f"{at[of[a].name]}.q_{a}__{b}"] if of[a] is of[b] else [f"{at[of[a].name]}.s_{a}", f"{at[of[b].name]}.s_{b}"]
                out.append(f"SUM({' * '.join([*first, *rest(of[a], of[b])])}) AS q_{a}__{b}")
    return out


# Payloads with categories are rows: the term's factors (attribute and category, "" where there is none), v and n.
_TERM = ("a1", "k1", "a2", "k2")


def _mixed_leaf(spec: QuerySpec, node: ViewNode, keys: list[str], columns: list[str], source: str) -> str:
    attrs = [a for a in sorted(spec.attributes, key=lambda a: a.name) if a.name in node.attrs]
    out = []
    for some in [(), *[(a,) for a in attrs], *[(a, b) for i, a in enumerate(attrs) for b in attrs[i:] if a is not b or a.kind != CAT]]:
        text = lambda a: f"CAST({a.sql} AS VARCHAR(255))" if a.kind == CAT else "CAST(NULL AS VARCHAR(255))"
        shown = [x for a in some for x in (f"'{a.name}'", text(a))] + ["''", "CAST(NULL AS VARCHAR(255))"] * (2 - len(some))
        v = " * ".join(["mult", *[f"CAST({a.sql} AS DOUBLE)" for a in some if a.kind != CAT]])
        group = [*columns, *[text(a) for a in some if a.kind == CAT]]
        named = [f"{x} AS {c}" for x, c in zip(shown, _TERM)]
        out.append(f"SELECT {', '.join([*keys, *named])}, SUM({v}) AS v, CAST(SUM(mult) AS BIGINT) AS n FROM {source}{' GROUP BY ' + ', '.join(group) if group else ' HAVING COUNT(*) > 0'}")
    return " UNION ALL ".join(f"({x})" if "HAVING" in x else x for x in out)


def _mixed_inner(node: ViewNode, at: dict[str, str]) -> str:
    """Children are multiplied one after the other; terms of more than two factors are left out."""
    source, seen = at[node.children[0].name], list(node.children[0].keys)
    for i, c in enumerate(node.children[1:]):
        shared = [k for k in c.keys if k in seen]
        keys = [f"l.{k}" for k in seen] + [f"r.{k}" for k in c.keys if k not in seen]
        seen += [k for k in c.keys if k not in seen]
        two = "l.a1 <> '' AND r.a1 <> ''"
        first = lambda x: f"CASE WHEN {two} THEN CASE WHEN l.a1 < r.a1 THEN l.{x} ELSE r.{x} END WHEN l.a1 <> '' THEN l.{x} ELSE r.{x} END AS {x}"
        second = lambda x, y: f"CASE WHEN {two} THEN CASE WHEN l.a1 < r.a1 THEN r.{y} ELSE l.{y} END WHEN l.a1 <> '' THEN l.{x} ELSE r.{x} END AS {x}"
        term = [first("a1"), first("k1"), second("a2", "a1"), second("k2", "k1")]
        fits = "NOT (l.a2 <> '' AND r.a1 <> '') AND NOT (l.a1 <> '' AND r.a2 <> '')"
        left = source if i == 0 else f"({source})"
        source = f"SELECT {', '.join([*keys, *term])}, l.v * r.v AS v, l.n * r.n AS n FROM {left} l JOIN {at[c.name]} r ON {' AND '.join(f'l.{k} = r.{k}' for k in shared)} WHERE {fits}"
    inner = f"({source})" if len(node.children) > 1 else source
    columns = [*node.keys, *_TERM]
    return f"SELECT {', '.join(columns)}, SUM(v) AS v, CAST(SUM(n) AS BIGINT) AS n FROM {inner} p GROUP BY {', '.join(columns)}"


def view_sql(tree: ViewTree, node: ViewNode, ring: str = "moments", names: dict[str, str] | None = None, source: str | None = None) -> str:
    """SQL of one view over the views below it or its table.

    ring: "count", "moments", or "mixed" for payloads with categories, which are rows of terms. names: what views are
    called, if not as in the tree. source: the relation a leaf reads, if not its table; it then has a column mult.
    """
    spec, at = tree.spec, {n.name: n.name for n in tree.nodes()} | (names or {})
    if ring == "moments" and any(a.kind == CAT for a in spec.attributes):
        raise ValueError("payloads with categories are emitted with ring='mixed'")
    if node.alias is not None:
        free = [f for f in spec.free if f.table == node.alias]
        keys = [f"{c} AS {v}" for v, c in spec.table_variables(node.alias).items() if v in node.keys] + [f"{f.sql} AS {f.name}" for f in free]
        columns = [*spec.table_variables(node.alias).values(), *[f.sql for f in free]]
        where = f" WHERE {spec.where[node.alias]}" if node.alias in spec.where else ""
        table = source or f"(SELECT *, 1 AS mult FROM {spec.tables[node.alias]}) t"
        if ring == "mixed":
            return _mixed_leaf(spec, node, keys, columns, f"{table}{where}")
        return f"SELECT {', '.join([*keys, *_dense_leaf(spec, node, ring)])} FROM {table}{where}{' GROUP BY ' + ', '.join(columns) if columns else ''}"
    if ring == "mixed":
        return _mixed_inner(node, at)
    seen, joins = set(node.children[0].keys), at[node.children[0].name]
    for c in node.children[1:]:
        joins += f" JOIN {at[c.name]} USING ({', '.join(k for k in c.keys if k in seen)})"
        seen |= set(c.keys)
    return f"SELECT {', '.join([*node.keys, *_dense_inner(node, ring, at)])} FROM {joins}{' GROUP BY ' + ', '.join(node.keys) if node.keys else ''}"


def script_sql(tree: ViewTree, ring: str = "moments", upto: ViewNode | None = None) -> str:
    """One statement for a view (the root), with the views below it as common table expressions."""
    node = upto or tree.root
    below = [f"{n.name} AS ({view_sql(tree, n, ring)})" for n in node.nodes() if n is not node]
    return (f"WITH {', '.join(below)} " if below else "") + view_sql(tree, node, ring)


def explain_tree(spark: SparkSession, tree: ViewTree, updatable: tuple[str, ...] | None = None, ring: str = "count") -> DataFrame:
    """view, parent, keys, summed_out, attributes, kept, sql: a row per view, children first."""
    kept = {n.name for n in tree.materialised(updatable)}
    rows = [(n.name, n.parent.name if n.parent else None, ",".join(n.keys), n.summed, ",".join(n.attrs), n.name in kept, view_sql(tree, n, ring)) for n in tree.nodes()]
    return spark.createDataFrame(rows, "view string, parent string, keys string, summed_out string, attributes string, kept boolean, sql string")


def view_keys(tree: ViewTree, tables: dict[str, DataFrame], nodes: list[ViewNode]) -> DataFrame:
    """view, n_keys: how many keys each of these views has over the tables (or over a bulk in one's place)."""
    ring = CountRing(tree.spec)
    parts = [evaluate(tree, tables, ring, n).df.agg(F.count(F.lit(1)).alias("n_keys")).select(F.lit(n.name).alias("view"), "n_keys") for n in nodes]
    return reduce(DataFrame.unionByName, parts)


def delta_steps(tree: ViewTree, alias: str, ring: str = "count") -> list[tuple[ViewNode, str]]:
    """The views an update of a table changes, in order, with the SQL of their change: the delta of a view is d_<view>,
    that of the table d_<alias>, whose rows have a signed mult."""
    out, path = [], tree.path(alias)
    for i, n in enumerate(path):
        names = {path[i - 1].name: f"d_{path[i - 1].name}"} if i else None
        out.append((n, view_sql(tree, n, ring, names, f"d_{alias}" if i == 0 else None)))
    return out


def explain_delta(spark: SparkSession, tree: ViewTree, alias: str, ring: str = "count") -> DataFrame:
    """step, view, siblings, keys, sql of delta_steps."""
    path = tree.path(alias)
    rows = [(i + 1, n.name, ",".join(c.name for c in n.children if i and c is not path[i - 1]), ",".join(n.keys), sql) for i, (n, sql) in enumerate(delta_steps(tree, alias, ring))]
    return spark.createDataFrame(rows, "step int, view string, siblings string, keys string, sql string")


def run_sql(spark: SparkSession, tree: ViewTree, tables: dict[str, DataFrame], ring: str = "moments") -> DataFrame:
    """The root by the emitted SQL alone. Temporary views get names of their own; none of the caller's is touched."""
    mark = uuid.uuid4().hex[:8]
    names = {n.name: f"{n.name}_{mark}" for n in tree.nodes()}
    for n in tree.nodes():
        source = None
        if n.alias is not None:
            source = f"t_{n.alias}_{mark}"
            df = tables[n.alias]
            (df if "mult" in df.columns else df.withColumn("mult", F.lit(1))).createOrReplaceTempView(source)
        spark.sql(view_sql(tree, n, ring, names, source)).createOrReplaceTempView(names[n.name])
    return spark.table(names[tree.root.name])


def moment_cells(spec: QuerySpec, entries: DataFrame) -> DataFrame:
    """attr_u, attr_v, rank, n_entries, cell: a cell's tensor rank is its number of categorical attributes (a diagonal cell counts one)."""
    cats = [a.name for a in spec.attributes if a.kind == CAT]
    one = lambda c: F.col(c).isin(cats).cast("int") if cats else F.lit(0)
    rank = F.when(F.col("attr_u") == F.col("attr_v"), one("attr_u")).otherwise(one("attr_u") + one("attr_v"))
    cell = F.map_from_entries(F.collect_list(F.struct(F.struct("cat_u", "cat_v"), "value")))
    return entries.groupBy("attr_u", "attr_v", rank.alias("rank")).agg(F.count("*").alias("n_entries"), cell.alias("cell"))
