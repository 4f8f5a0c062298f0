"""Updates as relations with signed multiplicities, and their way from a leaf to the root."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.tree import ViewTree
from ..sources.store import ViewStore
from .evaluate import inner_view, leaf_rows, leaf_view
from .rings import Ring, View

#: A delta view whose rows, by its number of payload columns and keys, take at most so many bytes is sent to all tasks
#: when it meets its stored siblings.
BROADCAST_BYTES = 64 << 20


def small_enough(ring: Ring, rows: int, attrs: tuple[str, ...], keys: tuple[str, ...]) -> bool:
    return rows * (ring.row_bytes(attrs) + 16 * len(keys)) <= BROADCAST_BYTES


def as_delta(inserts: DataFrame | None = None, deletes: DataFrame | None = None) -> DataFrame:
    """One relation of inserts (+) and deletes (-); a row may come with its own mult."""

    def signed(df: DataFrame, sign: int) -> DataFrame:
        return df.withColumn("mult", (F.col("mult") if "mult" in df.columns else F.lit(1)).cast("long") * F.lit(sign))

    parts = [signed(df, s) for df, s in ((inserts, 1), (deletes, -1)) if df is not None]
    if not parts:
        raise ValueError("an update needs inserts or deletes")
    return reduce(DataFrame.unionByName, parts)


def as_update(old: DataFrame, new: DataFrame) -> DataFrame:
    """Changed rows: the old ones go, the new ones come."""
    return as_delta(new, old)


def consolidate(delta: DataFrame) -> DataFrame:
    """Equal rows folded to one with the sum of their multiplicities; rows that cancel out are gone."""
    columns = [c for c in delta.columns if c != "mult"]
    return delta.groupBy(*columns).agg(F.sum("mult").alias("mult")).where("mult <> 0").select(*delta.columns)


def negative_multiplicities(state: DataFrame) -> DataFrame:
    """Rows deleted more often than they were there, of a base table kept as rows with mult."""
    return consolidate(state).where("mult < 0")


def propagate(store: ViewStore, alias: str, delta: DataFrame, batch: str, rows: int | None = None) -> dict[str, View]:
    """Push one table's delta up its path; the change of each kept view is written to its log and read back.

    At every step the small delta view meets the stored rows of its siblings only. Those are joined as
    they lie, snapshot and deltas unmerged, since the product distributes over their sum. rows: the number
    of delta rows if the caller has counted them; it bounds the leaf's change, which is sent to all tasks if that
    is small in bytes. A small bulk is not summed by key first, the view above sums it anyway. Rows of later
    changes are counted while they are written.
    """
    tree, ring, out = store.tree, store.ring, {}
    change: View | None = None
    below = None
    rows = delta.count() if rows is None else rows
    for node in tree.path(alias):
        if node.alias is not None:
            rows *= ring.rows_per_row(node.attrs)
            plain = node.name not in store.kept and small_enough(ring, rows, node.attrs, node.keys)
            change = (leaf_rows if plain else leaf_view)(node, tree, ring, delta)
        else:
            known = [store.rows(s) if s.name in store.kept else _computed(store, s) for s in node.children if s is not below]
            change = inner_view(node, ring, [change, *known], broadcast_first=rows is not None and small_enough(ring, rows, change.attrs, change.keys))
            rows = None
        if node.name in store.kept:
            change, rows = store.append(node, batch, alias, change)
        out[node.name] = change
        below = node
    return out


def _computed(store: ViewStore, node):
    if node.alias is not None:
        raise ValueError(f"{node.name} is not kept; declare the tables that change when the store is made")
    return inner_view(node, store.ring, [store.rows(c) if c.name in store.kept else _computed(store, c) for c in node.children])


def propagate_all(store: ViewStore, deltas: dict[str, DataFrame], batch: str, rows: dict[str, int] | None = None) -> bool:
    """One bulk over several tables: one after the other, each meeting what the earlier ones changed. False if it was applied before."""
    if not store.begin(batch):
        return False
    for alias, delta in deltas.items():
        propagate(store, alias, delta, batch, (rows or {}).get(alias))
    store.commit(batch)
    return True


def recomputed(tree: ViewTree, ring, tables: dict[str, DataFrame]) -> View:
    from .evaluate import evaluate

    return ring.state(evaluate(tree, tables, ring), tree.root.keys)


def factor_delta(delta: DataFrame, parts: list[list[str]]) -> list[DataFrame] | None:
    """The delta as a product of relations over column groups, with integer mult in each, or None if it isn't one.

    If multiplicities are a product at all, each factor is the slice through any one row, divided by its greatest
    common divisor; what all multiplicities have in common goes to the first factor. So all factors stay
    integers, deletes and bulks that sum to zero included. The check compares sizes and every row.
    """
    whole = consolidate(delta)
    columns = [c for p in parts for c in p]
    top = whole.agg(F.min(F.struct(*columns, "mult")).alias("r"), F.count(F.lit(1)).alias("n")).first()
    if not top["n"]:
        return None
    pivot, factors, divisors = top["r"], [], []
    for p in parts:
        others = [F.col(c).eqNullSafe(F.lit(pivot[c]).cast(whole.schema[c].dataType)) for c in columns if c not in p]
        part = whole.where(reduce(lambda a, b: a & b, others, F.lit(True))).select(*p, "mult")
        divisor = _common_divisor(part)
        divisors.append(divisor)
        factors.append(part.withColumn("mult", F.expr(f"mult div {divisor}L")))
    sizes = 1
    for f in factors:
        sizes *= f.count()
    here = 1
    for d in divisors:
        here *= pivot["mult"] // d
    if sizes != top["n"] or pivot["mult"] % here:
        return None
    factors[0] = factors[0].withColumn("mult", F.col("mult") * F.lit(pivot["mult"] // here))
    back = whole
    for i, (p, f) in enumerate(zip(parts, factors)):
        f = f.select(*[F.col(c).alias(f"__k{i}_{c}") for c in p], F.col("mult").alias(f"__f{i}"))
        back = back.join(f, reduce(lambda a, b: a & b, [F.col(c).eqNullSafe(F.col(f"__k{i}_{c}")) for c in p]))
    product = reduce(F.try_multiply, [F.col(f"__f{i}") for i in range(len(parts))])
    right = back.where(product.eqNullSafe(F.col("mult"))).count()
    return factors if right == top["n"] else None


def _common_divisor(part: DataFrame) -> int:
    """Greatest common divisor of mult: a number per task reaches the driver."""

    def run(batches):
        import numpy as np
        import pandas as pd

        found = 0
        for b in batches:
            found = int(np.gcd.reduce(np.abs(b["mult"].to_numpy(np.int64)), initial=found))
        yield pd.DataFrame({"g": [found]})

    return math.gcd(*[r[0] for r in part.select("mult").mapInPandas(run, "g long").collect()])


def propagate_factored(store: ViewStore, alias: str, factors: list[DataFrame], batch: str) -> dict[str, View]:
    """Push a bulk that is the product of some relations up its path without multiplying it out.

    Each factor becomes a view over its own keys and attributes. At every step only the factors that hold the
    summed variable are multiplied, with the siblings, and summed; the others wait. Factors meet where
    a kept view needs them, at the root as single rows. An attribute must be computable from one factor.
    """
    tree, ring, spec, out = store.tree, store.ring, store.tree.spec, {}
    waiting: list[View] = []
    below = None
    for node in tree.path(alias):
        if node.alias is not None:
            waiting = [ring.leaf(rows, keys, attrs) for rows, keys, attrs in spec.factor_rows(alias, factors, node.keys)]
        else:
            waiting += [store.rows(s) if s.name in store.kept else _computed(store, s) for s in node.children if s is not below]
            now = [v for v in waiting if node.summed in v.keys]
            waiting = [v for v in waiting if node.summed not in v.keys]
            waiting.append(ring.combined(now, tuple(sorted({k for v in now for k in v.keys} - {node.summed}, key=str))))
        if node.name in store.kept:
            whole = ring.combined(sorted(waiting, key=lambda v: -len(v.keys)), node.keys)
            change, _ = store.append(node, batch, alias, whole)
            waiting = [change]
            out[node.name] = change
        below = node
    return out


def propagate_factored_all(store: ViewStore, deltas: dict[str, list[DataFrame]], batch: str) -> bool:
    """One bulk of factored updates, as propagate_all."""
    if not store.begin(batch):
        return False
    for alias, factors in deltas.items():
        propagate_factored(store, alias, factors, batch)
    store.commit(batch)
    return True
