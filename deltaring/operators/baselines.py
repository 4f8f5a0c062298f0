"""The practices that keeping a view tree is compared with."""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spec import Attribute, CAT, QuerySpec
from ..plans.tree import ViewTree
from ..sources.store import new_folder
from .delta import consolidate, propagate_all
from .evaluate import evaluate
from .information import mutual_information_direct
from .rings import MomentRing, Ring, SumProductRing, View


def joined_rows(spec: QuerySpec, tables: dict[str, DataFrame], first: str | None = None) -> DataFrame:
    """The join itself, flat: join variables, attributes, free attributes and mult. `first` starts the join chain."""
    rows = {a: spec.rows(a, tables[a]).withColumnRenamed("mult", f"__m_{a}") for a in spec.tables}
    todo = list(spec.tables)
    if first:
        todo.remove(first)
        todo.insert(0, first)
    start = todo.pop(0)
    out, seen = rows[start], set(spec.table_variables(start))
    while todo:
        alias = next(a for a in todo if seen & set(spec.table_variables(a)))
        todo.remove(alias)
        mine = set(spec.table_variables(alias))
        out = out.join(rows[alias], sorted(seen & mine))
        seen |= mine
    mult = reduce(lambda x, y: x * y, [F.col(f"__m_{a}") for a in spec.tables])
    names = [a.name for a in (*spec.attributes, *spec.free)]
    return out.select(*sorted(seen), *names, mult.alias("mult"))


def recompute(spec: QuerySpec, tables: dict[str, DataFrame], ring: Ring) -> View:
    """Join everything, then aggregate: the payload of the flat join in one leaf."""
    flat = joined_rows(spec, tables)
    keys = tuple(f.name for f in spec.free)
    return ring.leaf(flat, keys, tuple(sorted(a.name for a in spec.attributes)))


class JoinMaintainer:
    """Keeps the join result itself: base tables and join rows as logs, the training set is aggregated anew on demand."""

    def __init__(self, spec: QuerySpec, tables: dict[str, DataFrame]):
        self.spec, self.tables = spec, {a: t if "mult" in t.columns else t.withColumn("mult", F.lit(1).cast("long")) for a, t in tables.items()}
        spark = next(iter(tables.values())).sparkSession
        self.path, self.spark, self.n = new_folder(spark, "join"), spark, 0
        joined_rows(spec, self.tables).write.parquet(f"{self.path}/0")

    def apply(self, alias: str, delta: DataFrame) -> None:
        """Join the delta with the other base tables; the change is appended to the kept join."""
        self.n += 1
        joined_rows(self.spec, {**self.tables, alias: delta}, first=alias).write.mode("overwrite").parquet(f"{self.path}/{self.n}")
        self.tables[alias] = self.tables[alias].unionByName(delta)

    def rows(self) -> DataFrame:
        return self.spark.read.parquet(*[f"{self.path}/{i}" for i in range(self.n + 1)])

    def moments(self, ring: Ring) -> View:
        keys = tuple(f.name for f in self.spec.free)
        return ring.leaf(self.rows(), keys, tuple(sorted(a.name for a in self.spec.attributes)))


def first_order_delta(spec: QuerySpec, tables: dict[str, DataFrame], alias: str, delta: DataFrame, ring: Ring) -> View:
    """The root's change by one delta query over the base tables, without any stored view."""
    flat = joined_rows(spec, {**tables, alias: delta}, first=alias)
    return ring.leaf(flat, tuple(f.name for f in spec.free), tuple(sorted(a.name for a in spec.attributes)))


def per_aggregate(spec: QuerySpec, tree: ViewTree, tables: dict[str, DataFrame], numeric: str = "decimal(38,4)") -> DataFrame:
    """attr_u, attr_v, value: the same moments, each by a tree of its own; nothing is shared."""
    names = sorted(a.name for a in spec.attributes)
    wanted = [("1", "1"), *[("1", a) for a in names], *[(a, b) for i, a in enumerate(names) for b in names[i:]]]
    out = None
    for u, v in wanted:
        functions = {a: a for a in {u, v} - {"1"}}
        if u == v != "1":
            functions = {u: f"cast({u} as decimal(12,2)) * cast({u} as decimal(12,2))"}
        ring = _ScalarRing(spec, functions, numeric)
        one = evaluate(tree, tables, ring).df.select(F.lit(u).alias("attr_u"), F.lit(v).alias("attr_v"), F.col("v").alias("value"))
        out = one if out is None else out.unionByName(one)
    return out


class _ScalarRing(SumProductRing):
    """Scalar ring whose functions keep four decimals, so that a square is exact."""

    def lifted(self, attrs):
        v = "CAST(mult AS decimal(10,0))"
        for a in attrs:
            if a in self.functions:
                v = f"CAST({v} * {self.functions[a]} AS decimal(34,4))"
        return [f"CAST({v} AS {self.numeric}) AS v"]


def online_sgd(batches: list[DataFrame], features: list[str], label: str, rate: float = 0.05, scale: dict[str, tuple[float, float]] | None = None) -> dict[str, float]:
    """A linear model trained on arriving joined rows, one averaged gradient step per batch; rows can't be taken back.

    scale: (mean, deviation) per column, fixed before the first batch.
    """
    scale = scale or {}
    value = lambda c: (F.col(c).cast("double") - F.lit(scale.get(c, (0.0, 1.0))[0])) / F.lit(scale.get(c, (0.0, 1.0))[1])
    theta = {"1": 0.0, **{f: 0.0 for f in features}}
    for df in batches:
        if "mult" in df.columns:
            df = df.where("mult > 0")
        error = F.lit(theta["1"]) + sum([F.lit(theta[f]) * value(f) for f in features], F.lit(0.0)) - value(label)
        row = df.select(error.alias("e"), *[value(f).alias(f) for f in features]).agg(F.avg("e").alias("g_1"), *[F.avg(F.col("e") * F.col(f)).alias(f"g_{f}") for f in features]).first()
        if row["g_1"] is not None:
            theta = {k: t - rate * row[f"g_{k}"] for k, t in theta.items()}
    return theta


def one_hot_moments(spec: QuerySpec, tables: dict[str, DataFrame]) -> DataFrame:
    """attr_u, attr_v, value over explicit indicator columns of the flat join: a column per category ever seen."""
    flat = joined_rows(spec, tables)
    columns, made = [], []
    for a in spec.attributes:
        if a.kind == CAT:
            seen = [r[0] for r in flat.select(a.name).distinct().orderBy(a.name).collect()]
            for i, c in enumerate(seen):
                made.append((f"{a.name}={c}", f"h_{a.name}_{i}"))
                columns.append(F.when(F.col(a.name).eqNullSafe(F.lit(c)), 1).otherwise(0).alias(f"h_{a.name}_{i}"))
        else:
            made.append((a.name, a.name))
            columns.append(F.col(a.name))
    shown = {c: n for n, c in made}
    dense = QuerySpec(tables={"flat": "flat"}, joins=(), attributes=tuple(Attribute(c, "flat") for _, c in made))
    ring = MomentRing(dense, "decimal")
    view = ring.leaf(flat.select(*columns, "mult"), (), tuple(sorted(c for _, c in made)))
    e = ring.entries(view)
    names = F.create_map(*[x for c, n in {**shown, "1": "1"}.items() for x in (F.lit(c), F.lit(n))])
    return e.select(names[F.col("attr_u")].alias("attr_u"), names[F.col("attr_v")].alias("attr_v"), "value")


def apply_with_anti_join(base: DataFrame, inserts: DataFrame, deletes: DataFrame, key: list[str]) -> DataFrame:
    """Set semantics: deletes by an anti join, inserts by a union; the whole base is read again."""
    return base.join(deletes.select(*key).distinct(), key, "left_anti").unionByName(inserts.select(*base.columns))


def evaluate_from_scratch(tree: ViewTree, tables: dict[str, DataFrame], ring: Ring) -> View:
    """Pushed aggregates, no increments: the tree from the current tables."""
    return ring.state(evaluate(tree, tables, ring), tree.root.keys)


def mi_pairwise(flat: DataFrame, attrs: list[str]) -> DataFrame:
    """attr_u, attr_v, mi by a query of its own for each pair; nothing is shared."""
    out = None
    for u, v in combinations(sorted(attrs), 2):
        one = mutual_information_direct(flat, u, v).select(F.lit(u).alias("attr_u"), F.lit(v).alias("attr_v"), "mi")
        out = one if out is None else out.unionByName(one)
    return out


__all__ = ["JoinMaintainer", "apply_with_anti_join", "consolidate", "evaluate_from_scratch", "first_order_delta", "joined_rows", "mi_pairwise", "one_hot_moments", "online_sgd", "per_aggregate", "propagate_all", "recompute"]
