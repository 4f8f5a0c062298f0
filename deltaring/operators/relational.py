"""Operators a user of maintained statistics needs around them."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(events: DataFrame, snapshots: DataFrame, on: str, by: list[str], values: list[str], parts: int | None = None) -> DataFrame:
    """Each event with the latest snapshot at or before it, per key: one union, one window, no pair is formed.

    Over no keys, or hot ones, time is cut into `parts` ranges; the last snapshot before each range is carried in.
    Snapshots with a null time or key meet no event.
    """
    asof, tail = f"{on}_asof", [*values, f"{on}_asof"]
    snapshots = snapshots.where(reduce(lambda a, b: a & b, [F.col(c).isNotNull() for c in [*by, on]]))
    e = events.select(*by, F.col(on), F.struct(*events.columns).alias("__event"), *[F.lit(None).cast(snapshots.schema[v].dataType).alias(v) for v in values], F.lit(None).cast(snapshots.schema[on].dataType).alias(asof))
    s = snapshots.select(*by, F.col(on), F.lit(None).cast(e.schema["__event"].dataType).alias("__event"), *values, F.col(on).alias(asof))
    both = s.unionByName(e)
    keys = list(by)
    if parts and parts > 1:
        cuts = both.agg(F.percentile_approx(on, [i / parts for i in range(1, parts)])).first()[0] or []  # parts - 1 values
        both = both.withColumn("__part", sum((F.coalesce((F.col(on) > F.lit(c)).cast("int"), F.lit(0)) for c in sorted(set(cuts))), F.lit(0)))
        keys.append("__part")
    order = Window.partitionBy(*keys).orderBy(F.col(on), F.col("__event").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    filled = both.select("__event", *keys, *[F.last(v, True).over(order).alias(v) for v in tail]).where("__event is not null")
    if keys != list(by):
        ends = both.groupBy(*keys).agg(*[F.max_by(v, F.when(F.col(v).isNotNull(), F.col(on))).alias(v) for v in tail])
        before = Window.partitionBy(*by).orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
        carried = ends.select(*keys, *[F.last(v, True).over(before).alias(f"__carried_{v}") for v in tail])
        filled = filled.join(carried, keys, "left").select("__event", *[F.coalesce(v, f"__carried_{v}").alias(v) for v in tail])
    return filled.select("__event.*", *tail)


def range_join(points: DataFrame, value: str, ranges: DataFrame, low: str, high: str, width: float) -> DataFrame:
    """Points with the ranges low <= value < high: an equi-join on cells of the given width, then the exact test."""
    cell = lambda c: F.floor(c / F.lit(width)).cast("long")
    p = points.withColumn("__cell", cell(F.col(value).cast("double")))
    r = ranges.where(F.col(low) < F.col(high)).withColumn("__cell", F.explode(F.sequence(cell(F.col(low).cast("double")), cell(F.col(high).cast("double")))))
    return p.join(r, "__cell").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("__cell")


def salted_join(large: DataFrame, small: DataFrame, keys: list[str], salts: int = 16) -> DataFrame:
    """An equi-join whose hot keys are dealt to `salts` tasks; the other side is repeated as often."""
    a = large.withColumn("__salt", F.pmod(F.xxhash64(*large.columns), F.lit(salts)).cast("int"))
    b = small.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [*keys, "__salt"]).drop("__salt")


def affected(view: DataFrame, delta: DataFrame, keys: list[str]) -> DataFrame:
    """Rows of a view whose keys a delta touches."""
    return view.join(delta.select(*keys).distinct(), keys, "left_semi")


def dangling(child: DataFrame, parent: DataFrame, keys: list[tuple[str, str]]) -> DataFrame:
    """Rows without a partner."""
    on = reduce(lambda a, b: a & b, [child[x] == parent[y] for x, y in keys])
    return child.join(parent, on, "left_anti")


def symmetric_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of one bag but not the other, with the difference of their counts as mult."""
    both = a.withColumn("mult", F.lit(1)).unionByName(b.withColumn("mult", F.lit(-1)))
    return both.groupBy(*a.columns).agg(F.sum("mult").cast("long").alias("mult")).where("mult <> 0")


def running(bulks: DataFrame, batch: str, values: list[str], by: list[str] | None = None) -> DataFrame:
    """The state after each bulk: running sums of per-bulk changes."""
    order = Window.partitionBy(*(by or [])).orderBy(batch).rowsBetween(Window.unboundedPreceding, 0)
    return bulks.select(*(by or []), batch, *[F.sum(v).over(order).alias(v) for v in values])


def sliding_bulks(bulks: DataFrame, batch: str, values: list[str], size: int, by: list[str] | None = None) -> DataFrame:
    """The sum of the last `size` bulks at each bulk: what leaves is subtracted, as the ring allows."""
    order = Window.partitionBy(*(by or [])).orderBy(batch)
    upto = order.rowsBetween(Window.unboundedPreceding, 0)
    gone = order.rowsBetween(Window.unboundedPreceding, -size)
    return bulks.select(*(by or []), batch, *[(F.sum(v).over(upto) - F.coalesce(F.sum(v).over(gone), F.lit(0))).alias(v) for v in values])


def moments_by_grouping_sets(df: DataFrame, groups: list[str], values: list[str]) -> DataFrame:
    """Moments for every subset of the groups at once (cube), with the grouping number."""
    vs = sorted(values)
    x = {v: F.col(v).cast("decimal(12,2)") for v in vs}
    sums = [F.count("*").alias("c"), *[F.sum(x[v]).alias(f"s_{v}") for v in vs], *[F.sum(x[a] * x[b]).alias(f"q_{a}__{b}") for i, a in enumerate(vs) for b in vs[i:]]]
    return df.cube(*groups).agg(F.grouping_id().alias("grouping"), *sums)


def correlation(c: Column, sx: Column, sy: Column, sxx: Column, sxy: Column, syy: Column) -> Column:
    """Pearson correlation from moments, in doubles."""
    d = lambda x: x.cast("double")
    c, sx, sy, sxx, sxy, syy = map(d, (c, sx, sy, sxx, sxy, syy))
    return (c * sxy - sx * sy) / (F.sqrt(c * sxx - sx * sx) * F.sqrt(c * syy - sy * sy))


def top_k(df: DataFrame, k: int, *order: Column) -> DataFrame:
    return df.orderBy(*order).limit(k)


def pivoted(mi: DataFrame, attrs: list[str]) -> DataFrame:
    """The MI matrix with a column per attribute."""
    return mi.groupBy("attr_u").pivot("attr_v", sorted(attrs)).agg(F.first("mi"))
