"""Mutual information of all pairs of categorical attributes from shared counts."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.store import new_folder
from .rings import View


def _log(x: Column, base: float | str) -> Column:
    return F.log(x) if base == "e" else F.log(x) / F.lit(math.log(float(base)))


def _nlogn(n: Column, base: float | str) -> Column:
    return F.when(n > 0, n * _log(n.cast("double"), base)).otherwise(0.0)


def count_entries(v: View) -> DataFrame:
    """attr_u, attr_v, n of an all-categorical root: a row per live category pair; "1" for none."""
    a = lambda i: F.coalesce(F.get("term", F.lit(i))["a"], F.lit("1"))
    return v.df.select(F.when(F.size("term") == 2, a(0)).otherwise(F.lit("1")).alias("attr_u"), F.when(F.size("term") == 2, a(1)).otherwise(a(0)).alias("attr_v"), F.col("n").cast("long").alias("n"))


def mutual_information(v: View, base: float | str = "e") -> DataFrame:
    """attr_u, attr_v, mi for each pair of attributes (attr_u <= attr_v), entropies on the diagonal.

    With h(T) the sum of n log n over the counts n of a grouping T of N rows, I(X, Y) = log N +
    (h(XY) - h(X) - h(Y)) / N: one pass over the entries and a join with a row per attribute.
    Pairs that never occur together add nothing. An empty join gives no rows. The view is evaluated once: the
    sums, a row per pair of attributes, are written to shared storage.
    """
    e = count_entries(v)
    h = e.groupBy("attr_u", "attr_v").agg(F.sum(_nlogn(F.col("n"), base)).alias("h"), F.sum("n").alias("n"))
    path = new_folder(h.sparkSession, "pair-sums")
    h.coalesce(1).write.parquet(path)
    h = h.sparkSession.read.schema(h.schema).parquet(path)
    total = h.where("attr_u = '1' and attr_v = '1'").select(F.col("n").alias("total"))
    single = h.where("attr_u = '1' and attr_v <> '1'").select(F.col("attr_v").alias("attr"), F.col("h").alias("h1"), F.lit(1).alias("k"))
    single = single.join(total.withColumn("k", F.lit(1)), "k").drop("k")  # a row per attribute, each with the one total
    single = single.where("total > 0")
    pair = h.where("attr_u <> '1'").select("attr_u", "attr_v", "h")
    x, y = (single.select(F.col("attr").alias(f"attr_{s}"), F.col("h1").alias(f"h_{s}"), F.col("total").alias(f"total_{s}")) for s in "uv")
    mi = pair.join(F.broadcast(x), "attr_u").join(F.broadcast(y), "attr_v")
    n = F.col("total_u").cast("double")
    out = mi.select("attr_u", "attr_v", (_log(n, base) + (F.col("h") - F.col("h_u") - F.col("h_v")) / n).alias("mi"))
    own = single.select(F.col("attr").alias("attr_u"), F.col("attr").alias("attr_v"), (_log(F.col("total").cast("double"), base) - F.col("h1") / F.col("total").cast("double")).alias("mi"))
    return out.unionByName(own)


def symmetric(mi: DataFrame) -> DataFrame:
    return mi.unionByName(mi.where("attr_u <> attr_v").select(F.col("attr_v").alias("attr_u"), F.col("attr_u").alias("attr_v"), "mi"))


def normalised(mi: DataFrame) -> DataFrame:
    """mi divided by the geometric mean of the two entropies, 0 where one is 0."""
    h = mi.where("attr_u = attr_v").select(F.col("attr_u").alias("attr"), F.col("mi").alias("entropy"))
    x, y = (h.select(F.col("attr").alias(f"attr_{s}"), F.col("entropy").alias(f"h_{s}")) for s in "uv")
    both = mi.join(F.broadcast(x), "attr_u").join(F.broadcast(y), "attr_v")
    root = F.sqrt(F.greatest(F.col("h_u") * F.col("h_v"), F.lit(0.0)))
    return both.select("attr_u", "attr_v", "mi", F.when(root > 0, F.col("mi") / root).otherwise(0.0).alias("normalised"))


def mutual_information_direct(df: DataFrame, x: str, y: str, base: float | str = "e") -> DataFrame:
    """mi of two columns of a flat table by the double sum over live pairs: one row."""
    joint = df.groupBy(F.col(x).alias("x"), F.col(y).alias("y")).agg(F.count("*").cast("double").alias("cxy"))
    cx = joint.groupBy("x").agg(F.sum("cxy").alias("cx"))
    cy = joint.groupBy("y").agg(F.sum("cxy").alias("cy"))
    n = joint.agg(F.sum("cxy").alias("n"))
    both = joint.join(cx, joint["x"].eqNullSafe(cx["x"])).join(cy, joint["y"].eqNullSafe(cy["y"]))
    total = n.scalar()
    return both.agg(F.sum(F.col("cxy") / total * _log(total * F.col("cxy") / (F.col("cx") * F.col("cy")), base)).alias("mi"))


def entropy(df: DataFrame, x: str, base: float | str = "e") -> DataFrame:
    """entropy of one column: one row."""
    return df.groupBy(x).agg(F.count("*").alias("c")).agg((_log(F.sum("c").cast("double"), base) - F.sum(_nlogn(F.col("c"), base)) / F.sum("c")).alias("entropy"))


def split_gain(df: DataFrame, label: str, ordered: str) -> DataFrame:
    """cut, gain: for each cut "ordered <= cut" the MI between the label and the side, from counts by (value, label).

    Prefix sums over the distinct values per label; the last value cuts nothing off and is left out.
    """
    from pyspark.sql import Window

    counts = df.groupBy(F.col(ordered).alias("cut"), F.col(label).alias("label")).agg(F.count("*").alias("c"))
    values = counts.select("cut").distinct()
    labels = counts.groupBy("label").agg(F.sum("c").alias("label_total"))
    grid = values.withColumn("k", F.lit(1)).join(F.broadcast(labels.withColumn("k", F.lit(1))), "k").drop("k")
    full = grid.join(counts, ["cut", "label"], "left").fillna(0, ["c"])
    left = full.withColumn("left", F.sum("c").over(Window.partitionBy("label").orderBy("cut").rowsBetween(Window.unboundedPreceding, 0)))
    h = left.groupBy("cut").agg(
        F.sum("label_total").alias("n"), F.sum("left").alias("l"),
        F.sum(_nlogn(F.col("label_total"), "e")).alias("hy"), F.sum(_nlogn(F.col("left"), "e") + _nlogn(F.col("label_total") - F.col("left"), "e")).alias("hxy"),
    )
    n, cut = F.col("n").cast("double"), F.col("l")
    gain = F.log(n) + (F.col("hxy") - F.col("hy") - _nlogn(cut, "e") - _nlogn(F.col("n") - cut, "e")) / n
    return h.where("l < n").select("cut", gain.alias("gain"))


def clustering_similarity(df: DataFrame, a: str, b: str) -> DataFrame:
    """mi and normalised of two cluster columns: one row."""
    joint = df.groupBy(F.col(a).alias("a"), F.col(b).alias("b")).agg(F.count("*").alias("c"))
    n = joint.agg(F.sum("c").alias("n"), F.sum(_nlogn(F.col("c"), "e")).alias("hxy"), F.lit(1).alias("k"))
    one = lambda c, h: joint.groupBy(c).agg(F.sum("c").alias("c")).agg(F.sum(_nlogn(F.col("c"), "e")).alias(h), F.lit(1).alias("k"))
    row = n.join(one("a", "ha"), "k").join(one("b", "hb"), "k")
    t = F.col("n").cast("double")
    mi = F.log(t) + (F.col("hxy") - F.col("ha") - F.col("hb")) / t
    ea, eb = F.log(t) - F.col("ha") / t, F.log(t) - F.col("hb") / t
    return row.select(mi.alias("mi"), F.when((ea > 0) & (eb > 0), mi / F.sqrt(ea * eb)).otherwise(0.0).alias("normalised"))
