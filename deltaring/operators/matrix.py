"""Matrix chains as sums of products over binary relations (i, j, v)."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def multiplied(a: DataFrame, b: DataFrame) -> DataFrame:
    left = a.select("i", F.col("j").alias("k"), F.col("v").alias("x"))
    right = b.select(F.col("i").alias("k"), "j", F.col("v").alias("y"))
    return left.join(right, "k").groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("v"))


def chain_order(dims: list[int]) -> tuple[float, tuple]:
    """Cheapest bracketing of a chain by the number of scalar products; dims has one more entry than the chain."""
    n = len(dims) - 1
    best: dict[tuple[int, int], tuple[float, tuple | int]] = {(i, i): (0.0, i) for i in range(n)}
    for span in range(1, n):
        for i in range(n - span):
            j = i + span
            best[i, j] = min(((best[i, k][0] + best[k + 1, j][0] + float(dims[i]) * dims[k + 1] * dims[j + 1], (best[i, k][1], best[k + 1, j][1])) for k in range(i, j)), key=lambda t: t[0])
    return best[0, n - 1]


def matrix_chain(matrices: list[DataFrame], dims: list[int] | None = None) -> DataFrame:
    """i, j, v of the product; with the dimensions the order of multiplication is chosen, else left to right."""
    if dims is None:
        return reduce(multiplied, matrices)

    def built(o) -> DataFrame:
        return matrices[o] if isinstance(o, int) else multiplied(built(o[0]), built(o[1]))

    return built(chain_order(dims)[1])


def matrix_chain_delta(matrices: list[DataFrame], at: int, change: DataFrame) -> DataFrame:
    """Change of the product when `change` is added to one factor: small times its neighbours, outwards."""
    out = change
    for m in reversed(matrices[:at]):
        out = multiplied(m, out)
    for m in matrices[at + 1 :]:
        out = multiplied(out, m)
    return out


def rank_one(u: DataFrame, w: DataFrame) -> DataFrame:
    """i, j, v of the outer product of (i, v) and (j, v)."""
    return u.withColumn("k", F.lit(1)).join(F.broadcast(w.select("j", F.col("v").alias("y")).withColumn("k", F.lit(1))), "k").select("i", "j", (F.col("v") * F.col("y")).alias("v"))


def matrix_chain_rank_one(matrices: list[DataFrame], at: int, u: DataFrame, w: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The change of the product for a rank-one change of one factor, kept as its two vectors (i, v) and (j, v)."""
    for m in reversed(matrices[:at]):
        u = m.join(u.select(F.col("i").alias("j"), F.col("v").alias("y")), "j").groupBy("i").agg(F.sum(F.col("v") * F.col("y")).alias("v"))
    for m in matrices[at + 1 :]:
        w = m.select(F.col("i").alias("k"), "j", F.col("v").alias("y")).join(w.select(F.col("j").alias("k"), "v"), "k").groupBy("j").agg(F.sum(F.col("v") * F.col("y")).alias("v"))
    return u, w


def added(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b).groupBy("i", "j").agg(F.sum("v").alias("v")).where("v <> 0")
