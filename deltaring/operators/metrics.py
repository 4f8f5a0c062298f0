"""Cost and accuracy measures."""

from __future__ import annotations

import time
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.tree import ViewTree
from ..sources.store import ViewStore
from .evaluate import evaluate
from .rings import CountRing, View


@dataclass
class BulkLog:
    """Seconds by part of the work and updates, a row per bulk."""

    rows: list[dict] = field(default_factory=list)
    _now: dict | None = None

    @contextmanager
    def bulk(self, batch: str, updates: int = 0):
        row = {"batch": batch, "updates": updates, "parts": {}}
        began = time.perf_counter()
        self._now = row
        yield self
        row["seconds"] = time.perf_counter() - began
        self.rows.append(row)

    def updates(self, n: int) -> None:
        self._now["updates"] = n

    @contextmanager
    def part(self, name: str):
        """A part of the current bulk, or of the last one once it is over."""
        began = time.perf_counter()
        yield
        if self._now is not None:
            self._now["parts"][name] = self._now["parts"].get(name, 0.0) + time.perf_counter() - began


def throughput(log: BulkLog) -> float:
    """Updates per second over all bulks, everything counted."""
    seconds = sum(r["seconds"] for r in log.rows)
    return sum(r["updates"] for r in log.rows) / seconds if seconds else 0.0


def bulk_timings(spark: SparkSession, log: BulkLog) -> DataFrame:
    """batch, part, seconds."""
    rows = [(r["batch"], p, s) for r in log.rows for p, s in [*r["parts"].items(), ("total", r["seconds"])]]
    return spark.createDataFrame(rows, "batch string, part string, seconds double")


def speedup(a: float, b: float) -> float:
    """How many times faster a is than b, in seconds."""
    return b / a if a > 0 else float("inf")


def view_sizes(store: ViewStore) -> DataFrame:
    """view, rows of each kept view, merged."""
    out = None
    for node in store.kept.values():
        one = store.state(node).df.agg(F.count("*").alias("rows")).select(F.lit(node.name).alias("view"), "rows")
        out = one if out is None else out.unionByName(one)
    return out


def repetition(tree: ViewTree, tables: dict[str, DataFrame]) -> tuple[int, int, float]:
    """Rows of all tables, rows of the join (counted, not built), and their ratio."""
    base = sum(t.count() for t in tables.values())
    row = evaluate(tree, tables, CountRing(tree.spec)).df.agg(F.sum("c")).first()
    n = int(row[0] or 0)
    return base, n, n / base if base else 0.0


def sparsity(entries: DataFrame) -> DataFrame:
    """attr_u, attr_v, live, possible: live entries of each cell against the product of live categories."""
    cats = entries.where("attr_u = '1' and attr_v <> '1'").groupBy(F.col("attr_v").alias("attr")).agg(F.count("*").alias("k"))
    cells = entries.where("attr_u <> '1'").groupBy("attr_u", "attr_v").agg(F.count("*").alias("live"))
    x, y = (cats.select(F.col("attr").alias(f"attr_{s}"), F.col("k").alias(f"k_{s}")) for s in "uv")
    return cells.join(F.broadcast(x), "attr_u").join(F.broadcast(y), "attr_v").select("attr_u", "attr_v", "live", F.when(F.col("attr_u") == F.col("attr_v"), F.col("k_u")).otherwise(F.col("k_u") * F.col("k_v")).alias("possible"))


def max_diff(a: DataFrame, b: DataFrame, keys: list[str], value: str = "value") -> tuple[float, float]:
    """Greatest absolute and relative difference of two results; a row that one lacks counts as 0 there."""
    x, y = a.select(*keys, F.col(value).cast("double").alias("x")), b.select(*keys, F.col(value).cast("double").alias("y"))
    both = x.join(y, keys, "full_outer").fillna(0.0, ["x", "y"])
    d = F.abs(F.col("x") - F.col("y"))
    row = both.agg(F.max(d), F.max(d / F.greatest(F.abs("x"), F.abs("y"), F.lit(1e-300)))).first()
    return float(row[0] or 0.0), float(row[1] or 0.0)


def drift(before: DataFrame, after: DataFrame) -> DataFrame:
    """attr_u, attr_v, change of mutual information between two bulks."""
    a, b = before.withColumnRenamed("mi", "x"), after.withColumnRenamed("mi", "y")
    return a.join(b, ["attr_u", "attr_v"], "full_outer").select("attr_u", "attr_v", (F.coalesce("y", F.lit(0.0)) - F.coalesce("x", F.lit(0.0))).alias("change"))


def cores(spark: SparkSession) -> int:
    return spark.sparkContext.defaultParallelism


def aggregates_kept(m: int) -> int:
    return 1 + m + m * (m + 1) // 2


def stage_summary(spark: SparkSession) -> list[dict]:
    """Shuffle and spill bytes and run time of the stages the status store still knows."""
    store = spark.sparkContext._jsc.sc().statusStore()
    stages = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None) if hasattr(store, "stageList") else []
    it, out = stages.iterator(), []
    while it.hasNext():
        s = it.next()
        out.append({"stage": s.stageId(), "tasks": s.numTasks(), "run_ms": s.executorRunTime(), "shuffle_write": s.shuffleWriteBytes(), "spill": s.diskBytesSpilled()})
    return out


def entries_diff(a: View, b: View, ring) -> tuple[float, float]:
    return max_diff(ring.entries(a), ring.entries(b), ["attr_u", "attr_v"])
