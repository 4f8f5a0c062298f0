"""A live session: views kept under bulks that arrive, and the applications refreshed after each."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.streaming import StreamingQuery

from ..operators.delta import consolidate, propagate_all
from ..operators.deptree import dependency_tree
from ..operators.information import mutual_information
from ..operators.metrics import BulkLog
from ..operators.ridge import RidgeModel, collected, ridge_fit, ridge_resume
from ..operators.rings import Ring
from ..operators.selection import select_features
from ..plans.explain import explain_tree
from ..plans.spec import QuerySpec
from ..plans.tree import ViewTree, build_view_tree
from ..sources.store import ViewStore


class LiveSession:
    """Input, selection, regression, tree and strategy over one query.

    spec is the mixed query; counts_spec, if given, the all-categorical one behind mutual information
    (continuous attributes binned). Both are kept under the same bulks. A bulk is applied once however
    often it is delivered.
    """

    def __init__(self, spark: SparkSession, spec: QuerySpec, ring: Ring, counts_spec: QuerySpec | None = None, counts_ring: Ring | None = None, order="auto", updatable: tuple[str, ...] | None = None, pause_seconds: float = 0.0, path: str | None = None):
        self.spark, self.spec, self.ring, self.pause = spark, spec, ring, pause_seconds
        self.tree: ViewTree = build_view_tree(spec, order)
        self.store = ViewStore(spark, self.tree, ring, f"{path}/moments" if path else None, updatable)
        self.counts = ViewStore(spark, build_view_tree(counts_spec, order), counts_ring, f"{path}/counts" if path else None, updatable) if counts_spec else None
        self.log, self.model, self.updatable = BulkLog(), None, updatable

    def start(self, tables: dict[str, DataFrame]) -> LiveSession:
        self.spec.validate(tables)
        for s in self._stores():
            s.initialise(tables)
        return self

    def _stores(self) -> list[ViewStore]:
        return [self.store] + ([self.counts] if self.counts else [])

    def apply_bulk(self, deltas: dict[str, DataFrame], batch: str) -> bool:
        """Apply a bulk to all kept views; False if it had been."""
        if all(s.is_committed(batch) for s in self._stores()):
            return False
        with self.log.bulk(batch) as log:
            with log.part("consolidate"):
                deltas = {a: consolidate(d.drop("bulk")) for a, d in deltas.items()}
                rows = {a: d.count() for a, d in deltas.items()}
                log.updates(sum(rows.values()))
            for s in self._stores():
                with log.part("propagate" if s is self.store else "propagate counts"):
                    propagate_all(s, deltas, batch, rows)
        if self.pause:
            time.sleep(self.pause)
        return True

    def mi(self) -> DataFrame:
        store = self.counts or self.store
        return mutual_information(store.ring.terms(store.state()))

    def select(self, label: str, threshold: float) -> DataFrame:
        return select_features(self.mi(), label, threshold)

    def ridge(self, features: list[str], label: str, lam: float = 0.0, **options) -> RidgeModel:
        """The model on the current moments; resumed from the last one where there is one of this label."""
        m = collected(self.ring, self.store.state(), features, label)
        again = self.model is not None and self.model.label == label and self.model.lam == lam
        self.model = ridge_resume(self.model, m, **options) if again else ridge_fit(m, label, lam, **options)
        return self.model

    def panels(self, choice: str, threshold: float, features: list[str], label: str, lam: float = 0.0, **options) -> dict:
        """What the panels show now: the selection for one label, the regression of another, and the tree; a row per
        attribute or edge. Refreshing is timed as a part of the last bulk, if there was one."""
        with self.log.part("refresh"):
            mi = self.mi()
            selected = select_features(mi, choice, threshold).orderBy("rank").collect()
            tree = dependency_tree(mi).orderBy("step").collect()
            return {"selection": selected, "tree": tree, "regression": self.ridge(features, label, lam, **options)}

    def dependency_tree(self) -> DataFrame:
        return dependency_tree(self.mi())

    def strategy(self) -> DataFrame:
        return explain_tree(self.spark, self.tree, self.updatable)

    def run(self, stream: DataFrame, alias: str, checkpoint: str, trigger: dict | None = None, after=None) -> StreamingQuery:
        """Apply a stream of one table's updates, a micro-batch as a bulk; after(session, batch) refreshes what is shown."""

        def on_batch(df: DataFrame, batch: int) -> None:
            if self.apply_bulk({alias: df}, f"{batch:09d}") and after:
                after(self, batch)

        return stream.writeStream.foreachBatch(on_batch).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()
