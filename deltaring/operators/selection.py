"""Features for a label by their mutual information with it."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .information import symmetric


def select_features(mi: DataFrame, label: str, threshold: float, partition: list[str] | None = None) -> DataFrame:
    """rank, attr, mi, selected: all attributes but the label, ranked; selected are those strictly above the threshold.

    Ties go by name. With `partition` (say a bulk number) each part is ranked by itself.
    """
    partition = partition or []
    with_label = symmetric(mi) if not partition else mi.unionByName(mi.where("attr_u <> attr_v").withColumns({"attr_u": F.col("attr_v"), "attr_v": F.col("attr_u")}))
    rows = with_label.where((F.col("attr_u") == label) & (F.col("attr_v") != label)).select(*partition, F.col("attr_v").alias("attr"), "mi")
    order = Window.partitionBy(*partition).orderBy(F.desc("mi"), "attr")
    return rows.select(*partition, F.row_number().over(order).alias("rank"), "attr", "mi", (F.col("mi") > F.lit(threshold)).alias("selected"))


def selection_changes(before: DataFrame, after: DataFrame) -> DataFrame:
    """attr, rank_before, rank_after, mi_before, mi_after, change ("entered", "left" or "stayed") of two selections."""
    a = before.select("attr", F.col("rank").alias("rank_before"), F.col("mi").alias("mi_before"), F.col("selected").alias("was"))
    b = after.select("attr", F.col("rank").alias("rank_after"), F.col("mi").alias("mi_after"), F.col("selected").alias("is"))
    was, now = F.coalesce("was", F.lit(False)), F.coalesce("is", F.lit(False))
    change = F.when(~was & now, "entered").when(was & ~now, "left").otherwise("stayed")
    return a.join(b, "attr", "full_outer").select("attr", "rank_before", "rank_after", "mi_before", "mi_after", change.alias("change"))
