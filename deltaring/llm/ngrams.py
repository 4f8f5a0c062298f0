"""Hashed word n-gram multinomials of a trusted and of the raw corpus, in Spark expressions alone."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE, hash60


@dataclass(frozen=True)
class NgramModel:
    """slots: hash slots of words and word pairs. smoothing: added to each slot's count in the trusted model, and in
    the same proportion in the raw one, so that n-grams too rare to tell weigh nothing.
    most_trusted: the trusted model is fitted on at most so many labelled documents, those first by a hash of
    their id; the raw model always counts every document."""

    slots: int = 1 << 16
    smoothing: float = 16.0
    most_trusted: int = 20_000


def words(text: Column) -> Column:
    """The words of a text; a null text has none."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), f"{SPACE}+", -1), lambda w: w != F.lit(""))


def slots_of(w: Column, slots: int) -> Column:
    """Slots of all words and of all pairs of neighbours; w is bound once, however often it is read."""

    def both(v: Column) -> Column:
        one = F.transform(v, lambda x: F.pmod(F.xxhash64(x), F.lit(slots)).cast("int"))
        two = F.transform(v, lambda x, i: F.pmod(F.xxhash64(F.get(v, i - 1), x, F.lit(2)), F.lit(slots)).cast("int"))
        return F.concat(one, F.slice(two, F.lit(2), F.greatest(F.size(v) - 1, F.lit(0))))

    return F.transform(F.array(w), both)[0]


def trusted_ids(labels: DataFrame, model: NgramModel) -> DataFrame:
    """trusted_id of at most most_trusted documents labelled as good."""
    good = labels.where((F.col("quality") == 1) & F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("trusted_id")).distinct()
    return good.orderBy(hash60(F.lit(5), F.col("trusted_id")), "trusted_id").limit(model.most_trusted)


def log_ratios(docs: DataFrame, labels: DataFrame, model: NgramModel) -> DataFrame:
    """slot, ratio: for each slot the log of its share in the trusted model over that in the raw one; 0 without labels."""
    marked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(trusted_ids(labels, model)), F.col("doc_id") == F.col("trusted_id"), "left")
    each = marked.select(F.col("trusted_id").isNotNull().cast("long").alias("good"), F.explode(slots_of(words(F.col("text")), model.slots)).alias("slot"))
    counts = each.groupBy("slot").agg(F.count("*").alias("raw"), F.sum("good").alias("good"))
    every = docs.sparkSession.range(model.slots).select(F.col("id").cast("int").alias("slot")).join(counts, "slot", "left").na.fill(0)
    share = every.agg((F.sum("good") / F.greatest(F.sum("raw"), F.lit(1))).alias("share")).scalar()
    a = F.lit(model.smoothing)
    return every.select("slot", (F.log(F.col("good") + a) - F.log(F.col("raw") * share + a)).alias("ratio"))
