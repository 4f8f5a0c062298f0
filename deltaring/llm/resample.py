"""Importance resampling of documents by the ratio of two hashed n-gram models, drawn by Gumbel top-k."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut_at, fresh, hash60, written
from .ngrams import NgramModel, trusted_ids
from .wordhash import mixed, word_hashes

#: The sample is as large as the number of documents whose weight is above a cut, the one that best tells held-out labels
#: apart, where letting all bad ones pass would cost BAD_COST of losing all good ones; NOISE (in natural logarithms) is left
#: for the Gumbel noise. One in HELD_OUT of the labelled documents, by a hash of the id, is kept from the fit for it, and
#: at most MOST_HELD of those are looked at, first by another hash.
BAD_COST, NOISE, HELD_OUT, MOST_HELD = 0.1, 2.0, 4, 20_000
#: Gumbel keys are compared as integers of this resolution.
SCALE = 1e6


def gram_slots(text: str | None, slots: int) -> np.ndarray:
    """Slots of a text's words and pairs of neighbouring words."""
    h = word_hashes(text)
    two = mixed(h[:-1] * np.uint64(3) + h[1:]) if len(h) > 1 else h[:0]
    return (np.concatenate([h, two]) % np.uint64(slots)).astype(np.int64)


def fitted_ratios(docs: DataFrame, labels: DataFrame, model: NgramModel) -> np.ndarray:
    """Per slot, the log of its share in the trusted model over that in the raw one. Each task sends one row per slot."""
    slots = model.slots

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        sums = np.zeros((2, slots), np.int64)
        for b in batches:
            for text, good in zip(b["text"], b["good"]):
                n = np.bincount(gram_slots(text, slots), minlength=slots) if text else 0
                sums[0] += n
                if good:
                    sums[1] += n
        some = np.flatnonzero(sums[0])
        yield pd.DataFrame({"slot": some.astype(np.int32), "raw": sums[0][some], "good": sums[1][some]})

    marked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(trusted_ids(labels, model)), F.col("doc_id") == F.col("trusted_id"), "left")
    counts = marked.select("text", F.col("trusted_id").isNotNull().alias("good")).mapInPandas(count, "slot int, raw long, good long").groupBy("slot").agg(F.sum("raw").alias("raw"), F.sum("good").alias("good")).toPandas()  # at most `slots` rows
    raw, good = np.zeros(slots), np.zeros(slots)
    raw[counts["slot"]], good[counts["slot"]] = counts["raw"], counts["good"]
    share = good.sum() / max(raw.sum(), 1.0)
    return np.log(good + model.smoothing) - np.log(raw * share + model.smoothing)


def gumbel(seed: int, *cols: Column) -> Column:
    """Standard Gumbel noise from a hash of the columns."""
    u = (F.shiftrightunsigned(hash60(F.lit(seed), *cols), 8) + F.lit(0.5)) / F.lit(float(1 << 52))
    return -F.log(-F.log(u))


def weighed(docs: DataFrame, ratios: np.ndarray, seed: int) -> DataFrame:
    """docs with log_weight, gumbel_key and their integer forms __key and __tie."""
    sent, slots = docs.sparkSession.sparkContext.broadcast(ratios), len(ratios)

    @F.pandas_udf("double")
    def log_weight(texts: pd.Series) -> pd.Series:
        known = sent.value
        return pd.Series([float(known[gram_slots(t, slots)].sum()) if t else 0.0 for t in texts])

    rows = docs.withColumn("log_weight", log_weight(F.col("text")))
    rows = rows.withColumn("gumbel_key", F.col("log_weight") + gumbel(seed, F.col("doc_id")))
    return rows.withColumn("__key", F.round(F.col("gumbel_key") * SCALE).cast("long")).withColumn("__tie", hash60(F.lit(seed + 1), F.col("doc_id"), F.col("text")))


def held_out(labels: DataFrame) -> Column:
    """Whether a label is kept from the fit."""
    return hash60(F.lit(7), labels["doc_id"].cast("long")) % HELD_OUT == 0


def best_cut(good: np.ndarray, bad: np.ndarray) -> float | None:
    """The weight at or above which documents are best taken for good; None without good ones."""
    if not len(good):
        return None
    cuts = np.unique(np.concatenate([good, bad]))
    lost = np.searchsorted(np.sort(good), cuts) / len(good)
    passed = 1.0 - np.searchsorted(np.sort(bad), cuts) / len(bad) if len(bad) else 0.0
    cost = np.round(lost + BAD_COST * passed, 9)
    best = np.flatnonzero(cost == cost.min())
    return float(cuts[best[len(best) // 2]])  # the middle one of equals


def sample_size(rows: DataFrame, labels: DataFrame) -> int | None:
    """How many documents have a weight above the cut that held-out labels tell (any labels where no good one is held out);
    None (all) without good labels. Every document is compared with the cut."""
    known = labels.where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("labelled"), F.col("quality").cast("int").alias("quality"), held_out(labels).alias("held")).distinct()
    some = known.orderBy(F.desc("held"), hash60(F.lit(11), F.col("labelled")), "labelled", "quality").limit(MOST_HELD)
    told = rows.select(F.col("doc_id").cast("long").alias("labelled"), "log_weight").join(F.broadcast(some), "labelled").select("log_weight", "quality", "held").toPandas()
    held = told[told["held"]]
    held = held if (held["quality"] == 1).any() else told
    weights = lambda good: held.loc[(held["quality"] == 1) == good, "log_weight"].to_numpy()
    cut = best_cut(weights(True), weights(False))
    return None if cut is None else rows.where(F.col("log_weight") >= cut - NOISE).count()


def sampled(docs: DataFrame, labels: DataFrame, share: float | None = None, seed: int = 23, model: NgramModel = NgramModel()) -> DataFrame:
    """docs (doc_id, text and any other columns) with log_weight, gumbel_key and selected.

    Texts are scored once; rows and scores are written to shared storage. The k largest keys are selected, k being
    `share` of all documents or, by default, `sample_size`.
    """
    names = {c: fresh(docs, c) for c in ("log_weight", "gumbel_key", "__key", "__tie")}
    kept = [c for c in docs.columns if c not in ("doc_id", "text")]
    plain = docs.select("doc_id", "text", *[F.col(c).alias(f"__own_{i}") for i, c in enumerate(kept)])
    rows = written(weighed(plain, fitted_ratios(docs.select("doc_id", "text"), labels.where(~held_out(labels)), model), seed), "weighed")
    size = sample_size(rows, labels) if share is None else math.ceil(share * rows.count() - 1e-9)
    taken = F.lit(True)
    if size is not None:
        cut, left = cut_at(rows, "__key", size)
        if cut is not None:
            tie = cut_at(rows.where(F.col("__key") == cut), "__tie", left)[0] if left else None
            at_cut = (F.col("__key") == cut) & (F.lit(left > 0) if tie is None else F.col("__tie") >= tie)
            taken = (F.col("__key") > cut) | at_cut
    own = [F.col(c) if c in ("doc_id", "text") else F.col(f"__own_{kept.index(c)}").alias(c) for c in docs.columns]
    return rows.select(*own, F.col("log_weight").alias(names["log_weight"]), F.col("gumbel_key").alias(names["gumbel_key"]), taken.alias(fresh(docs, "selected")))


def resampled_documents(docs: DataFrame, labels: DataFrame, share: float | None = None, seed: int = 23) -> DataFrame:
    """doc_id, log_weight, gumbel_key, selected for every document.

    log_weight is the sum, over all words and word pairs, of the log of the trusted model over the raw one;
    the k largest sums of weight and seeded Gumbel noise are selected, which draws k documents without
    replacement by their weights. k follows from the weights of the documents labelled as good (or is a given
    share of all), and is met exactly by counting, never by gathering rows; ties go by a hash of id and text, and rows
    equal in both are taken together. A null or blank text has weight 0. No documents give no rows; without
    labels all are taken.
    """
    return sampled(docs.select("doc_id", "text"), labels, share, seed).drop("text")
