"""Quality rules of whole documents, and the n-gram log-likelihood ratio verdict, in Spark expressions alone."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE, WORD
from .ngrams import NgramModel, log_ratios, slots_of, words

#: A document whose mean log ratio is below this is rejected.
THRESHOLD = -0.06


def repeated_words(w: Column) -> Column:
    """Words within three-word windows that stand in the text more than once (equal by a 64-bit hash)."""

    def covered(windows: Column) -> Column:
        def doubles(s: Column) -> Column:
            last = F.size(s) - 1
            twin = lambda x, i: (F.get(s, i - 1)["h"] == x["h"]) & (i > 0) | (i < last) & (F.get(s, i + 1)["h"] == x["h"])
            at = F.sort_array(F.transform(F.filter(s, lambda x, i: F.coalesce(twin(x, i), F.lit(False))), lambda x: x["i"]))
            step = lambda a, p: F.struct((p + 3).alias("end"), (a["n"] + p + 3 - F.greatest(a["end"], p)).alias("n"))
            return F.aggregate(at, F.struct(F.lit(0).alias("end"), F.lit(0).alias("n")), step, lambda a: a["n"])

        sorted_ = F.sort_array(F.transform(windows, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(windows)) == F.size(windows), 0).otherwise(F.transform(F.array(sorted_), doubles)[0])

    hashed = F.transform(F.array(w), lambda v: F.transform(F.sequence(F.lit(0), F.size(v) - 3), lambda i: F.xxhash64(F.get(v, i), F.get(v, i + 1), F.get(v, i + 2))))[0]
    return F.when(F.size(w) < 4, 0).otherwise(F.transform(F.array(hashed), covered)[0]).cast("long")


def counted(docs: DataFrame) -> DataFrame:
    """doc_id, words, and the base counts of each text; a null text has none of anything."""
    text = F.coalesce(F.col("text"), F.lit(""))
    lines = F.filter(F.split(text, "\n", -1), lambda x: x.rlike(WORD))
    rows = docs.select(F.col("doc_id"), words(text).alias("words"), text.alias("text"), lines.alias("lines"))
    return rows.select(
        "doc_id",
        "words",
        F.size("words").cast("long").alias("n_words"),
        F.length(F.regexp_replace("text", f"{SPACE}+", "")).cast("long").alias("word_chars"),
        F.length(F.regexp_replace("text", r"[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        repeated_words(F.col("words")).alias("n_repeat_words"),
    )


def ratio_array(ratios: DataFrame) -> Column:
    """The fitted ratios (slot, ratio), a number per slot of the model, as one constant array; six decimals."""
    known = [r["ratio"] for r in ratios.orderBy("slot").collect()]
    return F.split(F.lit(",".join(f"{x:.6g}" for x in known)), ",").cast("array<double>")


def judged_documents(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, model: NgramModel = NgramModel()) -> DataFrame:
    """Base counts, base_failed, mean log ratio and verdict of every document.

    kept is false where the base rules fail (under 50 words, or over half of the words in repeated
    windows), else true where the sum of the log ratios of all its words and word pairs, divided by their
    number, is at least the threshold. A null or blank text has no words and fails; repeated rows are
    judged each; without labels all ratios are 0 and every document that passes the base rules stays.
    """
    ratios = ratio_array(log_ratios(docs, labels, model))
    rows = counted(docs).withColumn("weight", F.transform(F.array(slots_of(F.col("words"), model.slots)), lambda g: F.struct(F.aggregate(g, F.lit(0.0), lambda t, x: t + F.get(ratios, x)).alias("sum"), F.size(g).alias("n")))[0])
    failed = (F.col("n_words") < 50) | (F.col("n_repeat_words") * 100 > F.col("n_words") * 50)
    mean = F.col("weight.sum") / F.greatest(F.col("weight.n"), F.lit(1))
    judged = rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), mean.alias("mean_log_ratio"))
    return judged.select(*judged.columns[:-1], (~F.col("base_failed") & (F.col("mean_log_ratio") >= F.lit(threshold))).alias("kept"), "mean_log_ratio")
