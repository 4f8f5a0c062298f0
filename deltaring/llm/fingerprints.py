"""Exact digests of documents in a canonical form, with bytes compared where digests are equal."""

from __future__ import annotations

import hashlib
import unicodedata
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import HASH_BITS, bucket_bits, hash60, written

#: Most bits of the map that tells which digests occur more than once (16 MB sent to each executor).
MOST_BITS = 1 << 27


def canonical(text: str | None) -> bytes:
    """NFKC and case folding until both hold, runs of Unicode white space as one space, none at the ends; null is empty."""
    if not text:
        return b""
    if text.isascii():  # NFKC leaves ASCII alone, case folding is lower()
        return " ".join(text.lower().split()).encode()
    while (folded := unicodedata.normalize("NFKC", text).casefold()) != text:
        text = folded
    return " ".join(text.split()).encode("utf-8", "surrogatepass")


def digest(form: bytes) -> str:
    return xxhash.xxh3_128_hexdigest(form)


def bucket_of(key: Column, splits: list[int]) -> Column:
    """Number of splits at or below key, by halving; null goes before all."""
    if not splits:
        return F.lit(0)
    array = F.array(*[F.lit(int(x)).cast("long") for x in splits])
    start = F.struct(F.lit(0).alias("low"), F.lit(len(splits)).alias("high"))

    def halve(s: Column, _: Column) -> Column:
        mid = F.shiftright(s["low"] + s["high"], 1)
        right = F.get(array, F.least(mid, F.lit(len(splits) - 1))) <= key
        return F.when(s["low"] >= s["high"], s).otherwise(F.when(right, F.struct((mid + 1).alias("low"), s["high"].alias("high"))).otherwise(F.struct(s["low"].alias("low"), mid.alias("high"))))

    return F.when(key.isNull(), 0).otherwise(F.aggregate(F.sequence(F.lit(1), F.lit(len(splits).bit_length() + 1)), start, halve)["low"])


def with_next(docs: DataFrame) -> DataFrame:
    """doc_id, text, next_text: each row's text and that of the next row by doc_id, after the last the first.

    Rows go to ranges of doc_id, once; each range also gets the first row of the next one. Rows with
    equal doc_id follow each other by text. Null ids come first, by a hash of their texts and in ranges of it; null
    texts are empty.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    n = 1 << bucket_bits(docs.sparkSession, 2)
    found = rows.agg(F.percentile_approx("doc_id", [i / n for i in range(1, n)], 20 * n)).first()[0] or []
    bits = bucket_bits(docs.sparkSession)
    lost = F.when(F.col("doc_id").isNull(), hash60("text"))
    rows = rows.withColumn("lost", lost).withColumn("range", F.when(F.col("doc_id").isNull(), F.shiftright("lost", HASH_BITS - bits).cast("int") - F.lit(1 << bits)).otherwise(bucket_of(F.col("doc_id"), sorted(set(found)))))
    low = rows.groupBy("range").agg(F.min(F.struct("doc_id", "lost")).alias("low"))
    firsts = rows.join(F.broadcast(low), "range").where(F.struct("doc_id", "lost") == F.col("low"))  # a row per range goes out: at most the number of ranges
    firsts = firsts.groupBy("range").agg(F.min(F.struct("doc_id", "lost", "text")).alias("first"))
    order = Window.orderBy("range")
    ends = firsts.select(F.lag("range").over(order).alias("range"), F.max("range").over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("last"), F.col("first.doc_id").alias("doc_id"), F.col("first.lost").alias("lost"), F.col("first.text").alias("text"))
    ends = ends.select("doc_id", "lost", "text", F.coalesce("range", "last").cast("int").alias("range"), F.lit(True).alias("end"))
    both = rows.select("doc_id", "lost", "text", F.col("range").cast("int"), F.lit(False).alias("end")).unionByName(ends)
    ahead = F.lead("text").over(Window.partitionBy("range").orderBy("end", F.col("doc_id").asc_nulls_first(), "lost", "text"))
    return both.withColumn("next_text", ahead).where("not end").select("doc_id", "text", "next_text")


def digests(df: DataFrame, texts: list[str], keep: list[str]) -> DataFrame:
    """keep, and for each text column c: c_digest and c_form_sha256, both of the canonical form."""
    kinds = {f.name: f.dataType.simpleString() for f in df.schema}
    schema = ", ".join([f"`{c}` {kinds[c]}" for c in keep] + [f"{c}_{x} string" for c in texts for x in ("digest", "form_sha256")])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        last: dict[str, tuple[str, str]] = {}
        for b in batches:
            out = {c: [] for c in texts}
            for row in zip(*[b[c] for c in texts]):
                now = {}
                for c, t in zip(texts, row):
                    if t in last:
                        now[t] = last[t]
                    elif t not in now:
                        form = canonical(t)
                        now[t] = digest(form), hashlib.sha256(form).hexdigest()
                    out[c].append(now[t])
                last = now  # the next text of this row is often the text of the next one
            yield b[keep].assign(**{f"{c}_{x}": [v[i] for v in out[c]] for c in texts for i, x in enumerate(("digest", "form_sha256"))})

    return df.select(*keep, *texts).mapInPandas(run, schema)


def marked_bits(many: DataFrame, bits: int) -> bytes:
    """A map of so many bits with a 1 at the place of each digest; tasks pack pieces of 65,536 bits, so the driver gets
    bytes and no digests."""

    def pack(p: pd.DataFrame) -> pd.DataFrame:
        piece = np.zeros(1 << 16, bool)
        piece[p["at"].to_numpy() % (1 << 16)] = True
        return pd.DataFrame({"piece": [int(p["piece"].iloc[0])], "packed": [np.packbits(piece).tobytes()]})

    at = F.conv(F.substring("text_digest", 1, 8), 16, 10).cast("long") % bits
    pieces = many.select(at.alias("at")).distinct().withColumn("piece", F.shiftright("at", 16)).groupBy("piece").applyInPandas(lambda p: pack(p), "piece long, packed binary")
    out = bytearray(bits // 8)
    for r in pieces.toLocalIterator():
        out[r["piece"] << 13 : (r["piece"] + 1) << 13] = r["packed"]
    return bytes(out)


def collided(docs: DataFrame, prints: DataFrame, make: Callable[[bytes], str] = digest, most_bits: int = MOST_BITS) -> DataFrame:
    """digest: those that stand for different canonical bytes among documents (text), by comparing bytes.

    prints has every digest, a row per document. Only texts whose digest occurs twice are compared; a bucket folds
    to its least and greatest bytes in each task before anything is shuffled. Which digests those are is told to
    tasks by a map of eight bits or more for each, where a false hit only sends a text more, or, where that would be
    too large a map, by a shuffled join.
    """
    many = prints.groupBy("text_digest").count().where("count > 1").select("text_digest")
    n = many.count()
    bits = max(1 << 16, 1 << (8 * n - 1).bit_length()) if n else 1 << 16
    sent = docs.sparkSession.sparkContext.broadcast(marked_bits(many, bits)) if bits <= most_bits else None

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        marks = np.unpackbits(np.frombuffer(sent.value, np.uint8)) if sent else None
        for b in batches:
            rows = [(d, f) for f in map(canonical, b["text"]) if (d := make(f)) and (marks is None or marks[int(d[:8], 16) % bits])]
            yield pd.DataFrame(rows, columns=["digest", "form"])

    forms = docs.select("text").mapInPandas(run, "digest string, form binary")
    if sent is None:
        forms = forms.join(many.withColumnRenamed("text_digest", "digest"), "digest", "left_semi")
    return forms.groupBy("digest").agg(F.min("form").alias("a"), F.max("form").alias("b")).where("a <> b").select("digest")


def fingerprinted_documents(docs: DataFrame) -> DataFrame:
    """Fingerprints of each text and of its edited text (its last quarter taken from the next document's start).

    doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next. Texts with the
    same canonical form have the same fingerprint; likeness is 1 for equal fingerprints, else 0. Where
    one digest stands for different bytes, the fingerprint goes on with their SHA-256. Null texts are
    empty, repeated rows are kept, no rows give no rows; a sole document is followed by itself.
    """
    pairs = with_next(docs)
    tail = F.floor(F.length("text") / F.lit(4)).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), F.length("text") - tail), F.substring(F.col("next_text"), F.lit(1), tail))
    pairs = pairs.withColumn("n_chars", F.length("text").cast("long")).withColumn("edited", edited).withColumn("edited_sha256", F.sha2(F.col("edited").cast("binary"), 256))
    prints = written(digests(pairs, ["text", "edited", "next_text"], ["doc_id", "n_chars", "edited_sha256"]), "digests")
    clashes = written(collided(docs, prints), "clashes")

    def print_of(c: str, clash: Column | None) -> Column:
        return F.col(f"{c}_digest") if clash is None else F.when(clash, F.concat(f"{c}_digest", F.lit("-"), f"{c}_form_sha256")).otherwise(F.col(f"{c}_digest"))

    out, columns = prints, {}
    some = not clashes.isEmpty()
    for c in ("text", "edited", "next_text"):
        if some:
            out = out.join(clashes.select(F.col("digest").alias(f"{c}_clash")), F.col(f"{c}_digest") == F.col(f"{c}_clash"), "left")
        columns[c] = print_of(c, F.col(f"{c}_clash").isNotNull() if some else None)
    like = lambda a, b: (a == b).cast("double")
    return out.select(
        "doc_id", "n_chars", "edited_sha256", columns["text"].alias("fingerprint"), columns["edited"].alias("edited_fingerprint"),
        like(columns["text"], columns["edited"]).alias("near_edited"), like(columns["text"], columns["next_text"]).alias("near_next"),
    )
