"""Jump consistent hashing of stable keys to shards, in Spark expressions alone."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import hash60, with_offsets

# Fixed value: the multiplier of the 64-bit linear congruential step that jump hashing is published with.
MULTIPLIER = 2862933555777941757
LOW32 = 0xFFFFFFFF
M_HIGH, M_LOW = MULTIPLIER >> 32, MULTIPLIER & LOW32


def _next(state: Column, most: int, base: int) -> Column:
    """One jump. The 64-bit key lies in two 32-bit halves, so that no product overflows under ANSI rules."""

    def times_low(x: Column) -> Column:  # x * M_LOW, x below 2**32, as (bits from 32 up, low 32 bits plus what the addend 1 needs)
        near = x.bitwiseAND(F.lit(0xFFFF)) * F.lit(M_LOW)
        far = F.shiftright(x, 16) * F.lit(M_LOW)
        both = near + F.shiftleft(far.bitwiseAND(F.lit(0xFFFF)), 16)
        return F.struct((F.shiftright(both + F.lit(1), 32) + F.shiftright(far, 16)).alias("up"), (both + F.lit(1)).bitwiseAND(F.lit(LOW32)).alias("plus_one"), both.bitwiseAND(F.lit(LOW32)).alias("low"))

    high, low, at = state["high"], state["low"], state["next"]
    lows = times_low(low)
    up = (lows["up"] + times_low(high)["low"] + (low * F.lit(M_HIGH)).bitwiseAND(F.lit(LOW32))).bitwiseAND(F.lit(LOW32))
    jump = F.floor((at + F.lit(1)).cast("double") * (F.lit(float(1 << 31)) / (F.shiftright(up, 1) + F.lit(1)).cast("double"))).cast("long")
    moved = F.struct(
        up.alias("high"),
        lows["plus_one"].alias("low"),
        F.when(at < F.lit(base), at).otherwise(state["shard"]).alias("shard"),
        at.alias("grown"),
        F.least(jump, F.lit(most)).alias("next"),
    )
    return F.when(at < F.lit(most), moved).otherwise(state)


def jump_shards(key: Column, shards: int) -> Column:
    """struct(shard, grown): the shard of a long key among `shards`, and among one more.

    Both come from the same chain of jumps: each count takes the last landing below itself. The chain
    is about ln(shards) long; rows whose chain outlasts the first steps go on as long as it may ever be.
    """
    if shards < 1:
        raise ValueError("shards must be at least 1")
    most = shards + 1
    none, long = F.lit(0).cast("long"), "long"
    start = F.struct(F.shiftrightunsigned(key, 32).cast(long).alias("high"), key.bitwiseAND(F.lit(LOW32)).cast(long).alias("low"), none.alias("shard"), none.alias("grown"), none.alias("next"))
    first = min(most, 8 + 3 * math.ceil(math.log(most + 1)))
    chain = F.aggregate(F.sequence(F.lit(1), F.lit(first)), start, lambda s, _: _next(s, most, shards))
    whole = F.transform(F.array(chain), lambda s: F.when(s["next"] >= F.lit(most), s).otherwise(F.aggregate(F.sequence(F.lit(1), F.lit(most)), s, lambda t, _: _next(t, most, shards))))[0]
    return F.struct(whole["shard"].cast("int").alias("shard"), whole["grown"].cast("int").alias("grown"))


def shard_by_key(df: DataFrame, keys: list[str], shards: int) -> DataFrame:
    """df with `shard`, `grown_shard` (with one shard more) and `slot` (place in the shard, gapless from 0).

    The key columns and the shard count decide the shard, nothing else; a null key counts as absent, so
    rows of equal keys, nulls among them, share a shard. Slots follow a hash of the key; rows that are
    equal in every key take neighbouring slots in any order. No rows give no rows.
    """
    placed = df.withColumn("__jump", jump_shards(F.xxhash64(*[F.col(k) for k in keys]), shards)).withColumn("__place", hash60(F.lit(17), *[F.col(k) for k in keys])).withColumn("__one", F.lit(1).cast("long"))
    placed = placed.select(*df.columns, F.col("__jump.shard").alias("shard"), F.col("__jump.grown").alias("grown_shard"), "__place", "__one")
    return with_offsets(placed, ["shard"], "__place", keys, "__one", "slot").drop("__place", "__one")


def sharded_documents(docs: DataFrame, shards: int = 24) -> DataFrame:
    """Documents by key: doc_id, size (UTF-8 bytes of the text, none for null, plus 8), text_crc32, law, shard, slot, grown_shard."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", (F.octet_length(text) + F.lit(8)).cast("long").alias("size"), F.crc32(text.cast("binary")).cast("long").alias("text_crc32"))
    out = shard_by_key(rows, ["doc_id"], shards)
    return out.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")
