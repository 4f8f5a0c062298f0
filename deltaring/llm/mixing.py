"""Mixing sources to target weights by highest quotients over equal blocks of words, in Spark expressions alone."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import HASH_BITS, SPACE, with_offsets, written

#: Weights of the sources in code point order, over and over.
CYCLE = (5, 2, 1)
BLOCK_WORDS = 16
SHARD_BLOCKS = 1024


def n_words(text: Column) -> Column:
    """Words of a text, parted by the six ASCII white-space characters; a null text has none."""
    parts = F.split(F.coalesce(text, F.lit("")), f"{SPACE}+", -1)
    return F.transform(F.array(parts), lambda p: F.greatest(F.lit(0), F.size(p) - (p[0] == F.lit("")).cast("int") - (F.element_at(p, -1) == F.lit("")).cast("int")))[0].cast("long")


def seeded(seed: int, *cols: Column) -> Column:
    """60 bits of an MD5 digest; other engines can compute the same."""
    text = F.concat_ws(":", F.lit(str(seed)), *[F.coalesce(c.cast("string"), F.lit("")) for c in cols])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, HASH_BITS // 4), 16, 10).cast("long")


def source_targets(sources: DataFrame, weights: tuple[int, ...] = CYCLE, repeats: int = 3) -> DataFrame:
    """Adds rank, weight and target to one row per source (source, source_size).

    Targets share the sum of the sizes by weight, none above `repeats` times its source's size: sorted by
    the level at which each source fills up, the water level is the first that the rest can share.
    Windows here run over one row per source.
    """
    everything = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    by_name = sources.withColumn("rank", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())).cast("long"))
    by_name = by_name.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), ((F.col("rank") - 1) % len(weights) + 1).cast("int")))
    order = Window.orderBy("fill", "rank")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    after = order.rowsBetween(0, Window.unboundedFollowing)
    cap = F.col("source_size") * F.lit(repeats)
    levels = by_name.withColumn("fill", cap / F.col("weight")).withColumn("total", F.sum("source_size").over(everything))
    levels = levels.withColumn("level", (F.col("total") - F.coalesce(F.sum(cap).over(before), F.lit(0))) / F.sum("weight").over(after))
    levels = levels.withColumn("water", F.min(F.when(F.col("fill") >= F.col("level"), F.struct("fill", "rank", "level"))).over(everything)["level"])
    return levels.select("source", "source_size", "rank", "weight", "total", F.least(cap.cast("double"), F.col("water") * F.col("weight")).alias("target"))


def block_quotas(targets: DataFrame, block_words: int = BLOCK_WORDS, repeats: int = 3) -> DataFrame:
    """Adds blocks (of the source) and quota: seats of the Sainte-Laguë method, a seat being one block.

    Only seats that can be in doubt are ranked by quotient. With S seats and n sources, the divisor lies
    between total / (S + n/2) and total / (S - n/2); each source surely gets the seats it has under
    the larger one, and at most 3 n quotients lie between the two.
    """
    everything = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    t = targets.withColumn("seats", F.floor(F.col("total") / F.lit(float(block_words)) + 0.5)).withColumn("half", F.count("*").over(everything) / 2.0)
    t = t.withColumn("sure", F.when((F.col("seats") > F.col("half")) & (F.col("total") > 0), F.greatest(F.lit(0), F.floor(F.col("target") * (F.col("seats") - F.col("half")) / F.col("total") + 0.499999999))).otherwise(0).cast("long"))
    t = t.withColumn("most", F.when(F.col("total") > 0, F.floor(F.col("target") * (F.col("seats") + F.col("half")) / F.col("total") + 0.5) + 1).otherwise(0).cast("long"))
    t = t.withColumn("open", F.col("seats") - F.sum("sure").over(everything))
    doubt = t.where("most > sure and target > 0").select("rank", "open", "target", F.explode(F.sequence(F.col("sure"), F.col("most") - 1)).alias("seat"))
    won = doubt.withColumn("place", F.row_number().over(Window.orderBy((F.col("target") / (2 * F.col("seat") + 1)).desc(), "rank"))).where("place <= open").groupBy("rank").agg(F.count("*").alias("more"))
    blocks = F.ceil(F.col("source_size") / F.lit(float(block_words))).cast("long")
    return t.join(won, "rank", "left").select(
        "rank", "source", "source_size", "target", blocks.alias("blocks"),
        F.least(F.col("sure") + F.coalesce(F.col("more"), F.lit(0)), blocks * repeats).cast("long").alias("quota"),
    )


def _seeded_sql(seed: int, *parts: str) -> str:
    return f"cast(conv(substring(md5(cast(concat_ws(':', '{seed}', {', '.join(parts)}) as binary)), 1, {HASH_BITS // 4}), 16, 10) as bigint)"


def _spans(block_words: int, shard_blocks: int, seed: int) -> Column:
    """Word ranges of a document in the last pass, from begin, size, blocks, extra and rank of its row."""
    per = block_words * shard_blocks
    high = f"least((s + 1) * {shard_blocks}, blocks)"
    low = f"(s * {shard_blocks})"
    upto = "(cast(extra as decimal(19,0)) * cast({} as decimal(19,0))) div blocks"
    shards = f"""transform(sequence(begin div {per}, (begin + size - 1) div {per}), s -> named_struct(
        'base', s * {per} - begin, 'm', {high} - {low}, 'q', {upto.format(high)} - {upto.format(low)},
        'at', pmod({_seeded_sql(seed, "rank", "s")}, {high} - {low})))"""
    runs = "array(named_struct('a', 0L, 'b', greatest(x.at + x.q - x.m, 0L)), named_struct('a', x.at, 'b', least(x.at + x.q, x.m)))"
    cut = f"named_struct('from', greatest(x.base + r.a * {block_words}, 0L), 'until', least(x.base + r.b * {block_words}, size))"
    return F.expr(f"""case when size > 0 and extra > 0
        then filter(flatten(transform({shards}, x -> transform({runs}, r -> {cut}))), y -> y.until > y.from)
        else cast(array() as array<struct<from: bigint, until: bigint>>) end""")


def mixture(docs: DataFrame, weights: tuple[int, ...] = CYCLE, repeats: int = 3, block_words: int = BLOCK_WORDS, shard_blocks: int = SHARD_BLOCKS, seed: int = 11) -> DataFrame:
    """Adds size, source_size, target, taken, copies and spans to documents (doc_id, source, and a text or a size).

    A source's documents, in the order of a seeded hash, form one stream of words, cut into blocks of
    block_words and shards of shard_blocks blocks. The quota q of b blocks takes the whole stream q div b
    times and q mod b blocks once more; these are shared over the shards in proportion, in integers, and
    each shard takes a run of its blocks, round its end, from a seeded block on. So a document is nearly
    always taken whole or left. copies counts its whole takes, spans are the word ranges (from,
    until) of itself in the last pass, taken is the words of both.

    A null or blank text has size 0 and takes 0. A null source is a source, last in order. Rows with
    the same doc_id are documents of their own; among those that also have the same size either may be
    the one that is taken. Reruns agree, whatever the partitions. No rows give no rows.
    """
    sized = docs if "size" in docs.columns else docs.withColumn("size", n_words(F.col("text")))
    totals = sized.groupBy(F.col("source").cast("string").alias("source")).agg(F.sum("size").alias("source_size"))
    quotas = written(block_quotas(source_targets(totals, weights, repeats), block_words, repeats), "quotas")
    known = quotas.withColumnRenamed("source", "known_source")
    known = F.broadcast(known) if quotas.count() <= 100_000 else known  # a row per source; beyond that the join is shuffled
    rows = sized.join(known, F.col("source").eqNullSafe(F.col("known_source"))).drop("known_source")
    placed = with_offsets(rows.withColumn("place", seeded(seed, F.col("doc_id"))), ["rank"], "place", ["doc_id", "size"], "size", "begin")
    out = placed.withColumn("extra", F.expr("case when blocks > 0 then quota % blocks else 0L end"))
    out = out.withColumn("copies", F.expr("case when blocks > 0 then quota div blocks else 0L end")).withColumn("spans", _spans(block_words, shard_blocks, seed + 1))
    taken = F.expr("copies * size + aggregate(spans, 0L, (s, x) -> s + x.until - x.from)")
    return out.withColumn("taken", taken).select(*sized.columns, "source_size", "target", "taken", "copies", "spans")


def mixed_documents(docs: DataFrame, seed: int = 11) -> DataFrame:
    """doc_id, size, source_size, target, taken for every document."""
    sized = written(docs.select("doc_id", F.col("source").cast("string").alias("source"), n_words(F.col("text")).alias("size")), "sizes")
    return mixture(sized, seed=seed).select("doc_id", "size", "source_size", "target", "taken")


def mixed_texts(docs: DataFrame, seed: int = 11) -> DataFrame:
    """The mix as documents (doc_id, text, lang, source, n_chars): whole takes repeat a row, the last pass gives its words.

    The words of a last pass keep the white space that follows them; n_chars is counted anew for them.
    """
    columns = ["doc_id", "text", "lang", "source", "n_chars"]
    takes = mixture(docs.select(*columns), seed=seed).where("taken > 0")
    words = F.regexp_extract_all(F.col("text"), F.lit(f"({SPACE}*[^\\x20\\x09-\\x0D]+{SPACE}*)"), 1)
    part = F.transform(F.array(words), lambda w: F.array_join(F.flatten(F.transform("spans", lambda x: F.slice(w, (x["from"] + 1).cast("int"), (x["until"] - x["from"]).cast("int")))), ""))[0]
    size = F.col("size")
    last = F.when(F.size("spans") == 0, F.lit(None)).when((F.size("spans") == 1) & (F.col("spans")[0]["until"] - F.col("spans")[0]["from"] == size), F.col("text")).otherwise(part)
    texts = F.concat(F.array_repeat(F.col("text"), F.col("copies").cast("int")), F.filter(F.array(last), lambda x: x.isNotNull()))
    out = takes.withColumn("taken_text", F.explode(texts))
    return out.select("doc_id", F.col("taken_text").alias("text"), "lang", "source", F.length("taken_text").cast("long").alias("n_chars"))
