"""Near-duplicate documents: an inverted join of MinHash coordinates, links confirmed on full shingle sets."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Working, hash60, written
from .wordhash import mixed, word_hashes

SHINGLE = 5


@dataclass(frozen=True)
class Matching:
    """coordinates: length of a signature. matches: coordinates in which a candidate pair must agree.

    With 32 and 13, a pair of sets of likeness 0.75 is missed with a chance of about 1 in 100,000; links are
    confirmed on the sets, so none is false. percent: least likeness, in hundredths.
    hub_rounds: rounds that test documents against one document per list before all other pairs are; up to
    most_hub_rounds of them while long lists are open and still come together.
    long_list: lists with more documents than this are compared in blocks, not as pairs of rows; what counts as a
    candidate is the same in both.
    block_rows, block_bytes: what one side of such a block may hold.
    """

    coordinates: int = 32
    matches: int = 13
    percent: int = 75
    hub_rounds: int = 2
    most_hub_rounds: int = 2
    long_list: int = 64
    block_rows: int = 1024
    block_bytes: int = 8 << 20


def _constants(n: int) -> tuple[np.ndarray, np.ndarray]:
    r = np.random.default_rng(20240501)
    return r.integers(0, 1 << 64, n, np.uint64, endpoint=False), r.integers(0, 1 << 63, n, np.uint64) * np.uint64(2) + np.uint64(1)


def shingle_set(text: str | None) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's runs of five words, A to Z lower-cased; fewer words are one run."""
    h = word_hashes(text, lower=True)
    if not len(h):
        return h
    k = min(SHINGLE, len(h))
    _, odd = _constants(SHINGLE)
    runs = np.full(len(h) - k + 1, k, np.uint64)
    for i in range(k):
        runs += h[i : len(h) - k + 1 + i] * odd[i]
    return np.unique(mixed(runs))


def signature(shingles: np.ndarray, coordinates: int) -> np.ndarray:
    """Per coordinate the least image of the set under one of as many mixes, upper 32 bits; none for the empty set."""
    if not len(shingles):
        return np.zeros(0, np.int32)
    flip, odd = _constants(coordinates)
    least = np.full(coordinates, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), 2048):
        least = np.minimum(least, ((shingles[at : at + 2048, None] ^ flip) * odd).min(axis=0))
    return (least >> np.uint64(32)).astype(np.uint32).view(np.int32)


def sketches(docs: DataFrame, coordinates: int) -> DataFrame:
    """doc_id, n_shingles, digest (of the set; null for the empty one), signature."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            sets = [shingle_set(t) for t in b["text"]]
            yield pd.DataFrame({
                "doc_id": b["doc_id"].astype("Int64"),
                "n_shingles": [len(s) for s in sets],
                "digest": [xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None for s in sets],
                "signature": [signature(s, coordinates) for s in sets],
            })

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInPandas(run, "doc_id long, n_shingles long, digest binary, signature array<int>")


def shared_postings(reps: DataFrame, m: Matching) -> DataFrame:
    """id, n, key, length (of the key's list), central: the postings that can lead to a pair with enough matches.

    A document is posted under each coordinate and value. Two documents that agree in `matches`
    coordinates share one of the coordinates - matches + 1 rarest of either, so the others are
    skipped, the longest lists first; a value that no other document has can't be shared at all.
    central sums the lengths of all lists a document is in: greatest for what most of a group was copied from.
    """
    spread = reps.select(F.col("doc_id").alias("id"), F.col("n_shingles").alias("n"), F.posexplode("signature").alias("c", "v"))
    keyed = spread.select("id", "n", (F.shiftleft(F.col("c").cast("long"), 32) + F.col("v").cast("long").bitwiseAND(F.lit(0xFFFFFFFF))).alias("key"))
    lengths = keyed.groupBy("key").agg(F.count("*").alias("length")).where("length > 1")  # summed in each task first, a key may be hot
    shared = keyed.join(lengths, "key")
    own = Window.partitionBy("id")
    prefix = m.coordinates - m.matches + 1
    ranked = shared.withColumn("place", F.row_number().over(own.orderBy("length", "key"))).withColumn("many", F.count("*").over(own)).withColumn("central", F.sum("length").over(own))
    return ranked.where(F.col("place") <= prefix - (m.coordinates - F.col("many"))).select("id", "n", "key", "length", "central")


def alike(n: Column, m: Column, percent: int) -> Column:
    """Whether sets of these sizes can be alike enough."""
    return (F.least(n, m) * 100 >= F.greatest(n, m) * percent) & (n > 0)


def confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets are alike enough."""
    left = pairs.join(sets.select(F.col("id").alias("a"), F.col("shingles").alias("of_a")), "a")
    both = left.join(sets.select(F.col("id").alias("b"), F.col("shingles").alias("of_b")), "b")
    counted = both.select("a", "b", (F.size("of_a") + F.size("of_b")).alias("n"), F.size(F.array_intersect("of_a", "of_b")).alias("common"))
    return counted.where(F.col("common") * 100 >= (F.col("n") - F.col("common")) * percent).select("a", "b")


def components(edges: DataFrame, work: Working) -> DataFrame:
    """id, root over the ids in edges (a, b), root being the least id of the component.

    Each round takes the least root among the neighbours and then the root's root; it ends when nothing
    changes. Tables are written to shared storage between rounds.
    """
    both = edges.select("a", "b").where("a <> b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")).where("a <> b"))
    near = work.written(both.distinct(), "edges")
    roots = work.written(near.groupBy(F.col("a").alias("id")).agg(F.least(F.min("b"), F.col("a")).alias("root")), "roots")
    while True:
        seen = near.join(roots.select(F.col("id").alias("b"), "root"), "b").groupBy(F.col("a").alias("id")).agg(F.min("root").alias("found"))
        best = roots.join(seen, "id").select("id", F.col("root").alias("old"), F.least("root", "found").alias("root"))
        further = roots.select(F.col("id").alias("root"), F.col("root").alias("further"))
        now = work.written(best.join(further, "root", "left").select("id", "old", F.least("root", F.coalesce("further", "root")).alias("root")), "roots")
        roots = now.select("id", "root")
        if now.where("old <> root").isEmpty():
            return roots


def merged(labels: DataFrame, edges: DataFrame, work: Working) -> DataFrame:
    """labels (id, comp) after joining the components that edges (a, b) connect; the same labels if they connect none."""
    ends = edges.join(labels.select(F.col("id").alias("a"), F.col("comp").alias("x")), "a").join(labels.select(F.col("id").alias("b"), F.col("comp").alias("y")), "b")
    between = work.written(ends.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), "between")
    if between.isEmpty():
        return labels
    roots = components(between, work).select(F.col("id").alias("comp"), "root")
    return work.written(labels.join(roots, "comp", "left").select("id", F.coalesce("root", "comp").alias("comp")), "labels")


def hub_pairs(postings: DataFrame, labels: DataFrame, m: Matching, turn: int, most: int = 2) -> DataFrame:
    """a, b: each document with hubs of its lists that are not yet in its component, those of most lists first.

    A list's hub is its most central document in the first turn, later one by a seeded hash.
    """
    lists = postings.join(labels, "id")
    rank = -F.col("central") if turn == 0 else hash60(F.lit(turn), F.col("id"), F.shiftright("key", 34))
    hubs = lists.groupBy("key").agg(F.min(F.struct(rank.alias("h"), "id", "n", "comp")).alias("hub"))
    met = lists.join(hubs, "key").where((F.col("comp") != F.col("hub.comp")) & alike(F.col("n"), F.col("hub.n"), m.percent))
    counts = met.groupBy(F.col("id").alias("a"), F.col("hub.id").alias("b")).agg(F.count("*").alias("lists"))
    return counts.withColumn("place", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("lists"), "b"))).where(F.col("place") <= most).select("a", "b")


def open_lists(postings: DataFrame, labels: DataFrame) -> DataFrame:
    """Postings of the lists that still hold documents of different components."""
    lists = postings.join(labels, "id")
    mixed_keys = lists.groupBy("key").agg(F.min("comp").alias("low"), F.max("comp").alias("high")).where("low <> high").select("key")
    return lists.join(mixed_keys, "key", "left_semi")


def pairs_of_short_lists(lists: DataFrame, reps: DataFrame, m: Matching) -> DataFrame:
    """a, b: all pairs of different components in a list, that agree in enough coordinates."""
    left, right = (lists.select("key", F.col("id").alias(i), F.col("n").alias(f"n_{i}"), F.col("comp").alias(f"comp_{i}")) for i in "ab")
    pairs = left.join(right, "key").where((F.col("a") < F.col("b")) & (F.col("comp_a") != F.col("comp_b")) & alike(F.col("n_a"), F.col("n_b"), m.percent)).select("a", "b").distinct()
    for i in "ab":
        pairs = pairs.join(reps.select(F.col("doc_id").alias(i), F.col("signature").alias(f"sig_{i}")), i)
    agreed = F.size(F.filter(F.zip_with("sig_a", "sig_b", lambda x, y: x == y), lambda x: x))
    return pairs.where(agreed >= m.matches).select("a", "b")


def common_counts(a: list[np.ndarray], b: list[np.ndarray], width: int = 2048) -> np.ndarray:
    """Sizes of the intersections of all sets of a with all of b, from 0/1 matrices of the elements found twice."""
    values = np.concatenate([*a, *b])
    row = np.repeat(np.arange(len(a) + len(b)), [len(x) for x in [*a, *b]])
    _, column, times = np.unique(values, return_inverse=True, return_counts=True)
    place = np.cumsum(times > 1) - 1
    keep = times[column] > 1
    row, column = row[keep], place[column[keep]]
    order = np.argsort(column, kind="stable")
    row, column = row[order], column[order]
    out = np.zeros((len(a), len(b)), np.float32)
    for low in range(0, int(place[-1]) + 1 if len(place) else 0, width):
        i, j = np.searchsorted(column, [low, low + width])
        x = np.zeros((len(a) + len(b), width), np.float32)
        x[row[i:j], column[i:j] - low] = 1.0
        out += x[: len(a)] @ x[len(a) :].T
    return out


def agreeing(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """In how many coordinates each signature of a agrees with each of b."""
    out = np.zeros((len(a), len(b)), np.int16)
    for c in range(a.shape[1]):
        out += a[:, c, None] == b[None, :, c]
    return out


def links_of_long_lists(lists: DataFrame, sets: DataFrame, reps: DataFrame, m: Matching) -> DataFrame:
    """a, b: links between different components in long lists, enough to join all that are linked there.

    A list is cut into parts of bounded size, every two parts are compared whole as blocks, first by their
    signatures and, where enough coordinates agree, on the full sets; a block gives a spanning forest of its
    links. Rows do not grow as the pairs do: each document is sent once per part of its list.
    """
    with_sets = lists.select("key", "id", "comp").join(sets, "id").join(reps.select(F.col("doc_id").alias("id"), "signature"), "id")
    sizes = with_sets.groupBy("key").agg(F.count("*").alias("rows"), F.sum(F.size("shingles") * F.lit(8)).alias("bytes"))
    sizes = sizes.select("key", F.greatest(F.ceil(F.col("rows") / m.block_rows), F.ceil(F.col("bytes") / m.block_bytes)).cast("int").alias("parts"))
    parted = with_sets.join(sizes, "key").withColumn("part", (hash60(F.lit(9), F.col("id")) % F.col("parts")).cast("int"))
    other = parted.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    blocks = other.select("key", F.least("part", "other").alias("x"), F.greatest("part", "other").alias("y"), "part", "id", "comp", "shingles", "signature")

    def links(key: tuple, p: pd.DataFrame) -> pd.DataFrame:
        _, x, y = key
        a, b = p[p["part"] == x], p[p["part"] == y]
        if not len(a) or not len(b) or p["comp"].nunique() < 2:
            return pd.DataFrame({"a": [], "b": []}).astype("int64")
        near = agreeing(np.stack(a["signature"].to_numpy()), np.stack(b["signature"].to_numpy())) >= m.matches
        _, comp = np.unique(np.concatenate([a["comp"], b["comp"]]), return_inverse=True)
        near &= comp[: len(a), None] != comp[None, len(a) :]
        rows, columns = near.any(axis=1), near.any(axis=0)
        if not rows.any():
            return pd.DataFrame({"a": [], "b": []}).astype("int64")
        a, b, near = a[rows], b[columns], near[np.ix_(rows, columns)]
        of = lambda q: [np.asarray(s, np.int64) for s in q["shingles"]]
        sa, sb = of(a), of(b)
        common = common_counts(sa, sb)
        na, nb = (np.array([len(s) for s in q], np.float32) for q in (sa, sb))
        _, comp = np.unique(np.concatenate([a["comp"], b["comp"]]), return_inverse=True)
        ca, cb = comp[: len(a)], comp[len(a) :]
        ids_a, ids_b = a["id"].to_numpy(), b["id"].to_numpy()
        root, out = np.arange(comp.max() + 1), []
        for i in range(len(a)):  # row by row, so that memory follows the block and not its links
            linked = np.flatnonzero(near[i] & (100 * common[i] >= m.percent * (na[i] + nb - common[i])) & (root[cb] != root[ca[i]]))
            if len(linked):
                others, first = np.unique(root[cb[linked]], return_index=True)
                for r, j in zip(others, linked[first]):
                    out.append((ids_a[i], ids_b[j]))
                    root[root == r] = root[ca[i]]
        return pd.DataFrame(out, columns=["a", "b"]).astype("int64")

    return blocks.groupBy("key", "x", "y").applyInPandas(lambda key, p: links(key, p), "a long, b long")


def near_duplicates(docs: DataFrame, m: Matching = Matching()) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every document.

    Documents whose sets of distinct runs of five words have a likeness of 75 in 100 or more are linked;
    component_id is the least doc_id that links reach, kept marks that document. Equal sets are
    folded to one first, so copies never meet in pairs. Large groups of near copies come together
    through hubs; documents still apart are then compared all, in blocks where lists are long, so no link
    between different components is left out. A null or blank text has the empty set and is linked with nothing, so is a
    null doc_id (component_id null, kept); rows with one doc_id are one document. No rows give no rows.
    """
    spark = docs.sparkSession
    work = Working(spark, "near-duplicates")
    sketched = written(sketches(docs, m.coordinates), "sketches")
    some = sketched.where("digest is not null and doc_id is not null")
    groups = some.groupBy("digest").agg(F.min(F.struct("doc_id", "n_shingles", "signature")).alias("rep"), F.count("*").alias("copies"))
    groups = work.written(groups.select("digest", "copies", "rep.*"), "groups")
    postings = work.written(shared_postings(groups, m), "postings")
    ids = work.written(postings.select("id").distinct(), "candidates")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for at in range(0, len(b), 1000):
                part = b.iloc[at : at + 1000]
                yield pd.DataFrame({"id": part["doc_id"], "shingles": [shingle_set(t).view(np.int64) for t in part["text"]]})

    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(ids.select(F.col("id").alias("doc_id")), "doc_id", "left_semi")
    sets = work.written(texts.mapInPandas(run, "id long, shingles array<long>"), "sets")
    labels = work.written(ids.select("id", F.col("id").alias("comp")), "labels")
    for turn in range(m.most_hub_rounds):
        if turn >= m.hub_rounds and open_lists(postings, labels).where(F.col("length") > m.long_list).isEmpty():
            break
        before, labels = labels, merged(labels, work.written(confirmed(hub_pairs(postings, labels, m, turn), sets, m.percent), "links"), work)
        if turn >= m.hub_rounds and labels is before:
            break
    lists = work.written(open_lists(postings, labels), "open-lists")
    short = confirmed(pairs_of_short_lists(lists.where(F.col("length") <= m.long_list), groups, m), sets, m.percent)
    long = links_of_long_lists(lists.where(F.col("length") > m.long_list), sets, groups, m)
    labels = merged(labels, work.written(short.unionByName(long), "links"), work)
    # Only groups of copies and linked documents can have another component than themselves. Groups with a
    # 256th of all documents or more, at most 256 of them, are sent to all tasks; the others are joined, blank texts
    # going anywhere.
    total = sketched.count()
    known = groups.join(labels.select(F.col("id").alias("doc_id"), "comp"), "doc_id", "left").select("digest", F.coalesce("comp", "doc_id").alias("comp"), "copies", "doc_id")
    known = written(known.where("copies > 1 or comp <> doc_id").select("digest", "comp", "copies"), "components")
    work.done()
    hot = known.where(F.col("copies") * 256 >= total)
    found = sketched.select("doc_id", "n_shingles", "digest").join(F.broadcast(hot.select("digest", F.col("comp").alias("hot_comp"))), "digest", "left")
    place = F.when(F.col("digest").isNull() | F.col("hot_comp").isNotNull(), F.concat(F.lit("-"), F.coalesce(F.col("doc_id"), F.lit(0)).cast("string")).cast("binary")).otherwise(F.col("digest"))
    rest = known.where(F.col("copies") * 256 < total).select(F.col("digest").alias("place"), "comp")
    found = found.withColumn("place", place).join(rest, "place", "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("hot_comp", "comp", "doc_id"))
    return found.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))
