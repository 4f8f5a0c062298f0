"""Best-fit packing of documents into sequences under several capacities at once."""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hash60, with_offsets, written
from .tokens import word_ids


@dataclass(frozen=True)
class Capacity:
    """What one sequence may hold: tokens, documents, and attention cost (the sum of squared lengths)."""

    tokens: int = 4096
    documents: int = 4096
    attention: int = 4096 * 4096

    def vector(self) -> np.ndarray:
        return np.array([self.tokens, self.documents, self.attention], np.int64)

    def fits_alone(self, length: int) -> bool:
        return bool((item(length) <= self.vector()).all())


def item(length: int) -> np.ndarray:
    return np.array([length, 1, length * length], np.int64)


def best_fit(counts: dict[int, int], capacity: Capacity, rule: str = "norm", weights: tuple[float, float, float] = (1.0, 1e-3, 1e-3)) -> np.ndarray:
    """Place counts[length] pieces of each length, longest first; rows (length, rank, pieces, sequence, offset).

    A row says: the pieces of this length with ranks rank .. rank + pieces - 1 go to the sequences
    sequence, sequence + 1, ... one each, at this offset. Among the open sequences in which a piece keeps
    within every capacity, rule "norm" takes the one whose residual vector it leaves shortest, rule
    "dot" the one whose residual vector has the largest product with it (both weighted, in parts of the
    capacity); ties go to the oldest. Sequences with the same content are one state with a count, so the
    work follows the number of distinct lengths, not of pieces.
    """
    if rule not in ("norm", "dot"):
        raise ValueError("rule is norm or dot")
    whole = capacity.vector()
    scale = np.asarray(weights, float) / whole.astype(float)
    w = np.asarray(weights, float)
    left, many, first = np.zeros((1024, 3), np.int64), np.zeros(1024, np.int64), np.zeros(1024, np.int64)
    states, sequences, runs = 0, 0, []

    def add(residual: np.ndarray, n: int, at: int) -> None:
        nonlocal left, many, first, states
        if states == len(many):
            left, many, first = (np.concatenate([x, np.zeros_like(x)]) for x in (left, many, first))
        left[states], many[states], first[states] = residual, n, at
        states += 1

    lengths = sorted((x for x, n in counts.items() if n > 0), reverse=True)
    smallest = item(lengths[-1]) if lengths else None
    for length in lengths:
        need, rank, todo = item(length), 0, counts[length]
        if not (need <= whole).all():
            raise ValueError(f"a piece of length {length} is over the capacity of an empty sequence")
        if states > 256:  # forget states that can take nothing any more
            open_ = (left[:states] >= smallest).all(axis=1) & (many[:states] > 0)
            k = int(open_.sum())
            if k < states // 2:
                left[:k], many[:k], first[:k] = left[:states][open_], many[:states][open_], first[:states][open_]
                states = k
        while todo:
            ok = np.flatnonzero((left[:states] >= need).all(axis=1) & (many[:states] > 0))
            if len(ok):
                if rule == "norm":
                    score = (((left[ok] - need) / whole) ** 2 * w).sum(axis=1)
                    s = ok[int(score.argmin())]
                else:
                    s = ok[int((left[ok] * scale * (need / whole)).sum(axis=1).argmax())]
                bins, residual, at = int(many[s]), left[s].copy(), int(first[s])
                per = int((residual // need).min()) if rule == "norm" else 1
                used = min(bins, max(1, todo // per)) if todo >= per else 1
                per = min(per, todo)
                many[s] -= used
                first[s] += used
            else:
                per = min(int((whole // need).min()), todo)
                used, residual, at = max(1, todo // per), whole.copy(), sequences
                sequences += used
            offset = int(whole[0] - residual[0])
            for i in range(per):
                runs.append((length, rank + i * used, used, at, offset + i * length))
            add(residual - per * need, used, at)
            rank += per * used
            todo -= per * used
    return np.array(runs, np.int64).reshape(-1, 5)


def token_pieces(docs: DataFrame, path: str, capacity: Capacity, end_id: int = 1) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: a document's ids and end_id, cut only where over the capacity."""
    most = capacity.tokens
    end = int(end_id).to_bytes(4, "little")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        coder = word_ids(path)
        for b in batches:
            for at in range(0, len(b), 512):
                part = b.iloc[at : at + 512]
                rows = []
                for doc, ids in zip(part["doc_id"], coder.encode(list(part["text"]))):
                    ids += end
                    n = len(ids) // 4
                    rows += [(doc, k, k * most, min(most, n - k * most), zlib.crc32(ids[4 * k * most : 4 * (k + 1) * most])) for k in range(-(-n // most))]
                yield pd.DataFrame(rows, columns=["doc_id", "piece", "start", "length", "ids_crc32"]).astype({"doc_id": "Int64"})

    return docs.select(F.col("doc_id").cast("long"), "text").mapInPandas(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def pack_pieces(pieces: DataFrame, capacity: Capacity, rule: str = "norm") -> DataFrame:
    """pieces with sequence_id and offset. pieces must be read from storage, as it is read twice.

    The driver gets one count per distinct length (at most the token capacity) and plans on those; each
    piece then finds its place from its rank among the pieces of its length. Pieces that are equal in every
    column take neighbouring ranks. No rows give no rows.
    """
    counts = {int(r[0]): int(r[1]) for r in pieces.groupBy("length").count().collect()}
    runs = best_fit(counts, capacity, rule)
    runs = runs[np.lexsort((runs[:, 1], runs[:, 0]))]
    ranked = with_offsets(
        pieces.withColumns({"__place": hash60(F.lit(3), F.col("doc_id"), F.col("piece")), "__one": F.lit(1).cast("long")}),
        ["length"], "__place", ["doc_id", "piece", "ids_crc32"], "__one", "__rank",
    ).drop("__place", "__one")
    sent = pieces.sparkSession.sparkContext.broadcast(runs)
    wide = np.int64(1) << 42

    def place(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        table = sent.value
        start = table[:, 0] * wide + table[:, 1]
        for b in batches:
            r = b.pop("__rank").to_numpy(np.int64)
            at = np.searchsorted(start, b["length"].to_numpy(np.int64) * wide + r, "right") - 1
            yield b.assign(sequence_id=table[at, 3] + r - table[at, 1], offset=table[at, 4])

    return ranked.mapInPandas(place, pieces.schema.simpleString()[7:-1].replace(":", " ") + ", sequence_id long, offset long")


def pack_documents(docs: DataFrame, path: str, capacity: Capacity | None = None, rule: str = "norm") -> DataFrame:
    """All documents packed: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    A null or empty text is the end id alone. Repeated rows are packed as often as they stand there.
    """
    capacity = capacity or Capacity()
    return pack_pieces(written(token_pieces(docs, path, capacity), "pieces"), capacity, rule)
