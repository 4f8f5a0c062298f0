"""Moments of many continuous attributes as blocks: of one table in one pass, and as a ring for view trees."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spec import CAT, QuerySpec
from .rings import MomentRing, Ring, View, matched
from .sparse import JointMomentRing, SparseMomentRing, layout_of


def upper(m: int) -> tuple[np.ndarray, np.ndarray]:
    return np.triu_indices(m + 1)


def gram_block(df: DataFrame, columns: list[str] | str, keys: list[str] | None = None, mult: str | None = None) -> DataFrame:
    """keys, i, j, v: the upper triangle of the moments of some columns, or of the elements of one array column.

    Index 0 is the constant, so (0, 0) is the count and (0, j) a sum. Each task holds one block per key it
    meets (keys should be few) and sends its entries once; the final sum is a plain aggregate. Null
    and NaN are refused.
    """
    keys = keys or []
    array = isinstance(columns, str)
    names = [columns] if array else list(columns)
    source = df.select(*keys, *[F.col(c).cast("array<double>" if array else "double") for c in names], *([F.col(mult).cast("double").alias("__mult")] if mult else []))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[tuple, np.ndarray] = {}
        for b in batches:
            if not b.num_rows:
                continue
            if array:
                column = b.column(len(keys))
                if column.null_count:
                    raise ValueError(f"null in {columns}")
                x = column.flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
            else:
                x = np.column_stack([b.column(len(keys) + i).to_numpy(zero_copy_only=False) for i in range(len(names))])
            if not np.isfinite(x).all():
                raise ValueError("null, NaN or infinity in a continuous attribute")
            x = np.concatenate([np.ones((b.num_rows, 1)), x], axis=1)
            w = x * b.column(b.num_columns - 1).to_numpy(zero_copy_only=False)[:, None] if mult else x
            if keys:
                rows = list(zip(*[b.column(i).to_pylist() for i in range(len(keys))]))
                order: dict[tuple, list[int]] = {}
                for r, k in enumerate(rows):
                    order.setdefault(k, []).append(r)
                parts = order.items()
            else:
                parts = [((), slice(None))]
            for k, at in parts:
                g = w[at].T @ x[at]
                sums[k] = sums[k] + g if k in sums else g
        for k, g in sums.items():
            i, j = upper(g.shape[0] - 1)
            yield pa.RecordBatch.from_arrays([pa.array([v] * len(i)).cast(t) for v, t in zip(k, key_types)] + [pa.array(i, pa.int32()), pa.array(j, pa.int32()), pa.array(g[i, j])], names=[*keys, "i", "j", "v"])

    from pyspark.sql.pandas.types import to_arrow_type

    key_types = [to_arrow_type(source.schema[k].dataType) for k in keys]
    schema = ", ".join([f"{k} {source.schema[k].dataType.simpleString()}" for k in keys] + ["i int", "j int", "v double"])
    return source.mapInArrow(run, schema).groupBy(*keys, "i", "j").agg(F.sum("v").alias("v"))


def _codes(columns: list[pa.Array], n: int) -> np.ndarray:
    """Equal rows of some columns have equal numbers; nulls are equal."""
    out = np.zeros(n, np.int64)
    for c in columns:
        c = c.combine_chunks() if isinstance(c, pa.ChunkedArray) else c
        code = c.dictionary_encode(null_encoding="encode").indices.to_numpy(zero_copy_only=False).astype(np.int64)
        _, out = np.unique(out * (int(code.max(initial=0)) + 1) + code, return_inverse=True)
    return out


def _unpacked(column: pa.Array, m: int) -> tuple[np.ndarray, np.ndarray]:
    """Blocks as rows of the upper triangle, and which of them are short."""
    lengths = np.diff(column.offsets.to_numpy())
    values = column.flatten().to_numpy(zero_copy_only=False)
    if not np.isfinite(values).all():
        raise ValueError("null, NaN or infinity in a continuous attribute, or a sum beyond doubles")
    i, j = upper(m)
    short = lengths == m + 1
    if m == 0:  # a count alone is its own short form
        return values.reshape(-1, 1), short
    out = np.empty((len(lengths), len(i)))
    is_short = np.repeat(short, lengths)
    out[~short] = values[~is_short].reshape(-1, len(i))
    x = values[is_short].reshape(-1, m + 1)
    out[short] = x[:, i] * x[:, j] / x[:, :1]
    return out, short


def _packed(blocks: np.ndarray, short: np.ndarray, m: int) -> pa.Array:
    """The inverse: a short block is its first row, count and sums."""
    lengths = np.where(short, m + 1, blocks.shape[1])
    keep = np.arange(blocks.shape[1])[None, :] < lengths[:, None]
    offsets = np.concatenate([[0], np.cumsum(lengths)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(blocks[keep]))


class BlockRing(Ring):
    """Moments of many continuous attributes (tens to hundreds): one array of doubles per key.

    A block is the upper triangle of the symmetric matrix over the constant and the attributes in order of
    name, row by row: the count, the sums, then the products. The block of a single row, or of a single join of single rows, has
    rank one and is kept short, as its count and sums alone, so views along foreign keys are as wide as their
    attributes and not as the square. Joins are Spark's; products and sums of arrays run on Arrow batches, each
    task adding up what it meets before anything is shuffled. Sums of integers are exact up to 2^53.
    """

    CHUNK = 1024

    def __init__(self, spec: QuerySpec):
        wrong = [a.name for a in spec.attributes if a.kind == CAT]
        if wrong:
            raise ValueError(f"categorical attributes need the sparse ring: {wrong}")
        self.spec = spec

    def payload(self, attrs):
        return ["block"]

    def width(self, attrs):
        return (len(attrs) + 1) * (len(attrs) + 2) // 2

    def row_bytes(self, attrs):
        return 8 * self.width(attrs) + 64

    def _schema(self, df: DataFrame, keys: tuple[str, ...]) -> str:
        return ", ".join([f"`{k}` {df.schema[k].dataType.simpleString()}" for k in keys] + ["block array<double>"])

    def _partial(self, df: DataFrame, keys: tuple[str, ...], m: int, blocks_of: Callable[[pa.RecordBatch], tuple[np.ndarray, np.ndarray]]) -> DataFrame:
        """Blocks of rows, summed by key within each chunk of a task, or over no keys within the task."""
        chunk = self.CHUNK

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total, rows, one = None, 0, False
            for whole in batches:
                for at in range(0, whole.num_rows, chunk):
                    b = whole.slice(at, chunk)
                    blocks, short = blocks_of(b)
                    if not keys:
                        one = rows == 0 and len(blocks) == 1 and bool(short[0])
                        rows += len(blocks)
                        total = blocks.sum(axis=0) if total is None else total + blocks.sum(axis=0)
                        continue
                    order = np.argsort(codes := _codes([b.column(i) for i in range(len(keys))], b.num_rows), kind="stable")
                    codes = codes[order]
                    starts = np.flatnonzero(np.concatenate([[True], codes[1:] != codes[:-1]]))
                    single = np.diff(np.concatenate([starts, [len(codes)]])) == 1
                    first = pa.array(order[starts])
                    sums = blocks[order] if single.all() else np.add.reduceat(blocks[order], starts, axis=0)
                    yield pa.RecordBatch.from_arrays([*[b.column(i).take(first) for i in range(len(keys))], _packed(sums, single & short[order][starts], m)], names=[*keys, "block"])
            if total is not None:
                yield pa.RecordBatch.from_arrays([_packed(total[None, :], np.array([one]), m)], names=["block"])

        return df.mapInArrow(run, self._schema(df, keys))

    def _summed(self, partial: DataFrame, keys: tuple[str, ...], m: int) -> DataFrame:
        """One block per key from those of the tasks: rows of a key stand together and are added as they stream by."""
        if not keys:
            together = partial.repartition(1)  # a block per task
        else:
            together = partial.repartition(*keys).sortWithinPartitions(*keys)
        n = len(keys)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            last, block, one = None, None, False
            for b in batches:
                if not b.num_rows:
                    continue
                blocks, short = _unpacked(b.column(n), m)
                codes = _codes([b.column(i) for i in range(n)], b.num_rows)
                starts = np.flatnonzero(np.concatenate([[True], codes[1:] != codes[:-1]]))
                single = np.diff(np.concatenate([starts, [b.num_rows]])) == 1
                sums = blocks if single.all() else np.add.reduceat(blocks, starts, axis=0)
                short = single & short[starts]
                heads = pa.RecordBatch.from_arrays([b.column(i).take(pa.array(starts)) for i in range(n)], names=list(keys)) if n else None
                if last is not None:
                    if last == (heads.slice(0, 1).to_pylist() if n else [{}]):
                        sums[0], short[0] = sums[0] + block, False
                    else:
                        yield pa.RecordBatch.from_arrays([*[pa.array([last[0][k]], heads.schema.field(k).type) for k in keys], _packed(block[None, :], np.array([one]), m)], names=[*keys, "block"])
                if len(sums) > 1:
                    yield pa.RecordBatch.from_arrays([*[heads.column(i).slice(0, len(sums) - 1) for i in range(n)], _packed(sums[:-1], short[:-1], m)], names=[*keys, "block"])
                last, block, one = (heads.slice(len(sums) - 1, 1).to_pylist() if n else [{}]), sums[-1].copy(), bool(short[-1])
                kinds = [heads.schema.field(k).type for k in keys]
            if last is not None:
                yield pa.RecordBatch.from_arrays([*[pa.array([last[0][k]], t) for k, t in zip(keys, kinds)], _packed(block[None, :], np.array([one]), m)], names=[*keys, "block"])

        return together.mapInArrow(run, self._schema(partial, keys))

    def single(self, rows, keys, attrs):
        weighed = ", ".join(["CAST(mult AS double)", *[f"mult * CAST(`{a}` AS double)" for a in sorted(attrs)]])
        return View(rows.where("mult <> 0").selectExpr(*[f"`{k}`" for k in keys], f"array({weighed}) AS block"), keys, tuple(sorted(attrs)))

    def combined(self, views, keys, broadcast=None):
        out, rest = views[0], list(views[1:])
        df, have, attrs = out.df.select(*out.keys, F.col("block").alias("b0")), out.keys, [sorted(out.attrs)]
        while rest:
            at = next((i for i, c in enumerate(rest) if set(c.keys) & set(have)), 0)
            v = rest.pop(at)
            df = matched(df, v.df.select(*v.keys, F.col("block").alias(f"b{len(attrs)}")), [k for k in v.keys if k in have], broadcast)
            have += tuple(k for k in v.keys if k not in have)
            attrs.append(sorted(v.attrs))
            broadcast = None
        steps, known = [], attrs[0]
        for mine in attrs[1:]:
            steps.append(_places(known, mine))
            known = sorted([*known, *mine])
        m, n = len(known), len(keys)

        def multiplied(b: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
            blocks, short = _unpacked(b.column(n), len(attrs[0]))
            for k, (left, right) in enumerate(steps, 1):
                more, also = _unpacked(b.column(n + k), len(attrs[k]))
                blocks, short = blocks[:, left] * more[:, right], short & also
            return blocks, short

        df = df.select(*keys, *[f"b{k}" for k in range(len(attrs))])
        return View(self._summed(self._partial(df, keys, m, multiplied), keys, m), keys, tuple(known))

    def product(self, a, b, broadcast=None):
        return self.combined([a, b], a.keys + tuple(k for k in b.keys if k not in a.keys), broadcast)

    def total(self, v, keys):
        return self.combined([v], keys)

    def negated(self, v):
        return View(v.df.select(*v.keys, F.transform("block", lambda x: -x).alias("block")), v.keys, v.attrs)

    def nonzero(self, v):
        return View(v.df.where(F.exists("block", lambda x: x != 0)), v.keys, v.attrs)

    def entries(self, v: View) -> DataFrame:
        """keys, attr_u, attr_v, value: as those of MomentRing, a row per entry of the upper triangle."""
        names = ["1", *sorted(v.attrs)]
        m = len(names) - 1
        i, j = upper(m)
        name = lambda at: F.split(F.lit(",".join(names[k] for k in at)), ",")[F.col("place")]
        size, m1 = F.size("block"), m + 1
        at = lambda k: F.get("block", F.lit(int(k)))
        full = F.when(size == m1, F.flatten(F.transform(F.sequence(F.lit(0), F.lit(m)), lambda p: F.transform(F.slice("block", p + 1, m1 - p), lambda y: F.get("block", p) * y / at(0))))).otherwise(F.col("block")) if m else F.col("block")
        return v.df.select(*v.keys, F.posexplode(full).alias("place", "value")).select(*v.keys, name(i).alias("attr_u"), name(j).alias("attr_v"), "value")


def _places(a: list[str], b: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """For each entry of the product's block, the entries of the factors' blocks whose product it is."""
    if set(a) & set(b):
        raise ValueError("views of a product share no attribute")
    both = ["", *sorted([*a, *b])]
    places = []
    for side in (a, b):
        names = ["", *side]
        at = {(names[i], names[j]): k for k, (i, j) in enumerate(zip(*upper(len(side))))}
        mine = set(names)
        i, j = upper(len(both) - 1)
        own = [tuple(sorted(x if x in mine else "" for x in (both[p], both[q]))) for p, q in zip(i, j)]
        places.append(np.array([at[o] for o in own]))
    return places[0], places[1]


def layout_for(spec: QuerySpec, tables: dict[str, DataFrame] | None = None) -> str:
    """columns up to 12 attributes, block beyond; joint where categories have few combinations in the tables, else sparse."""
    if any(a.kind == CAT for a in spec.attributes):
        return layout_of(spec, tables) if tables else "sparse"
    return "columns" if len(spec.attributes) <= 12 else "block"


def ring_for(spec: QuerySpec, tables: dict[str, DataFrame] | None = None, numeric: str = "double") -> Ring:
    """The moment ring that suits the attributes and tables; exact sums are not for blocks."""
    layout = layout_for(spec, tables)
    if layout in ("sparse", "joint"):
        return (JointMomentRing if layout == "joint" else SparseMomentRing)(spec, numeric)
    return BlockRing(spec) if layout == "block" and numeric == "double" else MomentRing(spec, numeric)
