"""Rings as plan fragments: payloads of counts, scalars, moments (a column each), and listings.

A view is a DataFrame of key columns and payload columns. A ring says how a table's rows become a view,
how two views multiply (joining on the keys they share) and how a view is summed to fewer keys; the
tree code above never looks inside a payload.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.spec import CAT, QuerySpec


@dataclass(frozen=True)
class View:
    df: DataFrame
    keys: tuple[str, ...]
    attrs: tuple[str, ...] = ()


def grouped(df: DataFrame, keys: tuple[str, ...], sums: list[Column]) -> DataFrame:
    """Sums by key; over no keys one row, or none where df has none."""
    if keys:
        return df.groupBy(*keys).agg(*sums)
    return df.agg(*sums, F.count("*").alias("__rows")).where("__rows > 0").drop("__rows")


class Ring:
    """What all rings offer. `payload` names the columns of a view over some attributes."""

    spec: QuerySpec

    def payload(self, attrs: tuple[str, ...]) -> list[str]:
        raise NotImplementedError

    def single(self, rows: DataFrame, keys: tuple[str, ...], attrs: tuple[str, ...]) -> View:
        """A table's rows as payloads, one by one."""
        raise NotImplementedError

    def leaf(self, rows: DataFrame, keys: tuple[str, ...], attrs: tuple[str, ...]) -> View:
        """A table's rows summed by key."""
        return self.total(self.single(rows, keys, attrs), keys)

    def product(self, a: View, b: View, broadcast: str | None = None) -> View:
        raise NotImplementedError

    def total(self, v: View, keys: tuple[str, ...]) -> View:
        raise NotImplementedError

    def combined(self, views: list[View], keys: tuple[str, ...], broadcast: str | None = None) -> View:
        """The product of connected views, summed to some keys. broadcast "a": the first is small."""
        out, rest = views[0], list(views[1:])
        while rest:
            at = next((i for i, c in enumerate(rest) if set(c.keys) & set(out.keys)), 0)
            out = self.product(out, rest.pop(at), broadcast)
        return self.total(out, keys)

    def negated(self, v: View) -> View:
        raise NotImplementedError

    def width(self, attrs: tuple[str, ...]) -> int:
        return len(self.payload(attrs))

    def row_bytes(self, attrs: tuple[str, ...]) -> int:
        """What a row of a view takes in memory, about."""
        return 16 * self.width(attrs)

    def rows_per_row(self, attrs: tuple[str, ...]) -> int:
        """Rows of a leaf view that one row of a table can make at most."""
        return 1

    def union(self, views: list[View]) -> View:
        out = views[0].df
        for v in views[1:]:
            out = out.unionByName(v.df)
        return View(out, views[0].keys, views[0].attrs)

    def nonzero(self, v: View) -> View:
        """Without the keys at which every component is zero; one zero count alone may be a delta's."""
        some = F.lit(False)
        for c in self.payload(v.attrs):
            some = some | (F.col(c) != 0)
        return View(v.df.where(some), v.keys, v.attrs)

    def state(self, v: View, keys: tuple[str, ...]) -> View:
        return self.nonzero(self.total(v, keys))


def matched(left: DataFrame, right: DataFrame, shared: list[str], broadcast: str | None = None) -> DataFrame:
    """Join on shared keys; without any, every row with every row, for factors of a product (one side is then sent to
    all tasks, so the caller knows it to be small). broadcast: "a" (left) or "b", a side of a size the caller knows."""
    left, right = (F.broadcast(left) if broadcast == "a" else left), (F.broadcast(right) if broadcast == "b" else right)
    return left.join(right, shared) if shared else left.crossJoin(right if broadcast else F.broadcast(right))


def joined(a: View, b: View, columns_a: list[str], columns_b: list[str], broadcast: str | None) -> tuple[DataFrame, tuple[str, ...]]:
    """The join of two views; payload columns become l_* and r_*."""
    left = a.df.select(*a.keys, *[F.col(c).alias(f"l_{c}") for c in columns_a])
    right = b.df.select(*b.keys, *[F.col(c).alias(f"r_{c}") for c in columns_b])
    return matched(left, right, [k for k in a.keys if k in b.keys], broadcast), a.keys + tuple(k for k in b.keys if k not in a.keys)


class _Columns(Ring):
    """Rings with one payload column per entry. Expressions are SQL, which the session parses in one call each."""

    def sums(self, attrs: tuple[str, ...]) -> list[Column]:
        return [F.expr(f"sum(`{c}`) AS `{c}`") for c in self.payload(attrs)]

    def lifted(self, attrs: tuple[str, ...]) -> list[str]:
        raise NotImplementedError

    def multiplied(self, a: tuple[str, ...], b: tuple[str, ...]) -> list[str]:
        raise NotImplementedError

    def single(self, rows: DataFrame, keys: tuple[str, ...], attrs: tuple[str, ...]) -> View:
        return View(rows.selectExpr(*[f"`{k}`" for k in keys], *self.lifted(attrs)), keys, attrs)

    def product(self, a: View, b: View, broadcast: str | None = None) -> View:
        both, keys = joined(a, b, self.payload(a.attrs), self.payload(b.attrs), broadcast)
        return View(both.selectExpr(*[f"`{k}`" for k in keys], *self.multiplied(a.attrs, b.attrs)), keys, tuple(sorted({*a.attrs, *b.attrs})))

    def total(self, v: View, keys: tuple[str, ...]) -> View:
        return View(grouped(v.df, keys, self.sums(v.attrs)), keys, v.attrs)

    def negated(self, v: View) -> View:
        return View(v.df.selectExpr(*[f"`{k}`" for k in v.keys], *[f"-`{c}` AS `{c}`" for c in self.payload(v.attrs)]), v.keys, v.attrs)


class CountRing(_Columns):
    """Integers: every attribute value is 1, a row weighs its multiplicity."""

    def __init__(self, spec: QuerySpec):
        self.spec = spec

    def payload(self, attrs):
        return ["c"]

    def lifted(self, attrs):
        return ["mult AS c"]

    def multiplied(self, a, b):
        return ["l_c * r_c AS c"]


class SumProductRing(_Columns):
    """Numbers: the sum over the join of a product of one function per attribute.

    functions: attribute -> SQL over its value; attributes without one count as 1. numeric: the type sums are kept in.
    """

    def __init__(self, spec: QuerySpec, functions: dict[str, str], numeric: str = "decimal(38,4)"):
        self.spec, self.functions, self.numeric = spec, functions, numeric

    def payload(self, attrs):
        return ["v"]

    def lifted(self, attrs):
        exact = self.numeric.startswith("decimal")
        factors = [f"CAST(mult AS {'decimal(18,0)' if exact else self.numeric})"]
        factors += [f"CAST({self.functions[a]} AS {'decimal(12,2)' if exact else self.numeric})" for a in attrs if a in self.functions]
        return [f"CAST({' * '.join(factors)} AS {self.numeric}) AS v"]

    def multiplied(self, a, b):
        narrow = "decimal(30,4)" if self.numeric.startswith("decimal") else self.numeric
        return [f"CAST(CAST(l_v AS {narrow}) * CAST(r_v AS {narrow}) AS {self.numeric}) AS v"]

    def sums(self, attrs):
        return [F.expr(f"CAST(sum(v) AS {self.numeric}) AS v")]


class MomentRing(_Columns):
    """Count, sums and sums of products of continuous attributes, a column per entry of the upper triangle.

    numeric "decimal" is exact for values with at most two decimals and fails on overflow; "double" is fast and
    depends on the order of additions in the last digits.
    """

    C, S, Q = "decimal(18,0)", "decimal(28,2)", "decimal(34,4)"

    def __init__(self, spec: QuerySpec, numeric: str = "double"):
        if numeric not in ("double", "decimal"):
            raise ValueError("numeric is double or decimal")
        wrong = [a.name for a in spec.attributes if a.kind == CAT]
        if wrong:
            raise ValueError(f"categorical attributes need the sparse ring: {wrong}")
        self.spec, self.exact = spec, numeric == "decimal"

    def payload(self, attrs):
        attrs = sorted(attrs)
        return ["c", *[f"s_{a}" for a in attrs], *[f"q_{a}__{b}" for i, a in enumerate(attrs) for b in attrs[i:]]]

    def lifted(self, attrs):
        attrs = sorted(attrs)
        x = {a: f"CAST(`{a}` AS {'decimal(12,2)' if self.exact else 'double'})" for a in attrs}
        w = f"CAST(mult AS {'decimal(10,0)' if self.exact else 'double'})"
        out = ["mult AS c", *[f"{w} * {x[a]} AS `s_{a}`" for a in attrs]]
        return out + [f"{w} * {x[a]} * {x[b]} AS `q_{a}__{b}`" for i, a in enumerate(attrs) for b in attrs[i:]]

    def _typed(self, side: str, name: str) -> str:
        if name == "c":
            return f"CAST({side}_c AS {self.C if self.exact else 'double'})"
        return f"CAST(`{side}_{name}` AS {self.S if name[0] == 's' else self.Q})" if self.exact else f"`{side}_{name}`"

    def multiplied(self, a, b):
        def has(side: str, *names: str) -> bool:
            return all(n in (a if side == "l" else b) for n in names)

        both = sorted({*a, *b})
        count = {s: self._typed(s, "c") for s in "lr"}
        other = {"l": "r", "r": "l"}
        out = ["l_c * r_c AS c"]
        for x in both:
            out.append(" + ".join(f"{self._typed(s, f's_{x}')} * {count[other[s]]}" for s in "lr" if has(s, x)) + f" AS `s_{x}`")
        for i, x in enumerate(both):
            for y in both[i:]:
                terms = [f"{self._typed(s, f'q_{x}__{y}')} * {count[other[s]]}" for s in "lr" if has(s, x, y)]
                terms += [f"{self._typed(s, f's_{x}')} * {self._typed(other[s], f's_{y}')}" for s in "lr" if has(s, x) and has(other[s], y)]
                out.append(" + ".join(terms) + f" AS `q_{x}__{y}`")
        return out

    def entries(self, v: View) -> DataFrame:
        """keys, attr_u, attr_v, value: "1" for the constant; one row per count, sum and product of the upper triangle."""
        attrs = sorted(v.attrs)
        pairs = [("1", "1", "c"), *[("1", a, f"s_{a}") for a in attrs], *[(a, b, f"q_{a}__{b}") for i, a in enumerate(attrs) for b in attrs[i:]]]
        kind = "decimal(38,4)" if self.exact else "double"
        rows = ", ".join(f"named_struct('attr_u', '{a}', 'attr_v', '{b}', 'value', CAST(`{c}` AS {kind}))" for a, b, c in pairs)
        return v.df.selectExpr(*[f"`{k}`" for k in v.keys], f"inline(array({rows}))")

    def full_matrix(self, v: View) -> DataFrame:
        """entries with the lower triangle restored."""
        e = self.entries(v)
        return e.unionByName(e.where("attr_u <> attr_v").select(*v.keys, F.col("attr_v").alias("attr_u"), F.col("attr_u").alias("attr_v"), "value"))


class ListingRing(Ring):
    """Relations as payloads: each key holds the tuples over some attributes with their multiplicities.

    Laid out flat: a row per key and tuple. Union adds multiplicities, join multiplies them.
    """

    def __init__(self, spec: QuerySpec, listed: tuple[str, ...]):
        self.spec, self.listed = spec, listed

    def payload(self, attrs):
        return [*[a for a in sorted(attrs) if a in self.listed], "mult"]

    def _tuple(self, attrs):
        return self.payload(attrs)[:-1]

    def single(self, rows, keys, attrs):
        return View(rows.select(*keys, *self.payload(attrs)), keys, attrs)

    def product(self, a, b, broadcast=None):
        both, keys = joined(a, b, self.payload(a.attrs), self.payload(b.attrs), broadcast)
        columns = [F.col(f"l_{c}").alias(c) for c in self._tuple(a.attrs)] + [F.col(f"r_{c}").alias(c) for c in self._tuple(b.attrs)]
        return View(both.select(*keys, *columns, (F.col("l_mult") * F.col("r_mult")).alias("mult")), keys, tuple(sorted({*a.attrs, *b.attrs})))

    def total(self, v, keys):
        return View(grouped(v.df, (*keys, *self._tuple(v.attrs)), [F.sum("mult").alias("mult")]), keys, v.attrs)

    def negated(self, v):
        return View(v.df.withColumn("mult", -F.col("mult")), v.keys, v.attrs)

    def nonzero(self, v):
        return View(v.df.where("mult <> 0"), v.keys, v.attrs)
