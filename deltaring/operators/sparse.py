"""Moments with categories: payload entries are little relations, laid out as one row per live entry.

A payload is a polynomial cut off above a degree. An entry is a term, a sorted list of (attribute,
category), with no category for continuous attributes, and a value: the empty term is the count, one factor a
sum, two a sum of products. A category is its own square, so the square of a categorical attribute
is read off its single terms. This is the moment ring over relations, and with categories only the
counts behind mutual information; with degree 4 it serves polynomial models.
"""

from __future__ import annotations

from itertools import combinations, combinations_with_replacement
from math import comb

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.spec import CAT, CONT, QuerySpec
from .rings import Ring, View, grouped, joined, matched

TERM = "array<struct<a:string,c:string>>"
WIDE, NARROW = "decimal(38,4)", "decimal(30,4)"


class SparseMomentRing(Ring):
    """v: the entry's value; n: the signed number of join rows behind it, which tells a dead entry (0 in a state) exactly."""

    def __init__(self, spec: QuerySpec, numeric: str = "double", max_degree: int = 2):
        self.spec, self.exact, self.degree = spec, numeric == "decimal", max_degree
        self.kinds = {a.name: a.kind for a in spec.attributes}
        if numeric not in ("double", "decimal"):
            raise ValueError("numeric is double or decimal")
        if self.exact and max_degree > 2:
            raise ValueError("exact terms above degree 2 would need more decimals; use double")

    def payload(self, attrs):
        return ["term", "v", "n"]

    def width(self, attrs):
        raise ValueError("the number of entries follows the live categories; count the rows of a view")

    def row_bytes(self, attrs):
        return 160

    def rows_per_row(self, attrs):
        """Terms of at most `degree` factors over the attributes."""
        return comb(len(attrs) + self.degree, self.degree)

    def _sums(self) -> list[Column]:
        return [F.sum("v").cast(WIDE if self.exact else "double").alias("v"), F.sum("n").alias("n")]

    def _monomials(self, attrs) -> tuple[list[str], list[tuple[str, ...]]]:
        conts = [a for a in sorted(attrs) if self.kinds[a] == CONT]
        return [a for a in sorted(attrs) if self.kinds[a] == CAT], [m for d in range(self.degree + 1) for m in combinations_with_replacement(conts, d)]

    def _lifted(self, rows, keys, attrs) -> DataFrame:
        """keys, categories, a column per monomial of continuous attributes, and n."""
        cats, monomials = self._monomials(attrs)
        number, wide = ("decimal(12,2)", WIDE) if self.exact else ("double", "double")
        weighed = lambda m: f"CAST({' * '.join([f'CAST(mult AS {'decimal(10,0)' if self.exact else 'double'})', *[f'CAST(`{a}` AS {number})' for a in m]])} AS {wide})"
        return rows.selectExpr(*[f"`{c}`" for c in (*keys, *cats)], *[f"{weighed(m)} AS __m{i}" for i, m in enumerate(monomials)], "mult AS __n")

    def _tall(self, dense: DataFrame, keys, attrs) -> View:
        """A row per term of each row of _lifted."""
        cats, monomials = self._monomials(attrs)
        entries = []
        for k in range(min(len(cats), self.degree) + 1):
            for some in combinations(cats, k):
                for i, m in enumerate(monomials):
                    if k + len(m) <= self.degree:
                        factors = sorted([*[(a, True) for a in some], *[(a, False) for a in m]])
                        term = ", ".join(f"named_struct('a', '{a}', 'c', {f'`{a}`' if cat else 'CAST(NULL AS string)'})" for a, cat in factors)
                        entries.append(f"named_struct('term', CAST(array({term}) AS {TERM}), 'v', CAST(__m{i} AS {WIDE if self.exact else 'double'}), 'n', __n)")
        return View(dense.selectExpr(*[f"`{k}`" for k in keys], f"inline(array({', '.join(entries)}))"), keys, attrs)

    def single(self, rows, keys, attrs):
        return self._tall(self._lifted(rows, keys, attrs), keys, attrs)

    def leaf(self, rows, keys, attrs):
        cats, monomials = self._monomials(attrs)
        dense = grouped(self._lifted(rows, keys, attrs), (*keys, *cats), [F.expr(f"sum({c}) AS {c}") for c in [*[f"__m{i}" for i in range(len(monomials))], "__n"]])
        tall = self._tall(dense, keys, attrs)
        return self.total(tall, keys) if cats else tall

    def product(self, a, b, broadcast=None):
        """Entries that meet under a key and stay within the degree; a plain join, so a key with many entries is split
        like any other skewed key."""
        shared = [k for k in a.keys if k in b.keys]
        left = a.df.select(*a.keys, F.col("term").alias("l_term"), F.col("v").alias("l_v"), F.col("n").alias("l_n"), F.size("term").alias("l_d"))
        right = b.df.select(*b.keys, F.col("term").alias("r_term"), F.col("v").alias("r_v"), F.col("n").alias("r_n"), F.size("term").alias("r_d"))
        keys = a.keys + tuple(k for k in b.keys if k not in a.keys)
        both = matched(left, right, shared, broadcast).where(F.col("l_d") + F.col("r_d") <= self.degree)
        v = (F.col("l_v").cast(NARROW) * F.col("r_v").cast(NARROW)).cast(WIDE) if self.exact else F.col("l_v") * F.col("r_v")
        term = F.when(F.col("r_d") == 0, F.col("l_term")).when(F.col("l_d") == 0, F.col("r_term")).otherwise(F.sort_array(F.concat("l_term", "r_term")))
        return View(both.select(*keys, term.alias("term"), v.alias("v"), (F.col("l_n") * F.col("r_n")).alias("n")), keys, tuple(sorted({*a.attrs, *b.attrs})))

    def total(self, v, keys):
        return View(grouped(v.df, (*keys, "term"), self._sums()), keys, v.attrs)

    def negated(self, v):
        return View(v.df.withColumns({"v": -F.col("v"), "n": -F.col("n")}), v.keys, v.attrs)

    def nonzero(self, v):
        return View(v.df.where("v <> 0 or n <> 0"), v.keys, v.attrs)

    def live(self, v: View) -> View:
        """Of a state (no negative multiplicities): entries with rows behind them."""
        return View(v.df.where("n <> 0"), v.keys, v.attrs)

    def terms(self, v: View) -> View:
        """The view with a row per term."""
        return v

    def entries(self, v: View) -> DataFrame:
        """keys, attr_u, cat_u, attr_v, cat_v, value, n: "1" for the constant, the diagonal of categories filled in."""
        at = lambda i, f: F.get("term", F.lit(i))[f]
        none = F.lit(None).cast("string")
        row = lambda u, cu, x, cx: F.struct(u.alias("attr_u"), cu.alias("cat_u"), x.alias("attr_v"), cx.alias("cat_v"))
        size = F.size("term")
        own = F.when(size == 2, row(at(0, "a"), at(0, "c"), at(1, "a"), at(1, "c"))).otherwise(row(F.lit("1"), none, F.coalesce(at(0, "a"), F.lit("1")), at(0, "c")))
        cats = [a for a, k in self.kinds.items() if k == CAT]
        square = F.when((size == 1) & at(0, "a").isin(cats), row(at(0, "a"), at(0, "c"), at(0, "a"), at(0, "c")))
        both = F.filter(F.array(own, square), lambda x: x.isNotNull()) if cats else F.array(own)
        return self.terms(v).df.select(*v.keys, F.inline(both), F.col("v").alias("value"), "n").select(*v.keys, "attr_u", "cat_u", "attr_v", "cat_v", "value", "n")


class JointMomentRing(SparseMomentRing):
    """The same moments, kept by joint category: a row per key and tuple of live categories of all attributes below a
    view, with a column per monomial of the continuous ones. `terms` spreads a view into entries.

    A key of a fact table has few joint tuples but many terms, so views down there are a fraction of the sparse
    ring's; at the root there are up to as many tuples as combinations of categories, which `layout_of` checks.
    """

    def payload(self, attrs):
        cats, monomials = self._monomials(attrs)
        return [*[f"k_{a}" for a in cats], *[self._name(m) for m in monomials], "n"]

    @staticmethod
    def _name(m: tuple[str, ...]) -> str:
        return "m_" + "__".join(m)

    def row_bytes(self, attrs):
        return 24 * len(self.payload(attrs))

    def rows_per_row(self, attrs):
        return 1

    @property
    def _wide(self) -> str:
        return WIDE if self.exact else "double"

    def single(self, rows, keys, attrs):
        cats, monomials = self._monomials(attrs)
        named = [*[f"`{a}` AS `k_{a}`" for a in cats], *[f"__m{i} AS `{self._name(m)}`" for i, m in enumerate(monomials)], "__n AS n"]
        return View(self._lifted(rows, keys, attrs).selectExpr(*[f"`{k}`" for k in keys], *named), keys, tuple(sorted(attrs)))

    def leaf(self, rows, keys, attrs):
        return self.total(self.single(rows, keys, attrs), keys)

    def product(self, a, b, broadcast=None):
        both, keys = joined(a, b, self.payload(a.attrs), self.payload(b.attrs), broadcast)
        attrs = tuple(sorted({*a.attrs, *b.attrs}))
        cats, monomials = self._monomials(attrs)
        side = lambda m, of: self._name(tuple(x for x in m if x in of.attrs))
        narrow = (lambda c: f"CAST(`{c}` AS {NARROW})") if self.exact else (lambda c: f"`{c}`")
        out = [f"`{'l' if x in a.attrs else 'r'}_k_{x}` AS `k_{x}`" for x in cats]
        out += [f"CAST({narrow('l_' + side(m, a))} * {narrow('r_' + side(m, b))} AS {self._wide}) AS `{self._name(m)}`" for m in monomials]
        return View(both.selectExpr(*[f"`{k}`" for k in keys], *out, "l_n * r_n AS n"), keys, attrs)

    def total(self, v, keys):
        cats, monomials = self._monomials(v.attrs)
        sums = [F.expr(f"CAST(sum(`{self._name(m)}`) AS {self._wide}) AS `{self._name(m)}`") for m in monomials]
        return View(grouped(v.df, (*keys, *[f"k_{a}" for a in cats]), [*sums, F.expr("sum(n) AS n")]), keys, v.attrs)

    def negated(self, v):
        cats, monomials = self._monomials(v.attrs)
        columns = [*[self._name(m) for m in monomials], "n"]
        return View(v.df.selectExpr(*[f"`{k}`" for k in (*v.keys, *[f"k_{a}" for a in cats])], *[f"-`{c}` AS `{c}`" for c in columns]), v.keys, v.attrs)

    def nonzero(self, v):
        _, monomials = self._monomials(v.attrs)
        return View(v.df.where(" OR ".join(["n <> 0", *[f"`{self._name(m)}` <> 0" for m in monomials]])), v.keys, v.attrs)

    def _dense(self, v):
        """The view as _lifted gives it."""
        cats, monomials = self._monomials(v.attrs)
        return v.df.selectExpr(*[f"`{k}`" for k in v.keys], *[f"`k_{a}` AS `{a}`" for a in cats], *[f"`{self._name(m)}` AS __m{i}" for i, m in enumerate(monomials)], "n AS __n")

    def terms(self, v):
        return SparseMomentRing.total(self, self._tall(self._dense(v), v.keys, v.attrs), v.keys)


class LateMomentRing(JointMomentRing):
    """The same moments, by joint category below and as live entries over all attributes.

    Joint tuples of a fact table's keys are spread into entries where the last attribute joins them, and summed in each
    task before they are sent anywhere. fine: variables whose values have few rows each, such as keys of
    orders; views keyed by one are left unsummed (a view may have several rows for a key), since sums there cost
    a shuffle and save nothing.
    """

    def __init__(self, spec: QuerySpec, fine: tuple[str, ...] = (), numeric: str = "double", max_degree: int = 2):
        super().__init__(spec, numeric, max_degree)
        self.fine = frozenset(fine)

    def _spread(self, attrs) -> bool:
        return set(attrs) == set(self.kinds)

    def payload(self, attrs):
        return ["term", "v", "n"] if self._spread(attrs) else super().payload(attrs)

    def row_bytes(self, attrs):
        return 160 if self._spread(attrs) else super().row_bytes(attrs)

    def rows_per_row(self, attrs):
        return SparseMomentRing.rows_per_row(self, attrs) if self._spread(attrs) else 1

    def _entries(self, v: View) -> View:
        """A view of joint tuples with a row per term, unsummed."""
        return self._tall(self._dense(v), v.keys, v.attrs)

    def single(self, rows, keys, attrs):
        one = JointMomentRing(self.spec, "decimal" if self.exact else "double", self.degree).single(rows, keys, attrs)
        return self._entries(one) if self._spread(attrs) else one

    def leaf(self, rows, keys, attrs):
        one = self.single(rows, keys, attrs)
        return one if self.fine & set(keys) else self.total(one, keys)

    def product(self, a, b, broadcast=None):
        if self._spread(a.attrs) or self._spread(b.attrs):
            a, b = (v if self._spread(v.attrs) else self._entries(v) for v in (a, b))
            return SparseMomentRing.product(self, a, b, broadcast)
        joint = JointMomentRing(self.spec, "decimal" if self.exact else "double", self.degree).product(a, b, broadcast)
        return self._entries(joint) if self._spread(joint.attrs) else joint

    def combined(self, views, keys, broadcast=None):
        if not self.fine & set(keys):
            return super().combined(views, keys, broadcast)
        out, rest = views[0], list(views[1:])
        while rest:
            at = next((i for i, c in enumerate(rest) if set(c.keys) & set(out.keys)), 0)
            out = self.product(out, rest.pop(at), broadcast)
        payload = self.payload(out.attrs)
        return View(out.df.select(*keys, *payload), keys, out.attrs)

    def _of(self, v: View):
        return SparseMomentRing if self._spread(v.attrs) else JointMomentRing

    def total(self, v, keys):
        return self._of(v).total(self, v, keys)

    def negated(self, v):
        return self._of(v).negated(self, v)

    def nonzero(self, v):
        return self._of(v).nonzero(self, v)

    def terms(self, v):
        return v if self._spread(v.attrs) else JointMomentRing.terms(self, v)


def layout_of(spec: QuerySpec, tables: dict[str, DataFrame], most: int = 1 << 20) -> str:
    """"joint" if the categories of all attributes, as counted, have at most so many combinations, else "sparse"."""
    product = 1.0
    for alias in spec.tables:
        cats = [a for a in spec.of_table(alias) if a.kind == CAT]
        if cats:
            found = tables[alias].select(*[F.expr(f"approx_count_distinct({a.sql})").alias(a.name) for a in cats]).first()
            for n in found:
                product *= n + 1
    return "joint" if product <= most else "sparse"


def compose(outer: str, inner: str, spec: QuerySpec, **options):
    """The ring with payload algebra `outer` over values of `inner`: moments over numbers or over relations."""
    from .rings import CountRing, ListingRing, MomentRing

    made = {
        ("count", "numbers"): lambda: CountRing(spec),
        ("moments", "numbers"): lambda: MomentRing(spec, **options),
        ("moments", "relations"): lambda: SparseMomentRing(spec, **options),
        ("relations", "moments"): lambda: JointMomentRing(spec, **options),
        ("count", "relations"): lambda: ListingRing(spec, **options),
    }
    if (outer, inner) not in made:
        raise ValueError(f"no ring {outer} over {inner}")
    return made[outer, inner]()
