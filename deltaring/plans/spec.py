"""What is to be learned from: tables, an equi-join graph, attributes with kinds, free variables, a label."""

from __future__ import annotations

import re
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

CONT, CAT = "cont", "cat"
#: Payload columns; keys of views can't be called so.
RESERVED = {"c", "v", "n", "term", "mult", "block"}


@dataclass(frozen=True)
class Attribute:
    """name: how payloads call it. expr: SQL over the table's columns (the name itself if left out)."""

    name: str
    table: str
    kind: str = CONT
    expr: str | None = None

    def __post_init__(self):
        if self.kind not in (CONT, CAT):
            raise ValueError(f"attribute {self.name}: kind {self.kind!r} is neither {CONT!r} nor {CAT!r}")

    @property
    def sql(self) -> str:
        return self.expr or self.name


class SpecError(ValueError):
    pass


@dataclass(frozen=True)
class QuerySpec:
    """A sum of products over a natural join.

    tables: alias -> table name (a table may stand under two aliases, for self-joins).
    joins: pairs "alias.column" = "alias.column"; columns that are equal in a row of pairs are one join variable.
    attributes: what the payload describes. free: names of attributes by which results are grouped.
    where: alias -> SQL filter, applied to the table and to its updates alike, before anything else.
    null_numeric: "error", "drop" or a number that stands for nulls of continuous attributes.
    null_category: "keep" (null is a category) or "drop".
    """

    tables: dict[str, str]
    joins: tuple[tuple[str, str], ...]
    attributes: tuple[Attribute, ...] = ()
    free: tuple[Attribute, ...] = ()
    label: str | None = None
    where: dict[str, str] = field(default_factory=dict)
    null_numeric: str | float = "error"
    null_category: str = "keep"

    def variables(self) -> dict[str, dict[str, str]]:
        """variable -> {alias: column}; a variable is named after its first column in the order of joins."""
        group: dict[str, str] = {}

        def find(x: str) -> str:
            while group.setdefault(x, x) != x:
                x = group[x]
            return x

        for a, b in self.joins:
            x, y = find(a), find(b)
            if x != y:
                group[y] = x
        out: dict[str, dict[str, str]] = {}
        for side in [s for pair in self.joins for s in pair]:
            alias, column = side.split(".")
            out.setdefault(find(side), {}).setdefault(alias, column)
        names: dict[str, dict[str, str]] = {}
        for root, columns in out.items():
            name = root.split(".")[1]
            while name in names:
                name += "_"
            names[name] = columns
        return names

    def table_variables(self, alias: str) -> dict[str, str]:
        """variable -> column of one table."""
        return {v: columns[alias] for v, columns in self.variables().items() if alias in columns}

    def of_table(self, alias: str) -> tuple[Attribute, ...]:
        return tuple(a for a in self.attributes if a.table == alias)

    def validate(self, tables: dict[str, DataFrame]) -> QuerySpec:
        """Fail on what can't work, before any job: missing tables and columns, kinds that do not fit types, joins
        of different types, names used twice. Nothing is read but schemas."""
        for alias in self.tables:
            if alias not in tables:
                raise SpecError(f"no data for table {alias}")
        for a, b in self.joins:
            kinds = []
            for side in (a, b):
                alias, _, column = side.partition(".")
                if alias not in self.tables:
                    raise SpecError(f"join column {side}: no such table")
                if column not in tables[alias].columns:
                    raise SpecError(f"join column {side}: no such column")
                kinds.append(tables[alias].schema[column].dataType)
            numbers = all(isinstance(k, (T.IntegerType, T.LongType, T.ShortType)) for k in kinds)
            if kinds[0] != kinds[1] and not numbers:
                raise SpecError(f"{a} and {b} have types {kinds[0].simpleString()} and {kinds[1].simpleString()}")
        names = [a.name for a in (*self.attributes, *self.free)]
        if len(set(names)) != len(names):
            raise SpecError("attribute names must differ")
        if set(names) & set(self.variables()):
            raise SpecError(f"join variables have these names: {sorted(set(names) & set(self.variables()))}; name the attributes otherwise and give their expr")
        taken = RESERVED & {*self.variables(), *(f.name for f in self.free)}
        if taken:
            raise SpecError(f"views have payload columns of these names: {sorted(taken)}")
        for a in (*self.attributes, *self.free):
            if a.table not in self.tables:
                raise SpecError(f"attribute {a.name}: no table {a.table}")
            try:
                kind = tables[a.table].select(F.expr(a.sql).alias("x")).schema["x"].dataType
            except Exception as e:
                raise SpecError(f"attribute {a.name}: {a.sql} can't be computed from {a.table}") from e
            if a.kind == CONT and not isinstance(kind, T.NumericType):
                raise SpecError(f"attribute {a.name}: a continuous attribute can't be of type {kind.simpleString()}")
        if self.label is not None and self.label not in names:
            raise SpecError(f"label {self.label} is not an attribute")
        return self

    def rows(self, alias: str, df: DataFrame) -> DataFrame:
        """Filtered rows of a table or of its delta: join variables, attributes, free attributes, and mult."""
        if alias in self.where:
            df = df.where(self.where[alias])
        free = [a for a in self.free if a.table == alias]
        return self._selected(df, {v: c for v, c in self.table_variables(alias).items()}, list(self.of_table(alias)), free)

    def _selected(self, df: DataFrame, variables: dict[str, str], values: list[Attribute], free: list[Attribute]) -> DataFrame:
        columns = [f"`{c}` AS `{v}`" for v, c in variables.items()] + [f"{self._value(a)} AS `{a.name}`" for a in values] + [f"{a.sql} AS `{a.name}`" for a in free]
        out = df.selectExpr(*columns, f"CAST({'mult' if 'mult' in df.columns else '1'} AS bigint) AS mult")
        drop = [a for a in values if (self.null_numeric if a.kind == CONT else self.null_category) == "drop"]
        return out.where(" AND ".join(f"`{a.name}` IS NOT NULL" for a in drop)) if drop else out

    def factor_rows(self, alias: str, factors: list[DataFrame], keys: tuple[str, ...]) -> list[tuple[DataFrame, tuple[str, ...], tuple[str, ...]]]:
        """(rows, keys, attributes) of each factor of an update of a table; each column of the table is in one factor."""
        known = {c for f in factors for c in f.columns}
        needs = lambda sql: {x for x in re.findall(r"[A-Za-z_][A-Za-z0-9_]*", re.sub(r"'[^']*'", "", sql)) if x in known}
        out, todo = [], {a.name: a for a in (*self.of_table(alias), *[f for f in self.free if f.table == alias])}
        where = self.where.get(alias)
        for f in factors:
            variables = {v: c for v, c in self.table_variables(alias).items() if c in f.columns and v in keys}
            mine = [todo.pop(name) for name, a in list(todo.items()) if needs(a.sql) and needs(a.sql) <= set(f.columns)]
            if where is not None and needs(where) <= set(f.columns):
                f, where = f.where(where), None
            free = [a for a in mine if a in self.free]
            values = [a for a in mine if a not in self.free]
            rows = self._selected(f, variables, values, free)
            out.append((rows, (*[v for v in keys if v in variables], *[a.name for a in free]), tuple(sorted(a.name for a in values))))
        if todo or where is not None:
            raise SpecError(f"no factor of {alias} has all columns of {sorted(todo) or where}")
        return out

    def _value(self, a: Attribute) -> str:
        if a.kind == CAT:
            return f"CAST({a.sql} AS string)"
        if isinstance(self.null_numeric, (int, float)):
            return f"coalesce({a.sql}, {float(self.null_numeric)!r}D)"
        if self.null_numeric == "error":
            return f"CASE WHEN ({a.sql}) IS NOT NULL THEN ({a.sql}) ELSE raise_error('null in continuous attribute {a.name}') END"
        return f"({a.sql})"


def load(spark: SparkSession, sf_dir: str, spec: QuerySpec) -> dict[str, DataFrame]:
    return {alias: spark.read.parquet(f"{sf_dir}/{table}.parquet") for alias, table in spec.tables.items()}
