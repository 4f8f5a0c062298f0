"""The toy data base of two relations, and polynomial algebra in plain Python to check rings against."""

from __future__ import annotations

from collections import defaultdict

R_ROWS = [("a1", 1), ("a2", 2), ("a2", 3), ("a3", 7)]
S_ROWS = [("a1", "p", 10), ("a1", "q", 20), ("a2", "p", 30), ("a4", "q", 40)]
BULK = [("a1", 5, 1), ("a2", 3, -1), ("a4", 6, 1)]


def frames(spark, numeric_c: bool = False):
    r = spark.createDataFrame(R_ROWS, "a string, b int")
    rows = [(a, {"p": 4, "q": 5}[c], d) for a, c, d in S_ROWS] if numeric_c else S_ROWS
    s = spark.createDataFrame(rows, f"a string, c {'int' if numeric_c else 'string'}, d int")
    return {"R": r, "S": s}


def poly_add(a, b, sign=1):
    out = defaultdict(float, a)
    for t, v in b.items():
        out[t] += sign * v
    return {t: v for t, v in out.items() if v}


def poly_mul(a, b, degree=2):
    out = defaultdict(float)
    for s, x in a.items():
        for t, y in b.items():
            if len(s) + len(t) <= degree:
                out[tuple(sorted(s + t))] += x * y
    return {t: v for t, v in out.items() if v}


def poly_lift(attr, value, categorical, degree=2):
    """1 + x + x*x for numbers, 1 + [attr=value] for categories (whose square is itself)."""
    if categorical:
        return {(): 1.0, ((attr, str(value)),): 1.0}
    return {(): 1.0, **{((attr, ""),) * d: float(value) ** d for d in range(1, degree + 1) if value}}


def poly_join(rows, kinds, degree=2):
    """Payload of flat rows: list of (dict attr -> value, multiplicity)."""
    total = {}
    for row, mult in rows:
        p = {(): float(mult)}
        for attr, kind in kinds.items():
            p = poly_mul(p, poly_lift(attr, row[attr], kind == "cat", degree), degree)
        total = poly_add(total, p)
    return total


def sparse_payload(rows):
    """Collected (term, v) of the sparse ring in the same form."""
    return {tuple((f["a"], f["c"] or "") for f in r["term"]): float(r["v"]) for r in rows if float(r["v"])}
