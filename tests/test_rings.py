import random

import pytest
from pyspark.sql import functions as F

from deltaring.operators.evaluate import evaluate, leaf_view
from deltaring.operators.rings import CountRing, ListingRing, MomentRing, SumProductRing, View
from deltaring.operators.sparse import LateMomentRing, SparseMomentRing, compose
from deltaring.plans.spec import CAT, Attribute, QuerySpec
from deltaring.plans.tree import build_view_tree
from deltaring.sources.store import ViewStore

from . import toy


def spec(kinds):
    where = {"b": "R", "c": "S", "d": "S"}
    return QuerySpec({"R": "R", "S": "S"}, (("R.a", "S.a"),), tuple(Attribute(n, where[n], k) for n, k in kinds.items()))


def entries(ring, view):
    return {(r["attr_u"], r["attr_v"]): float(r["value"]) for r in ring.entries(view).collect()}


def test_toy_counts(spark):
    s = spec({})
    tree, data = build_view_tree(s), toy.frames(spark)
    ring = CountRing(s)
    leaf = lambda a: {r[0]: r.c for r in leaf_view(tree.leaf(a), tree, ring, data[a]).df.collect()}
    assert leaf("R") == {"a1": 1, "a2": 2, "a3": 1} and leaf("S") == {"a1": 2, "a2": 1, "a4": 1}
    assert evaluate(tree, data, ring).df.first().c == 4


@pytest.mark.parametrize("numeric", ["double", "decimal"])
def test_toy_continuous(spark, numeric):
    s = spec({"b": "cont", "c": "cont", "d": "cont"})
    tree, data = build_view_tree(s), toy.frames(spark, True)
    ring = MomentRing(s, numeric)
    assert ring.width(("b", "c", "d")) == 10
    root = entries(ring, evaluate(tree, data, ring))
    want = {("1", "1"): 4, ("1", "b"): 7, ("1", "c"): 17, ("1", "d"): 90, ("b", "b"): 15, ("b", "c"): 29, ("b", "d"): 180, ("c", "c"): 73, ("c", "d"): 380, ("d", "d"): 2300}
    assert root == want
    view = {r["a"]: r for r in leaf_view(tree.leaf("S"), tree, ring, data["S"]).df.collect()}
    assert (view["a1"]["c"], float(view["a1"]["s_c"]), float(view["a1"]["q_c__d"]), float(view["a1"]["q_d__d"])) == (2, 9, 140, 500)
    assert len(ring.full_matrix(evaluate(tree, data, ring)).collect()) == 16


def test_toy_mixed(spark):
    s = spec({"b": "cont", "c": CAT, "d": "cont"})
    tree, data = build_view_tree(s), toy.frames(spark)
    ring = SparseMomentRing(s, "decimal")
    got = {(r["attr_u"], r["cat_u"], r["attr_v"], r["cat_v"]): float(r["value"]) for r in ring.entries(evaluate(tree, data, ring)).collect()}
    want = {("1", None, "1", None): 4, ("1", None, "b", None): 7, ("1", None, "c", "p"): 3, ("1", None, "c", "q"): 1, ("1", None, "d", None): 90, ("b", None, "b", None): 15, ("b", None, "c", "p"): 6, ("b", None, "c", "q"): 1,
            ("b", None, "d", None): 180, ("c", "p", "c", "p"): 3, ("c", "q", "c", "q"): 1, ("c", "p", "d", None): 70, ("c", "q", "d", None): 20, ("d", None, "d", None): 2300}
    assert got == want


def test_toy_categories(spark):
    s = spec({"b": CAT, "c": CAT, "d": CAT})
    tree, data = build_view_tree(s), toy.frames(spark)
    ring = SparseMomentRing(s)
    got = toy.sparse_payload(evaluate(tree, data, ring).df.collect())
    assert got[(("b", "1"),)] == 2 and got[(("c", "p"), ("d", "30"))] == 2 and got[(("b", "1"), ("c", "p"))] == 1 and got[()] == 4
    assert len(got) == 1 + 3 + 2 + 3 + 4 + 4 + 3


def random_db(seed):
    r = random.Random(seed)
    return [(r.choice("xyz"), r.randint(-3, 4)) for _ in range(12)], [(r.choice("xyw"), r.choice("pqr"), r.randint(0, 5)) for _ in range(14)]


@pytest.mark.parametrize("seed", [1, 2])
@pytest.mark.parametrize("degree", [2, 4])
def test_sparse_equals_polynomials_of_the_flat_join(spark, seed, degree):
    rr, ss = random_db(seed)
    s = spec({"b": "cont", "c": CAT, "d": "cont"})
    data = {"R": spark.createDataFrame(rr, "a string, b int"), "S": spark.createDataFrame(ss, "a string, c string, d int")}
    flat = [({"b": b, "c": c, "d": d}, 1) for a, b in rr for x, c, d in ss if a == x]
    want = toy.poly_join(flat, {"b": "cont", "c": "cat", "d": "cont"}, degree)
    got = toy.sparse_payload(evaluate(build_view_tree(s), data, SparseMomentRing(s, "double", degree)).df.collect())
    assert got == want


def axioms(spark, ring, attrs, views):
    """Sum and product over random views with one shared key: commutative, associative, distributive, inverse."""
    a, b, c = views
    total = lambda v: sorted(tuple(str(x) for x in r) for r in ring.state(v, ("k",)).df.select("k", *ring.payload(v.attrs)).collect())
    add, mul = lambda x, y: ring.total(ring.union([x, y]), ("k",)), lambda x, y: ring.total(ring.product(x, y), ("k",))
    assert total(add(a, b)) == total(add(b, a))
    assert total(add(add(a, b), b)) == total(add(a, add(b, b)))
    assert total(mul(add(a, b), c)) == total(add(mul(a, c), mul(b, c)))
    assert total(add(a, ring.negated(a))) == []


def test_moment_ring_axioms(spark):
    s = QuerySpec({"R": "R", "S": "S"}, (("R.k", "S.k"),), (Attribute("x", "R"), Attribute("y", "R"), Attribute("z", "S")))
    ring = MomentRing(s, "decimal")
    r = random.Random(4)
    rows = lambda n, names: spark.createDataFrame([(r.choice("ab"), *[r.randint(-5, 5) for _ in names], r.choice([1, 2, -1])) for _ in range(n)], f"k string, {', '.join(f'{x} int' for x in names)}, mult long")
    a, b, c = ring.leaf(rows(6, "xy"), ("k",), ("x", "y")), ring.leaf(rows(5, "xy"), ("k",), ("x", "y")), ring.leaf(rows(5, "z"), ("k",), ("z",))
    axioms(spark, ring, (), (a, b, c))
    key = lambda v: {x["k"]: [float(x[p]) for p in ring.payload(v.attrs)] for x in v.df.collect()}
    left, right = key(ring.product(a, c)), key(ring.product(c, a))
    assert left == right
    # the same attribute on both sides: the cross products meet on the diagonal, twice
    one = lambda v: ring.leaf(spark.createDataFrame([("a", v, 0, 1)], "k string, x int, y int, mult long"), ("k",), ("x", "y"))
    p = ring.product(one(3), one(5)).df.first()
    assert (p["c"], float(p["s_x"]), float(p["q_x__x"])) == (1, 8, 9 + 25 + 2 * 15)


def test_sparse_and_listing_axioms(spark):
    s = spec({"b": "cont", "c": CAT, "d": "cont"})
    r = random.Random(5)
    big = lambda n: spark.createDataFrame([(r.choice("ab"), r.randint(-4, 4), r.choice([1, -1, 2])) for _ in range(n)], "k string, b int, mult long")
    other = spark.createDataFrame([(r.choice("ab"), r.choice("pq"), r.randint(1, 4), 1) for _ in range(6)], "k string, c string, d int, mult long")
    for ring in (SparseMomentRing(s, "decimal"), ListingRing(s, ("b", "c"))):
        axioms(spark, ring, (), (ring.leaf(big(6), ("k",), ("b",)), ring.leaf(big(5), ("k",), ("b",)), ring.leaf(other, ("k",), ("c", "d"))))


def test_sum_product_and_composition(spark):
    s = spec({"b": "cont", "d": "cont"})
    tree, data = build_view_tree(s), toy.frames(spark)
    assert float(evaluate(tree, data, SumProductRing(s, {"b": "b", "d": "d"})).df.first().v) == 180
    assert isinstance(compose("moments", "numbers", s), MomentRing) and isinstance(compose("moments", "relations", s), SparseMomentRing)
    with pytest.raises(ValueError):
        compose("moments", "tensors", s)
    with pytest.raises(ValueError):
        MomentRing(spec({"c": CAT}))


def test_delta_with_count_zero_is_kept(spark):
    s = spec({"b": "cont"})
    ring = MomentRing(s, "decimal")
    rows = spark.createDataFrame([("a1", 5, 1), ("a1", 3, -1)], "k string, b int, mult long")
    v = ring.nonzero(ring.leaf(rows, ("k",), ("b",))).df.first()
    assert v["c"] == 0 and float(v["s_b"]) == 2


def test_exact_sums_fail_on_overflow(spark):
    s = QuerySpec({"R": "R"}, (), (Attribute("x", "R"),))
    big = spark.createDataFrame([(10.0**13, 1)], "x double, mult long")
    with pytest.raises(Exception, match="(?i)cannot be represented|overflow"):
        MomentRing(s, "decimal").leaf(big, (), ("x",)).df.collect()


def test_empty_join(spark):
    s = spec({"b": "cont"})
    data = toy.frames(spark)
    empty = {**data, "R": data["R"].limit(0)}
    for ring in (CountRing(s), MomentRing(s), SparseMomentRing(s)):
        assert evaluate(build_view_tree(s), empty, ring).df.count() == 0
    assert View(data["R"], ("a",)).attrs == () and F.lit(1) is not None


@pytest.mark.parametrize("fine", [(), ("a",)])
def test_late_ring_spreads_only_over_all_attributes(spark, fine):
    s = spec({"b": "cont", "c": CAT, "d": "cont"})
    tree, data = build_view_tree(s), toy.frames(spark)
    late, sparse = LateMomentRing(s, fine, "decimal"), SparseMomentRing(s, "decimal")
    got, want = evaluate(tree, data, late), evaluate(tree, data, sparse)
    assert toy.sparse_payload(got.df.collect()) == toy.sparse_payload(want.df.collect())
    for a in "RS":  # below there is no row per term
        leaf = leaf_view(tree.leaf(a), tree, late, data[a])
        assert "term" not in leaf.df.columns and leaf.df.count() <= data[a].count() < leaf_view(tree.leaf(a), tree, sparse, data[a]).df.count()


def test_tree_per_bulk_keeps_no_row_per_term_of_an_order(spark, monkeypatch):
    from deltaring import queries as q

    made = []
    monkeypatch.setattr(q, "ViewStore", lambda *a, **o: made.append(ViewStore(*a, **o)) or made[-1])
    monkeypatch.setattr(q.deptree, "dependency_tree", lambda mi: (_ for _ in ()).throw(KeyError("enough")))
    with pytest.raises(KeyError):
        q.queries()["tree_per_bulk"](spark, "/root/testdata/sf0.001")
    below = made[0].rows(made[0].tree.node("at_o_custkey")).df
    assert below.count() == spark.read.parquet("/root/testdata/sf0.001/orders.parquet").count()
