import dataclasses
import random

import pytest
from pyspark.sql import functions as F

from deltaring import workloads as w
from deltaring.operators import baselines, block, factorised, metrics
from deltaring.operators.delta import as_delta, as_update, consolidate, factor_delta, negative_multiplicities, propagate, propagate_all, propagate_factored, propagate_factored_all, recomputed
from deltaring.operators.rings import CountRing, MomentRing
from deltaring.operators.sparse import SparseMomentRing
from deltaring.plans.spec import CAT, Attribute, QuerySpec, SpecError, load
from deltaring.plans.tree import build_view_tree
from deltaring.sources import feeds
from deltaring.sources.store import ViewStore

from . import toy
from .test_rings import spec

SF = "/root/testdata/sf0.001"


def bulk(spark, rows=toy.BULK):
    return spark.createDataFrame(rows, "a string, b int, mult long")


@pytest.mark.parametrize("kinds,root,after", [
    ({}, {(): 2}, {(): 6}),
    ({"b": "cont", "c": CAT, "d": "cont"}, {(): 2, "b": 13, "cq": 2, "d": 40, "cp d": -20, "cq d": 60}, {(): 6, "b": 20, "cp d": 50, "cq d": 80}),
    ({"b": CAT, "c": CAT, "d": CAT}, {(): 2, "b3": -1, "d30": -1}, {(): 6, "b5": 2, "b6": 1}),
])
def test_toy_bulk(spark, kinds, root, after):
    s = spec(kinds)
    tree, data = build_view_tree(s), toy.frames(spark)
    ring = SparseMomentRing(s, "decimal") if kinds else CountRing(s)
    store = ViewStore(spark, tree, ring).initialise(data)
    change = propagate(store, "R", bulk(spark), "1")[tree.root.name]
    store.commit("1")

    def shown(view):
        if not kinds:
            return {(): view.df.first().c}
        return {"".join(a + (c if kinds[a] == CAT else "") + " " for a, c in t).strip() or (): v for t, v in toy.sparse_payload(view.df.collect()).items()}

    got, state = shown(change), shown(store.state())
    assert all(got[k] == v for k, v in root.items()) and all(state[k] == v for k, v in after.items())
    if kinds:
        assert "cp" not in got  # one row of p came and one went, while its products changed
        if kinds["b"] == CAT:
            assert not any("b3" in str(k) for k in state)


def same(a, b):
    rows = lambda v: sorted(map(str, v.df.collect()))
    return rows(a) == rows(b)


@pytest.mark.parametrize("order", [w.ORDER_FACT, w.ORDER_DIMENSION])
def test_state_equals_recompute_after_each_bulk(spark, order):
    s = w.j1(("l_quantity", "o_totalprice", "c_acctbal"))
    tree, data = build_view_tree(s, order), load(spark, SF, s)
    ring = MomentRing(s, "decimal")
    now = {a: d.withColumn("mult", F.lit(1).cast("long")) for a, d in data.items()}
    initial, bulks = feeds.lineitem_bulks(data["lineitem"], deletes=True)
    now["lineitem"] = initial.withColumn("mult", F.lit(1).cast("long"))
    store = ViewStore(spark, tree, ring).initialise(now)
    moved = data["customer"].where("c_custkey % 5 = 0")
    deltas = [{"lineitem": b} for b in bulks[:2]] + [{"customer": as_update(moved, moved.withColumn("c_nationkey", F.lit(3)).withColumn("c_acctbal", F.col("c_acctbal") + 1)), "lineitem": bulks[2], "nation": as_delta(None, data["nation"].where("n_nationkey = 7"))}]
    for i, d in enumerate(deltas):
        assert propagate_all(store, d, f"{i:02d}")
        for a, x in d.items():
            now[a] = now[a].unionByName(x.select(now[a].columns))
        assert same(store.state(), recomputed(tree, ring, now))
    assert metrics.entries_diff(store.state(), recomputed(tree, ring, now), ring) == (0.0, 0.0)
    assert not propagate_all(store, deltas[0], "00")  # delivered again
    before = store.state().df.collect()
    store.compact()
    assert store.state().df.collect() == before


def test_random_order_splits_and_inverse(spark):
    r = random.Random(8)
    s = spec({"b": "cont", "c": CAT, "d": "cont"})
    tree, data = build_view_tree(s), toy.frames(spark)
    ring = SparseMomentRing(s, "decimal")
    rows = [(r.choice(["a1", "a2", "a4", "a9"]), r.randint(-3, 9), r.choice([1, 1, -1])) for _ in range(12)]
    whole = ViewStore(spark, tree, ring).initialise(data)
    propagate_all(whole, {"R": bulk(spark, rows)}, "1")
    split = ViewStore(spark, tree, ring).initialise(data)
    r.shuffle(rows)
    for i in range(3):
        propagate_all(split, {"R": bulk(spark, rows[i::3])}, str(i))
    assert toy.sparse_payload(whole.state().df.collect()) == toy.sparse_payload(split.state().df.collect())
    propagate_all(split, {"R": bulk(spark, [(a, b, -m) for a, b, m in rows])}, "9")
    fresh = ViewStore(spark, tree, ring).initialise(data)
    assert toy.sparse_payload(split.state().df.collect()) == toy.sparse_payload(fresh.state().df.collect())


def test_delete_everything(spark):
    s = spec({"b": "cont", "d": "cont"})
    tree, data = build_view_tree(s), toy.frames(spark)
    store = ViewStore(spark, tree, MomentRing(s, "decimal")).initialise(data)
    propagate_all(store, {"R": as_delta(None, data["R"]), "S": as_delta(None, data["S"])}, "1")
    assert store.state().df.count() == 0
    assert all(store.state(n).df.count() == 0 for n in store.kept.values())
    assert negative_multiplicities(data["R"].withColumn("mult", F.lit(1)).unionByName(as_delta(None, bulk(spark, [("zz", 1, 1)])))).count() == 1


def test_break_between_views_and_again(spark):
    """A bulk that stops after some views is invisible and is replaced when it comes again."""
    s = spec({"b": "cont", "d": "cont"})
    tree, data = build_view_tree(s), toy.frames(spark)
    ring = MomentRing(s, "decimal")
    store = ViewStore(spark, tree, ring).initialise(data)
    before = store.state().df.collect()
    propagate(store, "R", bulk(spark), "1")  # no commit
    again = ViewStore(spark, tree, ring, path=store.path)
    assert again.state().df.collect() == before
    other = [{"R": bulk(spark), "S": as_delta(None, data["S"].where("d = 10"))}]
    assert propagate_all(again, other[0], "1")
    clean = ViewStore(spark, tree, ring).initialise(data)
    propagate_all(clean, other[0], "1")
    assert again.state().df.collect() == clean.state().df.collect() and again.committed() == ["1"]


def test_states_by_batch(spark):
    s = spec({"b": "cont"})
    tree, data = build_view_tree(s), toy.frames(spark)
    store = ViewStore(spark, tree, MomentRing(s, "decimal")).initialise(data)
    for i in (1, 2):
        propagate_all(store, {"R": bulk(spark, [("a1", 10 * i, 1)])}, str(i))
    assert [store.state(until=b).df.first().c for b in (0, "1", "2")] == [4, 6, 8]
    store.compact()
    with pytest.raises(ValueError):
        store.state(until="1")


@pytest.mark.parametrize("names", [["batch-8", "batch-9", "batch-10", "batch-11"], ["3", "2", "1", "0"], ["z", "a.b", "a", "Z-1"]])
def test_bulks_count_whatever_their_names(spark, names):
    """Order is that of commits: unpadded and late names before and after compaction."""
    s = spec({"b": "cont"})
    tree, data = build_view_tree(s), toy.frames(spark)
    ring = MomentRing(s, "decimal")
    store = ViewStore(spark, tree, ring).initialise(data)
    for i, name in enumerate(names):
        assert propagate_all(store, {"R": bulk(spark, [("a1", 1, 1)])}, name)
        assert not propagate_all(store, {"R": bulk(spark, [("a1", 1, 1)])}, name)
        assert store.state().df.first().c == 4 + 2 * (i + 1)
        if i % 2:
            store.compact()
            assert store.state().df.first().c == 4 + 2 * (i + 1)
        again = ViewStore(spark, tree, ring, path=store.path)
        assert again.committed() == names[: i + 1] and again.state().df.first().c == 4 + 2 * (i + 1)
    with pytest.raises(ValueError):
        store.begin("../x")
    with pytest.raises(ValueError):
        store.state(until="never")


def test_second_writer_fails(spark):
    s = spec({"b": "cont"})
    tree, data = build_view_tree(s), toy.frames(spark)
    ring = MomentRing(s, "decimal")
    one = ViewStore(spark, tree, ring).initialise(data)
    two = ViewStore(spark, tree, ring, path=one.path)
    assert two.begin("b")
    propagate(two, "R", bulk(spark, [("a1", 1, 1)]), "b")
    assert propagate_all(one, {"R": bulk(spark, [("a1", 1, 1)])}, "a")
    with pytest.raises(RuntimeError, match="another writer"):
        two.commit("b")
    assert ViewStore(spark, tree, ring, path=one.path).state().df.first().c == 6
    assert propagate_all(two, {"R": bulk(spark, [("a1", 1, 1)])}, "b") and two.state().df.first().c == 8


def test_a_retry_with_other_tables_leaves_nothing_behind(spark):
    s = spec({"b": "cont", "d": "cont"})
    tree, data = build_view_tree(s), toy.frames(spark)
    store = ViewStore(spark, tree, MomentRing(s, "decimal")).initialise(data)
    store.begin("1")
    propagate(store, "R", bulk(spark), "1")
    propagate(store, "S", as_delta(None, data["S"]), "1")  # broke off here
    assert propagate_all(store, {"R": bulk(spark, [("a1", 1, 1)])}, "1")
    assert store.state().df.first().c == 6


def test_block_ring_equals_columns(spark):
    """Wide payloads: initial load, bulks with deletes, dimensions, compaction and zero states."""
    s = w.j1(("l_quantity", "l_linenumber", "o_totalprice"))
    s = dataclasses.replace(s, attributes=(*s.attributes, w.attribute("c_place", expr="c_nationkey + 1"), w.attribute("r_place", expr="r_regionkey")))
    with pytest.raises(SpecError):
        w.j1(("c_nationkey",)).validate(load(spark, SF, s))
    data = load(spark, SF, s)
    initial, bulks = feeds.lineitem_bulks(data["lineitem"], deletes=True)
    gone = as_delta(None, data["nation"].where("n_nationkey = 7"))
    key = lambda ring, v: {(r.attr_u, r.attr_v): float(r.value) for r in ring.entries(v).collect()}
    for order in (w.ORDER_FACT, w.ORDER_DIMENSION):
        tree = build_view_tree(s, order)
        want, got = MomentRing(s), block.BlockRing(s)
        a, b = (ViewStore(spark, tree, r).initialise({**data, "lineitem": initial}) for r in (want, got))
        for i, x in enumerate([{"lineitem": bulks[0]}, {"nation": gone, "lineitem": bulks[1]}]):
            for st in (a, b):
                propagate_all(st, x, f"{i}")
            x, y = key(want, a.state()), key(got, b.state())
            assert x.keys() == y.keys() and all(abs(x[k] - y[k]) <= 1e-9 * max(1.0, abs(x[k])) for k in x)
        b.compact()
        assert key(got, b.state()) == pytest.approx(y, rel=1e-12)
    grouped = QuerySpec(s.tables, s.joins, s.attributes, free=(w.attribute("r_name", CAT),))
    tree = build_view_tree(grouped, w.ORDER_FACT)
    x, y = ({(e.r_name, e.attr_u, e.attr_v): float(e.value) for e in ring.entries(recomputed(tree, ring, data)).collect()} for ring in (MomentRing(grouped), block.BlockRing(grouped)))
    assert x.keys() == y.keys() and all(abs(x[k] - y[k]) <= 1e-9 * max(1.0, abs(x[k])) for k in x)
    v = got.leaf(s.rows("nation", data["nation"]), ("c_nationkey", "n_regionkey"), ())
    assert got.nonzero(got.total(got.union([v, got.negated(v)]), ("n_regionkey",))).df.count() == 0
    with pytest.raises(Exception, match="null, NaN"):
        nan = spark.createDataFrame([("a", float("nan"))], "k string, x double")
        ring = block.BlockRing(QuerySpec({"t": "t"}, (), (Attribute("x", "t"),)))
        ring.leaf(ring.spec.rows("t", nan), (), ("x",)).df.collect()


def test_factors_are_integers(spark):
    grid = lambda xs, ys, c=1: spark.createDataFrame([(i, j, c * m * n) for i, m in xs for j, n in ys], "i int, j string, mult long")
    for xs, ys, c in (([(1, 2), (2, 4)], [("a", 3), (None, -6)], 1), ([(None, 1), (2, -1)], [("a", 1), ("b", 5)], 7), ([(1, 10**9), (2, 3)], [("a", 10**9), ("b", -(10**9))], 1)):
        whole = grid(xs, ys, c)
        factors = factor_delta(whole, [["i"], ["j"]])
        assert all(dict(f.dtypes)["mult"] == "bigint" for f in factors)
        a, b = (f.collect() for f in factors)
        assert {(x.i, y.j): x.mult * y.mult for x in a for y in b} == {(r.i, r.j): r.mult for r in whole.collect()}
    assert factor_delta(grid([(1, 1)], [("a", 1)]).limit(0), [["i"], ["j"]]) is None
    three = spark.createDataFrame([(i, j, k, -6 * i * j) for i in (1, 2) for j in (1, 5) for k in (0, 1)], "i int, j int, k int, mult long")
    assert [f.count() for f in factor_delta(three, [["i"], ["j"], ["k"]])] == [2, 2, 2]


def test_factored_bulk_equals_the_bulk(spark):
    """A product pushed up as its factors, over both orders of variables and several rings."""
    s = QuerySpec({"R": "R", "S": "S", "T": "T"}, (("R.a", "S.a"), ("R.b", "T.b")), (Attribute("x", "R"), Attribute("c", "S", CAT), Attribute("d", "S"), Attribute("e", "T")))
    frames = {"R": spark.createDataFrame([(1, 1, 2), (2, 1, 3)], "a int, b int, x int"), "S": spark.createDataFrame([(1, "p", 4), (2, "q", 5), (2, "p", 6)], "a int, c string, d int"), "T": spark.createDataFrame([(1, 7), (2, 8)], "b int, e int")}
    f1 = spark.createDataFrame([(1, 2), (2, -1)], "a int, mult long")
    f2 = spark.createDataFrame([(1, 9, 1), (2, 5, 3)], "b int, x int, mult long")
    whole = f1.withColumnRenamed("mult", "m").crossJoin(f2).withColumn("mult", F.col("m") * F.col("mult")).select("a", "b", "x", "mult")
    for order in (("a", "b"), ("b", "a")):
        tree = build_view_tree(s, order)
        ring = SparseMomentRing(s, "decimal")
        one, two = (ViewStore(spark, tree, ring).initialise(frames) for _ in range(2))
        assert propagate_all(one, {"R": whole}, "1") and propagate_factored_all(two, {"R": [f1, f2]}, "1")
        assert not propagate_factored_all(two, {"R": [f1, f2]}, "1")
        for name, node in one.kept.items():
            a, b = (sorted(map(str, x.state(node).df.select(sorted(one.state(node).df.columns)).collect())) for x in (one, two))
            assert a == b, name
    with pytest.raises(SpecError):
        propagate_factored(two, "R", [f1, f2.drop("x")], "2")


def test_factorised_views_keep_no_dangling_tuple(spark):
    """A chain whose tables are named out of order, and a cycle."""
    s = QuerySpec({"B": "B", "A": "A", "C": "C"}, (("A.x", "B.x"), ("B.y", "C.y")), ())
    frames = {"A": spark.createDataFrame([(1,), (2,)], "x int"), "B": spark.createDataFrame([(1, 1), (2, 2), (3, 1)], "x int, y int"), "C": spark.createDataFrame([(1,)], "y int")}
    for order in (("x", "y"), ("y", "x")):
        v = factorised.factorised_views(build_view_tree(s, order), frames, ())
        assert {a: sorted(tuple(r[c] for c in r.__fields__ if c != "mult") for r in d.collect()) for a, d in v.items()} == {"A": [(1,)], "B": [(1, 1)], "C": [(1,)]}
        assert factorised.factorised_size(v) == 3
    tri = QuerySpec({"R": "R", "S": "S", "T": "T"}, (("R.a", "S.a"), ("S.b", "T.b"), ("R.c", "T.c")), ())
    t = {"R": spark.createDataFrame([(1, 1), (1, 2)], "a int, c int"), "S": spark.createDataFrame([(1, 1), (1, 2)], "a int, b int"), "T": spark.createDataFrame([(1, 1), (2, 3)], "b int, c int")}
    v = factorised.factorised_views(build_view_tree(tri), t, ())
    assert [v[a].count() for a in "RST"] == [1, 1, 1]


def test_views_that_were_not_declared(spark):
    s = w.j1(("l_quantity",))
    tree, data = build_view_tree(s, w.ORDER_FACT), load(spark, SF, s)
    store = ViewStore(spark, tree, MomentRing(s), updatable=("lineitem",)).initialise(data)
    with pytest.raises(ValueError):
        propagate(store, "customer", as_delta(data["customer"].limit(1)), "1")


def test_consolidate_and_factor(spark):
    d = spark.createDataFrame([(1, "x", 1), (1, "x", -1), (2, "y", 1), (2, "y", 1)], "k int, g string, mult long")
    assert [tuple(r) for r in consolidate(d).collect()] == [(2, "y", 2)]
    grid = spark.createDataFrame([(i, j, i * j) for i in (1, 2) for j in (1, 3)], "i int, j int, mult long")
    a, b = factor_delta(grid, [["i"], ["j"]])
    back = {(x.i, y.j): x.mult * y.mult for x in a.collect() for y in b.collect()}
    assert back == {(i, j): i * j for i in (1, 2) for j in (1, 3)}
    assert factor_delta(grid.where("not (i = 2 and j = 3)"), [["i"], ["j"]]) is None
    assert factor_delta(grid.withColumn("mult", F.when((F.col("i") == 2) & (F.col("j") == 3), 5).otherwise(F.col("mult")).cast("long")), [["i"], ["j"]]) is None


def test_baselines_agree(spark):
    s = w.j1(("l_quantity", "o_totalprice"))
    tree, data = build_view_tree(s, w.ORDER_FACT), load(spark, SF, s)
    ring = MomentRing(s, "decimal")
    initial, bulks = feeds.lineitem_bulks(data["lineitem"], deletes=True)
    base = {**data, "lineitem": initial}
    store = ViewStore(spark, tree, ring, updatable=("lineitem",)).initialise(base)
    joined = baselines.JoinMaintainer(s, base)
    first = [baselines.recompute(s, base, ring)]
    mult = {a: d.withColumn("mult", F.lit(1).cast("long")) for a, d in base.items()}
    for i, b in enumerate(bulks):
        propagate_all(store, {"lineitem": b}, f"{i}")
        joined.apply("lineitem", b)
        first.append(baselines.first_order_delta(s, mult, "lineitem", b, ring))
    want = store.state()
    assert same(want, ring.state(joined.moments(ring), ())) and same(want, ring.state(ring.union(first), ()))
    per = {(r.attr_u, r.attr_v): r.value for r in baselines.per_aggregate(s, tree, data).collect()}
    assert per == {(r.attr_u, r.attr_v): r.value for r in ring.entries(recomputed(tree, ring, data)).collect()}
    sizes = {r.view: r.rows for r in metrics.view_sizes(store).collect()}
    assert sizes["at_l_orderkey"] == 1
    rows, flat, _ = metrics.repetition(tree, data)
    assert flat == data["lineitem"].count() and rows > flat


def test_one_hot_and_set_semantics(spark):
    s = spec({"b": "cont", "c": CAT})
    e = {(r.attr_u, r.attr_v): float(r.value) for r in baselines.one_hot_moments(s, toy.frames(spark)).collect()}
    assert e["1", "c=p"] == 3 and e["c=p", "c=q"] == 0 and e.get(("b", "c=p"), e.get(("c=p", "b"))) == 6
    base = spark.createDataFrame([(1,), (1,), (2,)], "k int")
    out = baselines.apply_with_anti_join(base, spark.createDataFrame([(3,)], "k int"), spark.createDataFrame([(1,)], "k int"), ["k"])
    assert sorted(r.k for r in out.collect()) == [2, 3]  # both copies went: sets, not multiplicities


def test_online_learner_ignores_deletes(spark):
    rows = [(float(x % 7), 2.0 * (x % 7) + 1) for x in range(200)]
    df = spark.createDataFrame(rows, "x double, y double").withColumn("mult", F.lit(1))
    gone = df.withColumn("mult", F.lit(-1))
    a = baselines.online_sgd([df] * 40, ["x"], "y", 0.05)
    b = baselines.online_sgd([df.unionByName(gone)] * 40, ["x"], "y", 0.05)
    assert a == b and abs(a["x"] - 2) < 0.5


def test_free_variables_and_self_join(spark):
    s = QuerySpec({"x": "S", "y": "S"}, (("x.a", "y.a"),), (Attribute("d1", "x", expr="d"), Attribute("d2", "y", expr="d")), free=(Attribute("kind", "x", CAT, "c"),))
    data = {"x": toy.frames(spark)["S"], "y": toy.frames(spark)["S"]}
    tree = build_view_tree(s)
    ring = MomentRing(s, "decimal")
    store = ViewStore(spark, tree, ring).initialise(data)
    new = spark.createDataFrame([("a1", "p", 5, 1)], "a string, c string, d int, mult long")
    propagate_all(store, {"x": new, "y": new}, "1")
    now = {a: d.withColumn("mult", F.lit(1).cast("long")).unionByName(new) for a, d in data.items()}
    key = lambda v: sorted(map(str, v.df.select(*sorted(v.df.columns)).collect()))
    assert key(store.state()) == key(recomputed(tree, ring, now))
