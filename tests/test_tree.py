import os

import pytest

from deltaring import workloads as w
from deltaring.operators.evaluate import evaluate
from deltaring.operators.rings import CountRing, MomentRing
from deltaring.plans import explain
from deltaring.plans.spec import CAT, Attribute, QuerySpec, SpecError, load
from deltaring.plans.tree import build_view_tree, rows_met

SF = "/root/testdata/sf0.001"
#: Queries that once made up their data, or read none.
READS = ["strategy_delta_orders", "strategy_j1", "toy_count", "toy_mi", "toy_mixed", "toy_moments"]


def test_orders_of_the_five_relation_join():
    t = build_view_tree(w.j1(("l_quantity", "c_acctbal")), w.ORDER_FACT)
    keys = {n.name: n.keys for n in t.nodes()}
    assert keys["at_l_orderkey"] == () and keys["at_o_custkey"] == ("l_orderkey",) and keys["leaf_customer"] == ("o_custkey", "c_nationkey")
    assert [n.name for n in t.path("lineitem")] == ["leaf_lineitem", "at_l_orderkey"]
    assert {n.name for n in t.materialised(("lineitem",))} == {"at_o_custkey", "at_l_orderkey"}
    other = build_view_tree(w.j1(("l_quantity",)), w.ORDER_DIMENSION)
    assert len(other.path("lineitem")) == 5 and other.root.summed == "n_regionkey"
    assert build_view_tree(w.j1()).path("lineitem")[-1].summed == "l_orderkey"


def test_cyclic_join_has_keys_of_two_variables():
    spec = QuerySpec({t: t for t in ("lineitem", "orders", "customer", "supplier")}, (("lineitem.l_orderkey", "orders.o_orderkey"), ("orders.o_custkey", "customer.c_custkey"), ("lineitem.l_suppkey", "supplier.s_suppkey"), ("customer.c_nationkey", "supplier.s_nationkey")))
    t = build_view_tree(spec)
    assert max(len(n.keys) for n in t.nodes()) == 2


def test_cyclic_join_by_sizes_never_pairs_all_of_a_nation(spark):
    spec = QuerySpec({t: t for t in ("lineitem", "orders", "customer", "supplier")}, (("lineitem.l_orderkey", "orders.o_orderkey"), ("orders.o_custkey", "customer.c_custkey"), ("lineitem.l_suppkey", "supplier.s_suppkey"), ("customer.c_nationkey", "supplier.s_nationkey")))
    sizes = {t: (n * 1e4, {v: d * (1 if v == "c_nationkey" else 1e4) for v, d in k.items()}) for t, (n, k) in w.sizes_of(spec, load(spark, SF, spec)).items()}
    assert rows_met(build_view_tree(spec).root, sizes)[0] > 100 * sizes["lineitem"][0]
    for s in (sizes, w.sizes_of(spec, load(spark, SF, spec))):
        t = build_view_tree(spec, sizes=s)
        assert rows_met(t.root, s)[0] <= 4 * s["lineitem"][0]
        assert max(len(n.keys) for n in t.nodes()) == 2


def test_bad_specs(spark):
    data = load(spark, SF, w.j1())
    ok = w.j1(("l_quantity",))
    assert ok.validate(data) is ok
    for spec in (
        w.j1(("l_nothing",)),
        QuerySpec(w.J1_TABLES, (("lineitem.l_orderkey", "orders.nothing"),)),
        QuerySpec(w.J1_TABLES, (("lineitem.l_shipdate", "orders.o_orderkey"),)),
        QuerySpec(w.J1_TABLES, w.J1_JOINS, (Attribute("x", "region", "cont", "r_name"),)),
        QuerySpec(w.J1_TABLES, w.J1_JOINS, (Attribute("x", "region", CAT, "r_name"), Attribute("x", "nation", CAT, "n_name"))),
        w.j1(("l_quantity",), label="nothing"),
        w.j1(free=(Attribute("c", "region", CAT, "r_name"),)),
    ):
        with pytest.raises(SpecError):
            spec.validate(data)
    with pytest.raises(SpecError):
        build_view_tree(QuerySpec({"a": "region", "b": "nation", "c": "orders"}, (("a.r_regionkey", "b.n_regionkey"), ("c.o_custkey", "c.o_orderkey"))))
    with pytest.raises(SpecError):
        build_view_tree(w.j1(), ("l_orderkey",))
    with pytest.raises(ValueError):
        Attribute("x", "t", "other")


def test_null_policies(spark):
    t = spark.createDataFrame([(1.0, "a"), (None, "b"), (3.0, None)], "x double, g string")
    attrs = (Attribute("x", "t"), Attribute("g", "t", CAT))
    rows = lambda **o: QuerySpec({"t": "t"}, (), attrs, **o).rows("t", t).collect()
    with pytest.raises(Exception, match="null in continuous attribute x"):
        rows()
    assert len(rows(null_numeric="drop")) == 2 and [r.x for r in rows(null_numeric=0.0)] == [1.0, 0.0, 3.0]
    assert len(rows(null_numeric=0.0, null_category="drop")) == 2
    assert len(QuerySpec({"t": "t"}, (), attrs, where={"t": "x > 2"}, null_numeric="drop").rows("t", t).collect()) == 1


def test_plans(spark):
    """Pushed filters, pruned columns, partial aggregates below the joins, no Python, no product of tables."""
    spec = w.j1(("l_quantity", "o_totalprice"), where={"lineitem": "l_quantity > 10"})
    tree, data = build_view_tree(spec, w.ORDER_FACT), load(spark, SF, spec)
    plan = evaluate(tree, data, MomentRing(spec)).df._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    assert "GreaterThan(l_quantity,10" in plan and "PushedFilters" in plan
    line = plan[plan.index("l_quantity") :]
    assert "l_extendedprice" not in line and "Cartesian" not in plan and "NestedLoop" not in plan and "Python" not in plan
    assert plan.count("HashAggregate") >= 2 * len(tree.nodes())


def test_emitted_sql_equals_the_plan(spark):
    spec = w.j1(("l_quantity", "o_totalprice"))
    tree, data = build_view_tree(spec, w.ORDER_FACT), load(spark, SF, spec)
    a = explain.run_sql(spark, tree, data).first()
    b = evaluate(tree, data, MomentRing(spec)).df.first()
    for c in MomentRing(spec).payload(("l_quantity", "o_totalprice")):
        assert abs(float(a[c]) - float(b[c])) <= 1e-9 * abs(float(b[c]))
    rows = explain.explain_tree(spark, tree, ("lineitem",)).collect()
    assert [r.view for r in rows if r.kept] == ["at_o_custkey", "at_l_orderkey"]
    steps = explain.explain_delta(spark, tree, "orders").collect()
    assert [s.view for s in steps] == ["leaf_orders", "at_o_custkey", "at_l_orderkey"] and "d_orders" in steps[0].sql and "d_at_o_custkey" in steps[2].sql


def test_cell_ranks(spark):
    from deltaring.operators.sparse import SparseMomentRing

    spec = QuerySpec({"o": "orders"}, (), (Attribute("o_totalprice", "o"), Attribute("o_orderstatus", "o", CAT), Attribute("o_orderpriority", "o", CAT)))
    ring = SparseMomentRing(spec)
    rows = spec.rows("o", spark.read.parquet(f"{SF}/orders.parquet"))
    cells = {(r.attr_u, r.attr_v): r for r in explain.moment_cells(spec, ring.entries(ring.leaf(rows, (), ("o_orderpriority", "o_orderstatus", "o_totalprice")))).collect()}
    assert cells["o_totalprice", "o_totalprice"].rank == 0 and cells["o_orderstatus", "o_totalprice"].rank == 1 and cells["o_orderpriority", "o_orderstatus"].rank == 2
    assert cells["1", "1"].rank == 0 and cells["o_orderstatus", "o_orderstatus"].n_entries == 3


def test_count_of_cyclic_join(spark):
    spec = QuerySpec({t: t for t in ("lineitem", "orders", "customer", "supplier")}, (("lineitem.l_orderkey", "orders.o_orderkey"), ("orders.o_custkey", "customer.c_custkey"), ("lineitem.l_suppkey", "supplier.s_suppkey"), ("customer.c_nationkey", "supplier.s_nationkey")))
    data = load(spark, SF, spec)
    o, c, li, s = (data[t] for t in ("orders", "customer", "lineitem", "supplier"))
    flat = li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(s, (li.l_suppkey == s.s_suppkey) & (s.s_nationkey == c.c_nationkey))
    assert evaluate(build_view_tree(spec), data, CountRing(spec)).df.first().c == flat.count()


@pytest.fixture(scope="module")
def fewer(spark, tmp_path_factory):
    """The tables with half of the orders."""
    where = tmp_path_factory.mktemp("fewer")
    for n in os.listdir(SF):
        if n != "orders.parquet":
            os.symlink(f"{SF}/{n}", where / n)
    spark.read.parquet(f"{SF}/orders.parquet").where("o_orderkey % 4 < 2").write.parquet(str(where / "orders.parquet"))
    return str(where)


@pytest.mark.parametrize("name", READS)
def test_query_follows_the_given_tables(spark, fewer, name):
    from deltaring import queries as q

    rows = lambda at: sorted(q.queries()[name](spark, at).collect(), key=repr)
    assert rows(SF) != rows(fewer)
