import itertools
import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from deltaring.functions.binning import bin_edges, bin_quantile, bin_width, quantile_edges
from deltaring.operators import block, deptree, information, learners, matrix, ridge, selection
from deltaring.operators.evaluate import evaluate
from deltaring.operators.rings import MomentRing
from deltaring.operators.sparse import SparseMomentRing
from deltaring.plans.spec import CAT, Attribute, QuerySpec
from deltaring.plans.tree import build_view_tree

from . import toy
from .test_rings import spec


def flat_spec(kinds):
    return QuerySpec({"t": "t"}, (), tuple(Attribute(n, "t", k) for n, k in kinds.items()))


def root(ring, s, df):
    return ring.leaf(s.rows("t", df), (), tuple(sorted(a.name for a in s.attributes)))


def test_toy_information_and_tree(spark):
    s = spec({"b": CAT, "c": CAT, "d": CAT})
    v = evaluate(build_view_tree(s), toy.frames(spark), SparseMomentRing(s))
    mi = {(r.attr_u, r.attr_v): r.mi for r in information.mutual_information(v).collect()}
    assert mi["b", "c"] == pytest.approx(0.215762, abs=1e-6) and mi["b", "d"] == pytest.approx(math.log(2)) and mi["c", "d"] == pytest.approx(0.562335, abs=1e-6)
    assert mi["c", "c"] == pytest.approx(-(0.75 * math.log(0.75) + 0.25 * math.log(0.25)))
    two = {(r.attr_u, r.attr_v): r.mi for r in information.mutual_information(v, 2).collect()}
    assert two["b", "d"] == pytest.approx(mi["b", "d"] / math.log(2))
    frame = information.mutual_information(v)
    tree = [(r.parent, r.child) for r in deptree.dependency_tree(frame, "d").orderBy("step").collect()]
    assert tree == [("d", "b"), ("d", "c")]
    assert deptree.tree_weight(deptree.dependency_tree(frame)).first().weight == pytest.approx(1.255482, abs=1e-6)


def chain(spark, n=4000):
    r, rows = random.Random(3), []
    for _ in range(n):
        a = r.randint(0, 3)
        b = a if r.random() < 0.9 else r.randint(0, 3)
        c = b if r.random() < 0.8 else r.randint(0, 3)
        rows.append((a, b, c, c if r.random() < 0.7 else r.randint(0, 3), r.randint(0, 3)))
    return spark.createDataFrame(rows, "c1 int, c2 int, c3 int, c4 int, noise int")


def test_planted_chain_selection_and_changes(spark):
    s = flat_spec({c: CAT for c in ("c1", "c2", "c3", "c4", "noise")})
    v = root(SparseMomentRing(s), s, chain(spark))
    mi = information.mutual_information(v)
    t = deptree.dependency_tree(mi, "c1")
    assert {tuple(sorted((r.parent, r.child))) for r in t.collect()} > {("c1", "c2"), ("c2", "c3"), ("c3", "c4")}
    far = deptree.spanning_tree_distributed(mi)
    assert {(r.u, r.v) for r in far.collect()} == {tuple(sorted((r.parent, r.child))) for r in t.collect()}
    sel = selection.select_features(mi, "c1", 0.1)
    assert [r.attr for r in sel.where("selected").orderBy("rank").collect()] == ["c2", "c3", "c4"] and sel.count() == 4
    exact = sel.where("attr = 'c2'").first().mi
    assert not selection.select_features(mi, "c1", exact).where("attr = 'c2'").first().selected  # strictly above
    ch = selection.selection_changes(selection.select_features(mi, "c1", 5.0), sel).collect()
    assert {r.attr for r in ch if r.change == "entered"} == {"c2", "c3", "c4"}
    ll = deptree.log_likelihood(v, t, "c1").first().log_likelihood
    h = {r.attr_u: r.mi for r in mi.where("attr_u = attr_v").collect()}
    assert ll == pytest.approx(-4000 * (sum(h.values()) - deptree.tree_weight(t).first().weight))
    assert deptree.tree_changes(t, deptree.dependency_tree(mi, "c4")).count() == 0


@pytest.mark.parametrize("seed", range(5))
def test_spanning_tree_is_best(seed):
    r = random.Random(seed)
    names = "abcdef"[: 4 + seed % 3]
    edges = [(u, v, round(r.random(), 3)) for u, v in itertools.combinations(names, 2)]
    best = 0.0
    for some in itertools.combinations(edges, len(names) - 1):
        if len(deptree.spanning_edges(list(some))) == len(names) - 1:
            best = max(best, sum(w for *_, w in some))
    got = deptree.spanning_edges(edges)
    assert sum(w for *_, w in got) == pytest.approx(best) and deptree.spanning_edges(edges[::-1]) == got


def test_information_identities(spark):
    df = spark.read.parquet("/root/testdata/sf0.001/part.parquet")
    s = flat_spec({"p_brand": CAT, "p_type": CAT, "p_size": CAT, "p_name": CAT})
    mi = {(r.attr_u, r.attr_v): r.mi for r in information.mutual_information(root(SparseMomentRing(s), s, df)).collect()}
    for (u, v), x in mi.items():
        assert -1e-12 <= x <= min(mi[u, u], mi[v, v]) + 1e-12
        if u != v:
            assert x == pytest.approx(information.mutual_information_direct(df, u, v).first().mi)
        else:
            assert x == pytest.approx(information.entropy(df, u).first().entropy)
    norm = information.normalised(information.mutual_information(root(SparseMomentRing(s), s, df))).collect()
    assert all(0 <= r.normalised <= 1 + 1e-12 for r in norm)


def test_null_is_a_category(spark):
    df = spark.createDataFrame([("x", None), ("x", "u"), (None, "u"), (None, None)] * 3, "a string, b string")
    s = flat_spec({"a": CAT, "b": CAT})
    mi = {(r.attr_u, r.attr_v): r.mi for r in information.mutual_information(root(SparseMomentRing(s), s, df)).collect()}
    assert mi["a", "a"] == pytest.approx(math.log(2)) and abs(mi["a", "b"]) < 1e-12


def planted(spark, n=600):
    r, rows = random.Random(5), []
    for _ in range(n):
        x1, x2, c = r.randint(0, 40), r.randint(-20, 20), r.choice("uvw")
        rows.append((x1, x2, c, 2 + 3 * x1 - 1.5 * x2 + {"u": 0, "v": 4, "w": -2}[c]))
    return spark.createDataFrame(rows, "x1 int, x2 int, c string, y double")


def test_ridge_recovers_and_resumes(spark):
    df = planted(spark)
    s = flat_spec({"x1": "cont", "x2": "cont", "c": CAT, "y": "cont"})
    ring = SparseMomentRing(s)
    m = ridge.collected(ring, root(ring, s, df), ["x1", "x2", "c"], "y")
    model = ridge.ridge_fit(m, "y", 1e-9, tol=1e-12)
    closed = ridge.ridge_closed_form(m, "y", 1e-9)
    assert model.theta["x1", None] == pytest.approx(3, abs=1e-4) and model.theta["x2", None] == pytest.approx(-1.5, abs=1e-4)
    assert model.theta["c", "v"] - model.theta["c", "u"] == pytest.approx(4, abs=1e-3)
    assert all(model.theta[k] == pytest.approx(closed.theta[k], abs=1e-3) for k in closed.theta)
    assert model.gradient_norm <= 1e-12 and ridge.rmse_from_moments(m, model)[1] == pytest.approx(1)
    scored = ridge.predict(model, df).agg(F.max(F.abs(F.col("prediction") - F.col("y")))).first()[0]
    assert scored < 1e-3
    later = ridge.collected(ring, root(ring, s, df.limit(590)), ["x1", "x2", "c"], "y")
    warm, cold = ridge.ridge_resume(model, later, tol=1e-12), ridge.ridge_fit(later, "y", 1e-9, tol=1e-12)
    assert warm.iterations <= cold.iterations and warm.loss == pytest.approx(cold.loss, abs=1e-9)
    no_w = ridge.collected(ring, root(ring, s, df.where("c <> 'w'")), ["x1", "x2", "c"], "y")
    assert ("c", "w") not in ridge.ridge_resume(model, no_w).theta
    strong = ridge.ridge_fit(m, "y", 1.0)
    assert all(strong.theta[k] == pytest.approx(v, abs=1e-6) for k, v in ridge.ridge_closed_form(m, "y", 1.0).theta.items())
    unknown = ridge.predict(model, df.limit(1).withColumn("c", F.lit("new"))).first().prediction
    assert math.isfinite(unknown)


def test_distributed_descent(spark):
    df = planted(spark)
    s = flat_spec({"x1": "cont", "x2": "cont", "y": "cont"})
    ring = MomentRing(s)
    m = ridge.collected(ring, root(ring, s, df), ["x1", "x2"], "y")
    z, _, _ = ridge.standardise(m, "y")
    rows = [(a[0], a[1], b[0], b[1], float(z.matrix[i, j])) for i, a in enumerate(z.names) for j, b in enumerate(z.names)]
    e = spark.createDataFrame(rows, "attr_u string, cat_u string, attr_v string, cat_v string, value double")
    got = {r.attr: r.theta for r in ridge.ridge_fit_distributed(e, "y", 0.1, 15, 0.8).collect()}
    want = ridge.ridge_closed_form(m, "y", 0.1).scaled
    assert all(got[a] == pytest.approx(t, abs=1e-3) for (a, _), t in want.items())


def test_block_layout(spark):
    r = np.random.default_rng(2)
    x = r.normal(size=(300, 20))
    df = spark.createDataFrame([(i % 3, [float(v) for v in row], 1.0 if i % 7 else -1.0) for i, row in enumerate(x)], "k int, e array<double>, m double")
    full = np.concatenate([np.ones((300, 1)), x], axis=1)
    got = {(r.i, r.j): r.v for r in block.gram_block(df, "e").collect()}
    assert len(got) == 231 and all(v == pytest.approx((full.T @ full)[i, j]) for (i, j), v in got.items())
    w = np.array([1.0 if i % 7 else -1.0 for i in range(300)])
    got = {(r.k, r.i, r.j): r.v for r in block.gram_block(df, "e", ["k"], "m").collect()}
    assert got[1, 2, 3] == pytest.approx(sum(w[i] * full[i, 2] * full[i, 3] for i in range(1, 300, 3)))
    with pytest.raises(Exception, match="NaN|null"):
        block.gram_block(spark.createDataFrame([(1.0, float("nan"))], "a double, b double"), ["a", "b"]).collect()
    assert [block.layout_for(QuerySpec({'t': 't'}, (), tuple(Attribute(f'a{i}', 't', k) for i in range(n)))) for n, k in ((5, 'cont'), (64, 'cont'), (3, CAT))] == ['columns', 'block', 'sparse']


def test_bins(spark):
    df = spark.createDataFrame([(-1.0,), (0.0,), (19.9,), (20.0,), (999.0,), (None,)], "x double")
    assert [r[0] for r in df.select(bin_width("x", 0, 20, 25)).collect()] == [-1, 0, 0, 1, 25, None]
    assert [r[0] for r in df.select(bin_edges("x", [0, 20])).collect()] == [0, 1, 1, 2, 2, None]
    many = spark.range(1000).select(F.col("id").cast("double").alias("x"))
    assert len(quantile_edges(many, "x", 4)) == 3
    assert {r["count"] for r in many.groupBy(bin_quantile(many, "x", 4).alias("b")).count().collect()} <= {249, 250, 251, 252}


def test_matrices(spark):
    r = np.random.default_rng(0)
    a, b, c = r.integers(0, 3, (4, 5)), r.integers(0, 3, (5, 3)), r.integers(0, 3, (3, 2))
    frame = lambda m: spark.createDataFrame([(int(i), int(j), int(m[i, j])) for i, j in zip(*np.nonzero(m))], "i int, j int, v long")
    dense = lambda df, shape: np.array([[{(x.i, x.j): x.v for x in df.collect()}.get((i, j), 0) for j in range(shape[1])] for i in range(shape[0])])
    chain_ = [frame(m) for m in (a, b, c)]
    assert (dense(matrix.matrix_chain(chain_, [4, 5, 3, 2]), (4, 2)) == a @ b @ c).all() and (dense(matrix.matrix_chain(chain_), (4, 2)) == a @ b @ c).all()
    d = np.zeros((5, 3), int)
    d[1, 2], d[4, 0] = 2, -1
    change = matrix.matrix_chain_delta(chain_, 1, frame(d))
    assert (dense(matrix.added(matrix.matrix_chain(chain_), change), (4, 2)) == a @ (b + d) @ c).all()
    assert matrix.chain_order([10, 1000, 2, 1000])[1] == ((0, 1), 2)


def test_stepwise_polynomials_and_machines(spark):
    df = planted(spark).withColumn("noise", (F.col("x1") * 7919 % 13).cast("double"))
    s = flat_spec({"x1": "cont", "x2": "cont", "noise": "cont", "y": "cont"})
    ring = MomentRing(s)
    m = ridge.collected(ring, root(ring, s, df), ["x1", "x2", "noise"], "y")
    assert [g for _, g, *_ in learners.stepwise(m)][:2] == ["x1", "x2"] and "x1" not in [g for _, g, *_ in learners.stepwise(m, "backward")]
    quad = spark.createDataFrame([(x / 10, z / 10, 1 + 2 * x * z / 100) for x in range(-8, 9) for z in range(-6, 7)], "x double, z double, y double")
    s = flat_spec({"x": "cont", "z": "cont", "y": "cont"})
    terms = learners.term_values(root(SparseMomentRing(s, "double", 4), s, quad).df.collect())
    pm = learners.poly_moments(terms, ["x", "z"], "y", 2)
    fit = ridge.ridge_closed_form(pm, "y")
    assert fit.theta["x*z", None] == pytest.approx(2, abs=1e-6) and fit.theta["1", None] == pytest.approx(1, abs=1e-6)
    w0, _, v, losses = learners.fm_fit(terms, ["x", "z"], "y", 1, 400)
    assert all(a >= b for a, b in zip(losses, losses[1:])) and losses[-1] < 1e-4 * losses[0] and float(v[0] @ v[1]) == pytest.approx(2, abs=0.05)


def test_split_gain(spark):
    df = spark.createDataFrame([(i, int(i >= 6)) for i in range(10)], "x int, y int")
    gains = {r.cut: r.gain for r in information.split_gain(df, "y", "x").collect()}
    assert max(gains, key=gains.get) == 5 and gains[5] == pytest.approx(-(0.6 * math.log(0.6) + 0.4 * math.log(0.4))) and 9 not in gains


def test_quantile_edges_are_exact(spark):
    n = 200_000
    many = spark.range(n).selectExpr("CAST(pmod(id * 7919, 200000) AS double) / 100 AS x")
    assert quantile_edges(many, "x", 8) == [(-(-i * n // 8) - 1) / 100 for i in range(1, 8)]
    odd = [None, -1e308, 1e308, float("inf"), float("-inf"), 5e-324, 0.0, 0.0, 1.0, 1.0000000000000002, 3.0]
    few = spark.createDataFrame([(v,) for v in odd], "x double")
    known = sorted(v for v in odd if v is not None)
    assert quantile_edges(few, "x", 10) == sorted({known[i - 1] for i in range(1, 10)})
    assert quantile_edges(few, "x", 10, fan=2) == quantile_edges(few, "x", 10)
    assert quantile_edges(few.limit(0), "x", 4) == [] and quantile_edges(few.where("x = 3"), "x", 4) == [3.0]
