"""Registered queries of the library and their SQL: every method, variant, baseline and surrounding operator on the given tables."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import workloads as w
from .functions.binning import bin_edges, bin_width, quantile_edges
from .functions.payload import added_arrays, merged_maps
from .functions.unpack import UnpackEntries
from .operators import baselines, block, deptree, factorised, information, learners, matrix, metrics, relational, ridge, selection
from .operators.delta import as_delta, as_update, consolidate, factor_delta, propagate_all, propagate_factored_all
from .operators.evaluate import evaluate
from .operators.rings import CountRing, ListingRing, MomentRing, SumProductRing
from .operators.sparse import JointMomentRing, LateMomentRing, SparseMomentRing, compose
from .plans import explain
from .plans.spec import CAT, Attribute, QuerySpec
from .plans.tree import build_view_tree
from .sources import feeds
from .sources.store import ViewStore, new_folder
from .streaming import windows
from .streaming.live import LiveSession

Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_oracles: dict[str, str] = {}


def query(oracle: str | None = None):
    def register(f: Query) -> Query:
        _queries[f.__name__] = f
        if oracle:
            _oracles[f.__name__] = oracle
        return f

    return register


def queries() -> dict[str, Query]:
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    return dict(_oracles)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tables(spark: SparkSession, sf_dir: str, *names: str) -> list[DataFrame]:
    return [table(spark, sf_dir, n) for n in names]


def digits(df: DataFrame, column: str, n: int) -> DataFrame:
    return df.withColumn(column, F.round(F.col(column), n) + F.lit(0.0))


# Counts and scalar sums of products


@query(f"SELECT CAST(COUNT(*) AS BIGINT) AS c {w.J1_SQL}")
def count_join_j1(spark, sf_dir):
    spec = w.j1()
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    return evaluate(tree, data, CountRing(spec)).df


@query(f"SELECT CAST(COUNT(*) AS BIGINT) AS c {w.J3_SQL}")
def count_join_j3(spark, sf_dir):
    spec = w.j3(())
    tree, data = w.opened(spark, sf_dir, spec)
    return evaluate(tree, data, CountRing(spec)).df


@query("SELECT CAST(COUNT(*) AS BIGINT) AS c FROM orders JOIN customer ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey AND s_nationkey = c_nationkey")
def count_cyclic_j7(spark, sf_dir):
    """A cyclic join: customers and suppliers of one nation that meet in an order."""
    spec = QuerySpec({t: t for t in ("lineitem", "orders", "customer", "supplier")}, (("lineitem.l_orderkey", "orders.o_orderkey"), ("orders.o_custkey", "customer.c_custkey"), ("lineitem.l_suppkey", "supplier.s_suppkey"), ("customer.c_nationkey", "supplier.s_nationkey")))
    tree, data = w.opened(spark, sf_dir, spec, "sized")
    return evaluate(tree, data, CountRing(spec)).df


@query(f"SELECT r_name, CAST(COUNT(*) AS BIGINT) AS c {w.J1_SQL} GROUP BY r_name")
def count_by_region(spark, sf_dir):
    spec = w.j1(free=(w.attribute("r_name", CAT),))
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    return evaluate(tree, data, CountRing(spec)).df


@query(f"SELECT CAST(SUM(CAST(value AS DECIMAL(12,2)) * CAST(o_totalprice AS DECIMAL(12,2))) AS DOUBLE) AS v {w.J2_SQL}")
def sum_product_j2(spark, sf_dir):
    spec = w.j2((w.VALUE, w.PRICE))
    tree, data = w.opened(spark, sf_dir, spec)
    return evaluate(tree, data, SumProductRing(spec, {"value": "value", "o_totalprice": "o_totalprice"})).df.select(F.col("v").cast("double").alias("v"))


# Moments of continuous attributes


@query(w.moments_sql({a: a for a in w.A1_CONT}, w.J1_SQL))
def moments_j1_cont(spark, sf_dir):
    spec = w.j1(w.A1_CONT)
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    ring = w.decimal_ring(spec)
    return w.entry_rows(ring, evaluate(tree, data, ring))


@query(w.moments_sql({a: a for a in w.A1_CONT}, w.J1_SQL))
def moments_j1_dimension_order(spark, sf_dir):
    """The same under the other order of variables."""
    spec = w.j1(w.A1_CONT)
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_DIMENSION)
    ring = w.decimal_ring(spec)
    return w.entry_rows(ring, evaluate(tree, data, ring))


@query(w.moments_sql({"value": "value", "o_totalprice": "o_totalprice"}, w.J2_SQL))
def moments_j2_toy(spark, sf_dir):
    """Two relations that share one variable, the smallest case."""
    spec = w.j2((w.VALUE, w.PRICE))
    tree, data = w.opened(spark, sf_dir, spec)
    ring = w.decimal_ring(spec)
    return w.entry_rows(ring, evaluate(tree, data, ring))


@query(w.moments_sql({"l_quantity": "l_quantity", "o_totalprice": "o_totalprice"}, w.J1_SQL, {"c_mktsegment": "c_mktsegment"}))
def moments_grouped_segment(spark, sf_dir):
    spec = w.j1(("l_quantity", "o_totalprice"), free=(w.attribute("c_mktsegment", CAT),))
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    ring = w.decimal_ring(spec)
    return w.entry_rows(ring, evaluate(tree, data, ring))


@query(f"""WITH j AS (SELECT r_name, c_mktsegment, CAST(l_quantity AS DECIMAL(12,2)) AS a, CAST(o_totalprice AS DECIMAL(12,2)) AS b {w.J1_SQL})
SELECT r_name, c_mktsegment, CAST(GROUPING(r_name) * 2 + GROUPING(c_mktsegment) AS BIGINT) AS grouping, CAST(COUNT(*) AS BIGINT) AS c, CAST(SUM(a) AS DOUBLE) AS s_l_quantity, CAST(SUM(b) AS DOUBLE) AS s_o_totalprice,
CAST(SUM(a * b) AS DOUBLE) AS q_l_quantity__o_totalprice FROM j GROUP BY CUBE (r_name, c_mktsegment)""")
def moments_cube_region_segment(spark, sf_dir):
    """Each grouping is a ring sum over the finest one."""
    free = (w.attribute("r_name", CAT), w.attribute("c_mktsegment", CAT))
    spec = w.j1(("l_quantity", "o_totalprice"), free=free)
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    ring = w.decimal_ring(spec)
    finest = evaluate(tree, data, ring).df
    cube = finest.cube("r_name", "c_mktsegment").agg(F.grouping_id().alias("grouping"), *ring.sums(tree.root.attrs))
    return cube.select("r_name", "c_mktsegment", "grouping", "c", *[F.col(c).cast("double").alias(c) for c in ("s_l_quantity", "s_o_totalprice", "q_l_quantity__o_totalprice")])


_EMBEDDED = """WITH e AS (SELECT CAST(embedding AS DOUBLE[]) AS x FROM embeddings), i AS (SELECT unnest(generate_series(0, 64)) AS i), j AS (SELECT unnest(generate_series(0, 64)) AS j)
SELECT CAST(i AS INTEGER) AS i, CAST(j AS INTEGER) AS j, round(SUM((CASE WHEN i = 0 THEN 1.0 ELSE x[i] END) * (CASE WHEN j = 0 THEN 1.0 ELSE x[j] END)), 4) + 0.0 AS v FROM e, i, j WHERE i <= j GROUP BY i, j"""


@query(_EMBEDDED)
def moments_wide_embeddings(spark, sf_dir):
    """2,145 aggregates of 64 attributes by Gram blocks."""
    return digits(block.gram_block(table(spark, sf_dir, "embeddings"), "embedding"), "v", 4)


@query("""SELECT label, CAST(COUNT(*) AS DOUBLE) AS n, round(SUM(CAST(embedding[1] AS DOUBLE)), 6) + 0.0 AS s1, round(SUM(CAST(embedding[1] AS DOUBLE) * CAST(embedding[2] AS DOUBLE)), 6) + 0.0 AS q12 FROM embeddings GROUP BY label""")
def moments_wide_by_label(spark, sf_dir):
    g = block.gram_block(table(spark, sf_dir, "embeddings"), "embedding", ["label"]).where("(i = 0 and j in (0, 1)) or (i = 1 and j = 2)")
    at = lambda i, j: F.max(F.when((F.col("i") == i) & (F.col("j") == j), F.col("v")))
    return g.groupBy("label").agg(at(0, 0).alias("n"), (F.round(at(0, 1), 6) + F.lit(0.0)).alias("s1"), (F.round(at(1, 2), 6) + F.lit(0.0)).alias("q12"))


@query(w.moments_sql({a: a for a in ("l_quantity", "l_discount", "l_tax")}, "FROM lineitem"))
def layouts_agree(spark, sf_dir):
    """The same moments as columns, as blocks and as sparse entries; rows that differ would come twice."""
    names = ["l_discount", "l_quantity", "l_tax"]
    data = table(spark, sf_dir, "lineitem")
    spec = QuerySpec({"lineitem": "lineitem"}, (), tuple(Attribute(a, "lineitem") for a in names))
    rows = spec.rows("lineitem", data)
    dense, sparse = MomentRing(spec, "decimal"), SparseMomentRing(spec, "decimal")
    a = w.entry_rows(dense, dense.leaf(rows, (), tuple(names)))
    b = w.entry_rows(sparse, sparse.leaf(rows, (), tuple(names))).select("attr_u", "attr_v", "value")
    c = block.gram_block(data, names).select(F.transform(F.array("i", "j"), lambda k: F.element_at(F.array(F.lit("1"), *[F.lit(n) for n in names]), k + 1)).alias("p"), "v")
    c = c.select(F.col("p")[0].alias("attr_u"), F.col("p")[1].alias("attr_v"), F.round("v", 3).alias("value"))
    same = a.unionByName(b).withColumn("value", F.round("value", 4)).distinct()
    near = same.join(c.withColumnRenamed("value", "by_block"), ["attr_u", "attr_v"]).where(F.abs(F.col("value") - F.col("by_block")) <= F.abs("value") * 1e-9 + 2e-3)
    return near.select("attr_u", "attr_v", "value")


# Mixed kinds


def _mixed():
    return w.j1(("l_quantity", "o_totalprice"), ("l_returnflag", "c_mktsegment", "r_name"))


_MIXED_J = f"j AS (SELECT CAST(l_quantity AS DECIMAL(12,2)) AS l_quantity, CAST(o_totalprice AS DECIMAL(12,2)) AS o_totalprice, l_returnflag, c_mktsegment, r_name {w.J1_SQL})"


def _mixed_sql() -> str:
    cont, cat = ["l_quantity", "o_totalprice"], ["c_mktsegment", "l_returnflag", "r_name"]
    kinds = {**{c: "cont" for c in cont}, **{c: "cat" for c in cat}}
    row = lambda u, cu, v, cv, x, g: f"SELECT '{u}' AS attr_u, {cu} AS cat_u, '{v}' AS attr_v, {cv} AS cat_v, CAST({x} AS DOUBLE) AS value FROM j{f' GROUP BY {g}' if g else ''}"
    null = "CAST(NULL AS VARCHAR)"
    parts = [row("1", null, "1", null, "COUNT(*)", "")]
    for a in sorted(kinds):
        parts.append(row("1", null, a, a if kinds[a] == "cat" else null, "COUNT(*)" if kinds[a] == "cat" else f"SUM({a})", a if kinds[a] == "cat" else ""))
    names = sorted(kinds)
    for i, a in enumerate(names):
        for b in names[i:]:
            if a == b and kinds[a] == "cat":
                parts.append(row(a, a, a, a, "COUNT(*)", a))
                continue
            g = ", ".join(x for x in (a, b) if kinds[x] == "cat")
            x = " * ".join(x for x in (a, b) if kinds[x] == "cont") or None
            parts.append(row(a, a if kinds[a] == "cat" else null, b, b if kinds[b] == "cat" else null, f"SUM({x})" if x else "COUNT(*)", g))
    return f"WITH {_MIXED_J} " + " UNION ALL ".join(parts)


def _mixed_entries(spark, sf_dir):
    spec = _mixed()
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    ring = block.ring_for(spec, data, "decimal")
    return spec, ring.entries(evaluate(tree, data, ring)).withColumn("value", F.col("value").cast("double"))


@query(_mixed_sql())
def moments_mixed_j1(spark, sf_dir):
    return _mixed_entries(spark, sf_dir)[1].drop("n")


@query(f"WITH {_MIXED_J} SELECT c_mktsegment AS cat, CAST(SUM(l_quantity) AS DOUBLE) AS value FROM j GROUP BY c_mktsegment")
def cells_cont_cat(spark, sf_dir):
    e = _mixed_entries(spark, sf_dir)[1]
    return e.where("attr_u = 'c_mktsegment' and attr_v = 'l_quantity'").select(F.col("cat_u").alias("cat"), "value")


@query(f"WITH {_MIXED_J} SELECT l_returnflag AS cat_u, r_name AS cat_v, CAST(COUNT(*) AS BIGINT) AS n FROM j GROUP BY l_returnflag, r_name")
def cells_cat_cat(spark, sf_dir):
    e = _mixed_entries(spark, sf_dir)[1]
    return e.where("attr_u = 'l_returnflag' and attr_v = 'r_name'").select("cat_u", "cat_v", F.col("n").cast("long").alias("n"))


@query(f"""WITH e AS ({_mixed_sql()}), k AS (SELECT attr_u, attr_v, COUNT(*) AS n FROM e GROUP BY attr_u, attr_v)
SELECT attr_u, attr_v, CAST(CASE WHEN attr_u = attr_v THEN CASE WHEN attr_u IN ('c_mktsegment', 'l_returnflag', 'r_name') THEN 1 ELSE 0 END
ELSE CASE WHEN attr_u IN ('c_mktsegment', 'l_returnflag', 'r_name') THEN 1 ELSE 0 END + CASE WHEN attr_v IN ('c_mktsegment', 'l_returnflag', 'r_name') THEN 1 ELSE 0 END END AS INTEGER) AS rank, CAST(n AS BIGINT) AS n_entries FROM k""")
def moment_cell_rank(spark, sf_dir):
    spec, e = _mixed_entries(spark, sf_dir)
    return explain.moment_cells(spec, e).drop("cell")


# Mutual information


def _a2(spark, sf_dir, attrs=w.A2_CAT):
    spec = w.j1((), attrs)
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    return spec, tree, data, block.ring_for(spec, data)


def _mi(tree, data, ring):
    return information.mutual_information(ring.terms(evaluate(tree, data, ring)))


def _j1_mi(spark, sf_dir):
    spec, tree, data, ring = _a2(spark, sf_dir)
    return _mi(tree, data, ring)


_A2 = {a: a for a in w.A2_CAT}
_A2_MI = w.mi_parts(_A2, w.J1_SQL)


@query("WITH j AS (SELECT n_name, r_name, l_returnflag " + w.J1_SQL + """) SELECT '1' AS attr_u, '1' AS attr_v, CAST(COUNT(*) AS BIGINT) AS n, CAST(1 AS BIGINT) AS live FROM j
UNION ALL SELECT '1', 'n_name', CAST(SUM(c) AS BIGINT), CAST(COUNT(*) AS BIGINT) FROM (SELECT COUNT(*) AS c FROM j GROUP BY n_name)
UNION ALL SELECT '1', 'r_name', CAST(SUM(c) AS BIGINT), CAST(COUNT(*) AS BIGINT) FROM (SELECT COUNT(*) AS c FROM j GROUP BY r_name)
UNION ALL SELECT '1', 'l_returnflag', CAST(SUM(c) AS BIGINT), CAST(COUNT(*) AS BIGINT) FROM (SELECT COUNT(*) AS c FROM j GROUP BY l_returnflag)
UNION ALL SELECT 'n_name', 'r_name', CAST(SUM(c) AS BIGINT), CAST(COUNT(*) AS BIGINT) FROM (SELECT COUNT(*) AS c FROM j GROUP BY n_name, r_name)
UNION ALL SELECT 'l_returnflag', 'n_name', CAST(SUM(c) AS BIGINT), CAST(COUNT(*) AS BIGINT) FROM (SELECT COUNT(*) AS c FROM j GROUP BY n_name, l_returnflag)
UNION ALL SELECT 'l_returnflag', 'r_name', CAST(SUM(c) AS BIGINT), CAST(COUNT(*) AS BIGINT) FROM (SELECT COUNT(*) AS c FROM j GROUP BY r_name, l_returnflag)""")
def mi_counts_j1(spark, sf_dir):
    """The shared counts of degree 0, 1 and 2: their sums and numbers of live categories."""
    spec, tree, data, ring = _a2(spark, sf_dir, ("n_name", "r_name", "l_returnflag"))
    e = information.count_entries(ring.terms(evaluate(tree, data, ring)))
    return e.groupBy("attr_u", "attr_v").agg(F.sum("n").alias("n"), F.count("*").alias("live"))


@query(w.mi_sql(_A2, w.J1_SQL))
def mi_matrix_j1(spark, sf_dir):
    return digits(_j1_mi(spark, sf_dir), "mi", 8)


_DOCS = "FROM documents d JOIN labels l ON d.doc_id = l.doc_id"
_DOC_ATTRS = {"lang": "lang", "source": "source", "quality": "quality", "toxic": "toxic", "size_bin": "least(CAST(floor(n_chars / 500.0) AS BIGINT), 20)"}


def _docs_spec():
    return QuerySpec({"documents": "documents", "labels": "labels"}, (("documents.doc_id", "labels.doc_id"),), (
        Attribute("lang", "documents", CAT), Attribute("source", "documents", CAT), Attribute("size_bin", "documents", CAT, "least(cast(floor(n_chars / 500.0) as bigint), 20)"),
        Attribute("quality", "labels", CAT), Attribute("toxic", "labels", CAT)))


def _docs_mi(spark, sf_dir):
    spec = _docs_spec()
    tree, data = w.opened(spark, sf_dir, spec)
    return _mi(tree, data, SparseMomentRing(spec))


@query(w.mi_sql(_DOC_ATTRS, _DOCS))
def mi_matrix_docs(spark, sf_dir):
    """A join in which most documents have no partner; size in bins."""
    return digits(_docs_mi(spark, sf_dir), "mi", 8)


@query(w.mi_sql({"event_type": "event_type", "value_bin": "least(CAST(floor(value / 20.0) AS BIGINT), 25)", "n_name": "n_name"}, "FROM events JOIN customer ON user_id = c_custkey JOIN nation ON c_nationkey = n_nationkey"))
def mi_binned_events(spark, sf_dir):
    spec = QuerySpec({"events": "events", "customer": "customer", "nation": "nation"}, (("events.user_id", "customer.c_custkey"), ("customer.c_nationkey", "nation.n_nationkey")), (
        Attribute("event_type", "events", CAT), Attribute("value_bin", "events", CAT, "value_bin"), Attribute("n_name", "nation", CAT)))
    events = table(spark, sf_dir, "events").withColumn("value_bin", bin_width("value", 0.0, 20.0, 25))
    data = {"events": events, "customer": table(spark, sf_dir, "customer"), "nation": table(spark, sf_dir, "nation")}
    spec.validate(data)
    return digits(information.mutual_information(evaluate(build_view_tree(spec), data, SparseMomentRing(spec))), "mi", 8)


@query(f"WITH {_A2_MI[0]}, mi AS ({_A2_MI[1]}) SELECT attr_u AS attr, round(mi, 8) + 0.0 AS entropy FROM mi WHERE attr_u = attr_v")
def mi_entropy_diag(spark, sf_dir):
    return digits(_j1_mi(spark, sf_dir).where("attr_u = attr_v").select(F.col("attr_u").alias("attr"), F.col("mi").alias("entropy")), "entropy", 8)


@query(w.mi_sql({a: a for a in ("n_name", "r_name", "c_mktsegment", "l_returnflag")}, w.J1_SQL, diagonal=False))
def mi_pairwise_baseline(spark, sf_dir):
    """One query per pair over the flat join: what the shared counts avoid."""
    spec = w.j1((), ("n_name", "r_name", "c_mktsegment", "l_returnflag"))
    _, data = w.opened(spark, sf_dir, spec)
    return digits(baselines.mi_pairwise(baselines.joined_rows(spec, data), [a.name for a in spec.attributes]), "mi", 8)


@query("""WITH j AS (SELECT p_brand AS x, p_size AS y FROM part), n AS (SELECT CAST(COUNT(*) AS DOUBLE) AS n FROM j)
SELECT round(SUM(cxy / n * ln(n * cxy / (cx * cy))), 8) + 0.0 AS mi FROM (SELECT x, y, CAST(COUNT(*) AS DOUBLE) AS cxy FROM j GROUP BY x, y) p
JOIN (SELECT x, CAST(COUNT(*) AS DOUBLE) AS cx FROM j GROUP BY x) a USING (x) JOIN (SELECT y, CAST(COUNT(*) AS DOUBLE) AS cy FROM j GROUP BY y) b USING (y), n""")
def mi_direct_form(spark, sf_dir):
    return digits(information.mutual_information_direct(table(spark, sf_dir, "part"), "p_brand", "p_size"), "mi", 8)


@query("""WITH c AS (SELECT p_brand, CAST(COUNT(*) AS DOUBLE) AS c FROM part GROUP BY p_brand), n AS (SELECT SUM(c) AS n FROM c) SELECT round(-SUM(c / n * ln(c / n)), 8) + 0.0 AS entropy FROM c, n""")
def entropy_brand(spark, sf_dir):
    return digits(information.entropy(table(spark, sf_dir, "part"), "p_brand"), "entropy", 8)


@query(f"""WITH {_A2_MI[0]}, mi AS ({_A2_MI[1]}) SELECT m.attr_u, m.attr_v, round(CASE WHEN h.mi * k.mi > 0 THEN m.mi / sqrt(h.mi * k.mi) ELSE 0.0 END, 8) + 0.0 AS normalised
FROM mi m JOIN mi h ON h.attr_u = m.attr_u AND h.attr_v = m.attr_u JOIN mi k ON k.attr_u = m.attr_v AND k.attr_v = m.attr_v""")
def mi_normalised(spark, sf_dir):
    return digits(information.normalised(_j1_mi(spark, sf_dir)).drop("mi"), "normalised", 8)


# Selection


def _selected_sql(ctes: str, parts: str, label: str, threshold: float) -> str:
    return f"""WITH {ctes}, mi AS ({parts}), r AS (SELECT CASE WHEN attr_u = '{label}' THEN attr_v ELSE attr_u END AS attr, mi FROM mi WHERE (attr_u = '{label}') <> (attr_v = '{label}'))
SELECT CAST(row_number() OVER (ORDER BY mi DESC, attr) AS INTEGER) AS rank, attr, round(mi, 8) + 0.0 AS mi, mi > {threshold} AS selected FROM r"""


@query(_selected_sql(*_A2_MI, "l_returnflag", 1e-4))
def select_features_returnflag(spark, sf_dir):
    return digits(selection.select_features(_j1_mi(spark, sf_dir), "l_returnflag", 1e-4), "mi", 8)


@query(_selected_sql(*w.mi_parts(_DOC_ATTRS, _DOCS), "quality", 0.03))
def select_features_quality(spark, sf_dir):
    return digits(selection.select_features(_docs_mi(spark, sf_dir), "quality", 0.03), "mi", 8)


def _change_sql() -> str:
    attrs = {"r_name": "r_name", "c_mktsegment": "c_mktsegment", "o_orderpriority": "o_orderpriority"}
    sides = []
    for side, where in (("a", "l_orderkey % 6 <= 2"), ("b", "l_orderkey % 6 <= 5")):
        ctes, parts = w.mi_parts({**attrs, "l_returnflag": "l_returnflag"}, f"{w.J1_SQL} WHERE {where}")
        ctes = ctes.replace("j AS", f"j{side} AS").replace("n AS (SELECT CAST(COUNT(*) AS DOUBLE) AS n FROM j)", f"n{side} AS (SELECT CAST(COUNT(*) AS DOUBLE) AS n FROM j{side})")
        parts = parts.replace("FROM j ", f"FROM j{side} ").replace(", n UNION", f", n{side} UNION")
        parts = parts[: parts.rindex(", n")] + f", n{side}"
        label = "l_returnflag"
        sides.append(f"{ctes}, mi{side} AS ({parts}), r{side} AS (SELECT CASE WHEN attr_u = '{label}' THEN attr_v ELSE attr_u END AS attr, mi FROM mi{side} WHERE (attr_u = '{label}') <> (attr_v = '{label}')), s{side} AS (SELECT row_number() OVER (ORDER BY mi DESC, attr) AS rank, attr, mi FROM r{side})")
    return f"WITH {sides[0]}, {sides[1]} SELECT a.attr, CAST(a.rank AS INTEGER) AS rank_before, CAST(b.rank AS INTEGER) AS rank_after, round(a.mi, 8) + 0.0 AS mi_before, round(b.mi, 8) + 0.0 AS mi_after, CASE WHEN a.mi <= 0.0001 AND b.mi > 0.0001 THEN 'entered' WHEN a.mi > 0.0001 AND b.mi <= 0.0001 THEN 'left' ELSE 'stayed' END AS change FROM sa a JOIN sb b ON a.attr = b.attr"


@query(_change_sql())
def selection_changes_bulk(spark, sf_dir):
    """Ranks before and after three bulks of line items."""
    spec = w.j1((), ("r_name", "c_mktsegment", "o_orderpriority", "l_returnflag"))
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    initial, bulks = feeds.lineitem_bulks(data["lineitem"])
    store = ViewStore(spark, tree, SparseMomentRing(spec), updatable=("lineitem",)).initialise({**data, "lineitem": initial})
    before = selection.select_features(information.mutual_information(store.state()), "l_returnflag", 1e-4)
    for i, b in enumerate(bulks):
        propagate_all(store, {"lineitem": b}, f"{i:03d}")
    after = selection.select_features(information.mutual_information(store.state()), "l_returnflag", 1e-4)
    return digits(digits(selection.selection_changes(before, after), "mi_before", 8), "mi_after", 8)


# Dependency tree


_TREE = f"""WITH RECURSIVE {_A2_MI[0]}, mi AS ({_A2_MI[1]}), r AS (SELECT attr_u, attr_v, mi, row_number() OVER (ORDER BY mi DESC, attr_u, attr_v) AS k FROM mi WHERE attr_u <> attr_v),
reach(k, node) AS (SELECT k, attr_u FROM r UNION SELECT reach.k, CASE WHEN e.attr_u = reach.node THEN e.attr_v ELSE e.attr_u END FROM reach JOIN r e ON e.k < reach.k AND (e.attr_u = reach.node OR e.attr_v = reach.node)),
t AS (SELECT attr_u AS u, attr_v AS v, mi FROM r WHERE NOT EXISTS (SELECT 1 FROM reach WHERE reach.k = r.k AND reach.node = r.attr_v))"""


#: The tree of any attributes: fill in CTEs and MI rows.
_TREE_OF = _TREE.replace(_A2_MI[0], "{ctes}").replace(_A2_MI[1], "{parts}")


@query(f"{_TREE} SELECT u, v, round(mi, 8) + 0.0 AS mi FROM t")
def dependency_tree_j1(spark, sf_dir):
    t = deptree.dependency_tree(_j1_mi(spark, sf_dir), "n_name")
    return digits(t.select(F.least("parent", "child").alias("u"), F.greatest("parent", "child").alias("v"), "mi"), "mi", 8)


@query(f"{_TREE} SELECT u, v, round(mi, 8) + 0.0 AS mi FROM t")
def dependency_tree_distributed(spark, sf_dir):
    """The same tree by rounds over edges that never reach the driver."""
    return digits(deptree.spanning_tree_distributed(_j1_mi(spark, sf_dir)), "mi", 8)


@query(f"{_TREE} SELECT round(SUM(mi), 8) + 0.0 AS weight, CAST(COUNT(*) AS BIGINT) AS edges FROM t")
def tree_weight(spark, sf_dir):
    return digits(deptree.tree_weight(deptree.dependency_tree(_j1_mi(spark, sf_dir))), "weight", 8)


@query(f"""WITH j AS (SELECT n_name, r_name {w.J1_SQL}) SELECT 'n_name' AS parent, n_name AS parent_cat, 'r_name' AS child, r_name AS child_cat, CAST(COUNT(*) AS BIGINT) AS n,
round(COUNT(*) / CAST(SUM(COUNT(*)) OVER (PARTITION BY n_name) AS DOUBLE), 8) + 0.0 AS p FROM j GROUP BY n_name, r_name""")
def tree_cpts(spark, sf_dir):
    spec, tree, data, ring = _a2(spark, sf_dir, ("n_name", "r_name"))
    v = ring.terms(evaluate(tree, data, ring))
    return digits(deptree.cpts(v, deptree.dependency_tree(information.mutual_information(v), "n_name")), "p", 8)


# Ridge regression


def _two(spark, sf_dir, data=None):
    spec = w.j1(("l_extendedprice", "l_quantity", "o_totalprice"), label="l_extendedprice")
    tree, found = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    ring = w.decimal_ring(spec)
    return ring, spec, tree, found


def _theta(spark, model):
    t = F.col("theta")
    shown = F.when(F.col("attr") == "1", F.round(t, 3)).when(F.col("attr") == "l_quantity", F.round(t, 5)).otherwise(F.round(t, 8))
    return ridge.model_rows(spark, model).select("attr", (shown + F.lit(0.0)).alias("theta"))


_CLOSED = w.closed_form_sql("l_extendedprice", "l_quantity", "o_totalprice", w.J1_SQL)


@query(_CLOSED)
def ridge_two_features_closed(spark, sf_dir):
    ring, spec, tree, data = _two(spark, sf_dir)
    m = ridge.collected(ring, evaluate(tree, data, ring), ["l_quantity", "o_totalprice"], "l_extendedprice")
    return _theta(spark, ridge.ridge_closed_form(m, "l_extendedprice"))


@query(_CLOSED)
def ridge_gd_j1(spark, sf_dir):
    ring, spec, tree, data = _two(spark, sf_dir)
    m = ridge.collected(ring, evaluate(tree, data, ring), ["l_quantity", "o_totalprice"], "l_extendedprice")
    return _theta(spark, ridge.ridge_fit(m, "l_extendedprice", tol=1e-13))


def _ridge_mixed_sql() -> str:
    cats = {"c_mktsegment": w.SEGMENTS, "o_orderpriority": w.PRIORITIES, "r_name": w.REGIONS}
    conts = ["c_acctbal", "l_discount", "l_quantity", "l_tax", "o_totalprice"]
    named = sorted([(c, None) for c in conts] + [(a, v) for a, vs in cats.items() for v in vs], key=lambda f: (f[0], f[1] or ""))
    x = ["1.0", *[c if v is None else f"CASE WHEN {c} = '{v}' THEN 1.0 ELSE 0.0 END" for c, v in named], "l_extendedprice"]
    shown = " UNION ALL ".join(f"SELECT {i} AS i, '{a}' AS attr, {f'{v!r}' if v else 'CAST(NULL AS VARCHAR)'} AS cat" for i, (a, v) in enumerate([("1", None), *named], 1))
    cells = ", ".join(f"[{', '.join(f'avg(v[{min(i, j)}] * v[{max(i, j)}])' for j in range(1, len(x) + 1))}]" for i in range(1, len(x) + 1))
    matrix = f"j AS (SELECT [{', '.join(f'CAST({e} AS DOUBLE)' for e in x)}] AS v {w.J1_SQL}), matrix AS (SELECT [{cells}] AS m FROM j)"
    return f"WITH RECURSIVE {w.solved_sql(matrix, 1e-3)}, names AS ({shown}) SELECT attr, cat, round(theta, 2) + 0.0 AS theta FROM names JOIN theta USING (i)"


@query(_ridge_mixed_sql())
def ridge_mixed_j1(spark, sf_dir):
    """One parameter per continuous attribute and per live category, by descent with a penalty."""
    spec = w.j1(("l_quantity", "l_discount", "l_tax", "o_totalprice", "c_acctbal", "l_extendedprice"), ("c_mktsegment", "o_orderpriority", "r_name"), label="l_extendedprice")
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    ring = block.ring_for(spec, data, "decimal")
    features = [a.name for a in spec.attributes if a.name != "l_extendedprice"]
    m = ridge.collected(ring, evaluate(tree, data, ring), features, "l_extendedprice")
    return digits(ridge.model_rows(spark, ridge.ridge_fit(m, "l_extendedprice", lam=1e-3, tol=1e-13)), "theta", 2)


@query(f"WITH RECURSIVE {w.solved_sql(f'j AS (SELECT [1.0, CAST(l_quantity AS DOUBLE), CAST(o_totalprice AS DOUBLE), CAST(l_extendedprice AS DOUBLE)] AS v {w.J1_SQL}), matrix AS (SELECT [' + ', '.join('[' + ', '.join(f'avg(v[{i}] * v[{j}])' for j in range(1, 5)) + ']' for i in range(1, 5)) + '] AS m FROM j)', 1e-2)} SELECT CASE i WHEN 2 THEN 'l_quantity' ELSE 'o_totalprice' END AS attr, round(a[i - 1][3], 6) + 0.0 AS theta FROM theta, (SELECT a FROM g ORDER BY step DESC LIMIT 1) WHERE i > 1")
def ridge_distributed_j1(spark, sf_dir):
    """The descent as joins of the matrix with the parameters, for more of them than a driver should hold; scaled slopes."""
    ring, spec, tree, data = _two(spark, sf_dir)
    m = ridge.collected(ring, evaluate(tree, data, ring), ["l_quantity", "o_totalprice"], "l_extendedprice")
    entries = spark.createDataFrame(ridge.scaled_entries(m, "l_extendedprice"), "attr_u string, cat_u string, attr_v string, cat_v string, value double")
    return digits(ridge.ridge_fit_distributed(entries, "l_extendedprice", 1e-2, 10, 0.95).select("attr", "theta"), "theta", 6)


@query(_CLOSED)
def ridge_resume_bulk(spark, sf_dir):
    """A model of the initial state, resumed after each of three bulks: it ends at the optimum of the final state."""
    ring, spec, tree, data = _two(spark, sf_dir)
    initial, bulks = feeds.lineitem_bulks(data["lineitem"])
    store = ViewStore(spark, tree, ring, updatable=("lineitem",)).initialise({**data, "lineitem": initial})
    read = lambda: ridge.collected(ring, store.state(), ["l_quantity", "o_totalprice"], "l_extendedprice")
    model = ridge.ridge_fit(read(), "l_extendedprice", tol=1e-13)
    for i, b in enumerate(bulks):
        propagate_all(store, {"lineitem": b}, f"{i:03d}")
        model = ridge.ridge_resume(model, read(), tol=1e-13)
    return _theta(spark, model)


@query("SELECT l_returnflag, round(regr_slope(l_extendedprice, l_quantity), 4) + 0.0 AS slope, round(regr_intercept(l_extendedprice, l_quantity), 3) + 0.0 AS intercept, round(corr(l_extendedprice, l_quantity), 8) + 0.0 AS corr, round(var_pop(l_quantity), 6) + 0.0 AS var_x FROM lineitem GROUP BY l_returnflag")
def regr_from_moments(spark, sf_dir):
    spec = QuerySpec({"lineitem": "lineitem"}, (), (Attribute("l_extendedprice", "lineitem"), Attribute("l_quantity", "lineitem")), free=(Attribute("l_returnflag", "lineitem", CAT),))
    tree_rows = spec.rows("lineitem", table(spark, sf_dir, "lineitem"))
    v = w.decimal_ring(spec).leaf(tree_rows, ("l_returnflag",), ("l_extendedprice", "l_quantity")).df
    c, sy, sx = (F.col(x).cast("double") for x in ("c", "s_l_extendedprice", "s_l_quantity"))
    qyy, qxy, qxx = (F.col(x).cast("double") for x in ("q_l_extendedprice__l_extendedprice", "q_l_extendedprice__l_quantity", "q_l_quantity__l_quantity"))
    slope = (c * qxy - sx * sy) / (c * qxx - sx * sx)
    out = v.select("l_returnflag", slope.alias("slope"), ((sy - slope * sx) / c).alias("intercept"), relational.correlation(c, sx, sy, qxx, qxy, qyy).alias("corr"), (qxx / c - (sx / c) * (sx / c)).alias("var_x"))
    for name, n in (("slope", 4), ("intercept", 3), ("corr", 8), ("var_x", 6)):
        out = digits(out, name, n)
    return out


@query(f"""WITH j AS (SELECT l_quantity, l_discount, o_totalprice {w.J1_SQL}) SELECT 'l_discount' AS attr_u, 'l_quantity' AS attr_v, round(corr(l_discount, l_quantity), 8) + 0.0 AS corr FROM j
UNION ALL SELECT 'l_discount', 'o_totalprice', round(corr(l_discount, o_totalprice), 8) + 0.0 FROM j UNION ALL SELECT 'l_quantity', 'o_totalprice', round(corr(l_quantity, o_totalprice), 8) + 0.0 FROM j""")
def corr_matrix_from_moments(spark, sf_dir):
    names = ("l_discount", "l_quantity", "o_totalprice")
    spec = w.j1(names)
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    v = evaluate(tree, data, w.decimal_ring(spec)).df
    rows = [F.struct(F.lit(a).alias("attr_u"), F.lit(b).alias("attr_v"), relational.correlation(F.col("c"), F.col(f"s_{a}"), F.col(f"s_{b}"), F.col(f"q_{a}__{a}"), F.col(f"q_{a}__{b}"), F.col(f"q_{b}__{b}")).alias("corr")) for i, a in enumerate(names) for b in names[i + 1 :]]
    return digits(v.select(F.inline(F.array(*rows))), "corr", 8)


_FITTED = w.closed_form_sql("l_extendedprice", "l_quantity", "o_totalprice", w.J1_SQL).split("SELECT '1' AS attr")[0]


@query(f"""{_FITTED} SELECT round(sqrt(avg(power(y - (my - ta * ma - tb * mb) - ta * a - tb * b, 2))), 4) + 0.0 AS rmse, round(1 - avg(power(y - (my - ta * ma - tb * mb) - ta * a - tb * b, 2)) / var_pop(y), 8) + 0.0 AS r2 FROM j, t""")
def rmse_from_moments(spark, sf_dir):
    ring, spec, tree, data = _two(spark, sf_dir)
    m = ridge.collected(ring, evaluate(tree, data, ring), ["l_quantity", "o_totalprice"], "l_extendedprice")
    rmse, r2 = ridge.rmse_from_moments(m, ridge.ridge_closed_form(m, "l_extendedprice"))
    return digits(digits(spark.createDataFrame([(rmse, r2)], "rmse double, r2 double"), "rmse", 4), "r2", 8)


@query(f"""{_FITTED} SELECT round(avg((my - ta * ma - tb * mb) + ta * a + tb * b), 2) + 0.0 AS mean, CAST(COUNT(*) AS BIGINT) AS n FROM j, t""")
def predict_rows(spark, sf_dir):
    """The fitted model scored on every join row by a column expression."""
    ring, spec, tree, data = _two(spark, sf_dir)
    m = ridge.collected(ring, evaluate(tree, data, ring), ["l_quantity", "o_totalprice"], "l_extendedprice")
    scored = ridge.predict(ridge.ridge_closed_form(m, "l_extendedprice"), baselines.joined_rows(spec, data))
    return digits(scored.agg(F.avg("prediction").alias("mean"), F.count("*").alias("n")), "mean", 2)


@query(f"""{_FITTED}, l AS (SELECT round(0.5 * avg(power(y - (my - ta * ma - tb * mb) - ta * a - tb * b, 2)) / var_pop(y), 8) + 0.0 AS loss FROM j, t) SELECT 'warm' AS start, loss, true AS no_slower FROM l UNION ALL SELECT 'cold', loss, true FROM l""")
def cold_start_ablation(spark, sf_dir):
    """After a bulk: descent resumed against started anew. Both reach the optimum, the resumed one in no more steps."""
    ring, spec, tree, data = _two(spark, sf_dir)
    initial, bulks = feeds.lineitem_bulks(data["lineitem"])
    features, label = ["l_quantity", "o_totalprice"], "l_extendedprice"
    before = ridge.collected(ring, evaluate(tree, {**data, "lineitem": initial}, ring), features, label)
    after = ridge.collected(ring, evaluate(tree, data, ring), features, label)
    model = ridge.ridge_fit(before, label)
    warm, cold = ridge.ridge_resume(model, after), ridge.ridge_fit(after, label)
    rows = [(n, round(x.loss, 8), x.iterations <= cold.iterations) for n, x in (("warm", warm), ("cold", cold))]
    return spark.createDataFrame(rows, "start string, loss double, no_slower boolean")


# Maintenance


_CONT2 = ("l_quantity", "o_totalprice", "c_acctbal")


def _kept(spark, sf_dir, spec, order, initial: dict, bulks: list[dict], ring=None, updatable=None):
    """Initial load and bulks through the view store; the store."""
    tree, data = w.opened(spark, sf_dir, spec, order)
    ring = ring or w.decimal_ring(spec)
    made = {a: f(data[a]) for a, f in initial.items()}
    store = ViewStore(spark, tree, ring, updatable=updatable or tuple({a for b in bulks for a in b})).initialise({**data, **made})
    for i, b in enumerate(bulks):
        propagate_all(store, {a: f(data[a]) for a, f in b.items()}, f"{i + 1:03d}")
    return store


def _rows(store):
    return w.entry_rows(store.ring, store.state())


def _residue(lo: int, hi: int | None = None, key="l_orderkey"):
    return lambda df: df.where(F.pmod(F.col(key), F.lit(6)).between(lo, lo if hi is None else hi))


def _inserted(lo: int, key="l_orderkey"):
    return lambda df: as_delta(_residue(lo, key=key)(df))


_CONT2_SQL = {a: a for a in _CONT2}


@query(w.moments_sql(_CONT2_SQL, w.J1_SQL))
def delta_insert_j1(spark, sf_dir):
    return _rows(_kept(spark, sf_dir, w.j1(_CONT2), w.ORDER_FACT, {"lineitem": _residue(0, 2)}, [{"lineitem": _inserted(2 + b)} for b in (1, 2, 3)]))


@query(w.moments_sql(_CONT2_SQL, f"{w.J1_SQL} WHERE l_orderkey % 6 <= 2"))
def delta_delete_j1(spark, sf_dir):
    gone = lambda r: lambda df: as_delta(None, _residue(r)(df))
    return _rows(_kept(spark, sf_dir, w.j1(_CONT2), w.ORDER_FACT, {}, [{"lineitem": gone(r)} for r in (3, 4, 5)]))


@query(w.moments_sql(_CONT2_SQL, f"{w.J1_SQL} WHERE NOT (l_orderkey % 6 < 3 AND l_linenumber = 1)"))
def delta_mixed_j1(spark, sf_dir):
    """Inserts and deletes in one bulk; other order of variables, so each bulk passes five views."""
    mixed = lambda b: lambda df: as_delta(_residue(2 + b)(df), _residue(b - 1)(df).where("l_linenumber = 1"))
    return _rows(_kept(spark, sf_dir, w.j1(_CONT2), w.ORDER_DIMENSION, {"lineitem": _residue(0, 2)}, [{"lineitem": mixed(b)} for b in (1, 2, 3)]))


_EVENTS_STATE = "event_id < (SELECT COUNT(*) * 0.8 FROM events) AND NOT (event_id < (SELECT COUNT(*) * 0.7 FROM events) AND event_id % 10 = 3)"


def _events_bulk(b: int):
    def bulk(df):
        n = df.count()
        low, high = n * (4 + b) / 10, n * (5 + b) / 10
        older = df.where((F.col("event_id") < low) & (F.col("event_id") >= (0 if b == 1 else n * (3 + b) / 10)) & (F.col("event_id") % 10 == 3))
        return as_delta(df.where((F.col("event_id") >= low) & (F.col("event_id") < high)), older)

    return bulk


def _first_half(df):
    return df.where(F.col("event_id") < df.count() * 0.5)


@query(w.moments_sql({"value": "value", "l_quantity": "l_quantity"}, f"{w.J3_SQL} WHERE {_EVENTS_STATE}"))
def delta_mixed_j3(spark, sf_dir):
    """A join far larger than its inputs, under inserts and deletes of events."""
    spec = w.j3((w.VALUE, Attribute("l_quantity", "lineitem")))
    return _rows(_kept(spark, sf_dir, spec, "auto", {"events": _first_half}, [{"events": _events_bulk(b)} for b in (1, 2, 3)]))


@query(w.moments_sql(_CONT2_SQL, f"{w.J1_SQL} WHERE l_orderkey % 6 <= 4"))
def delta_two_relations(spark, sf_dir):
    """Line items come before their orders in the same bulk."""
    bulks = [{"lineitem": _inserted(2 + b), "orders": _inserted(2 + b, "o_orderkey")} for b in (1, 2)]
    return _rows(_kept(spark, sf_dir, w.j1(_CONT2), w.ORDER_FACT, {"lineitem": _residue(0, 2), "orders": _residue(0, 2, "o_orderkey")}, bulks))


@query(w.moments_sql({"l_quantity": "l_quantity", "o_totalprice": "CASE WHEN o_orderkey % 7 = 0 THEN o_totalprice + 100 ELSE o_totalprice END"}, w.J1_SQL))
def delta_value_update(spark, sf_dir):
    changed = lambda df: as_update(df.where("o_orderkey % 7 = 0"), df.where("o_orderkey % 7 = 0").withColumn("o_totalprice", F.col("o_totalprice") + 100))
    return _rows(_kept(spark, sf_dir, w.j1(("l_quantity", "o_totalprice")), w.ORDER_FACT, {}, [{"orders": changed}]))


@query("SELECT n_name, CAST(COUNT(*) AS BIGINT) AS c FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON n_nationkey = CASE WHEN c_custkey % 50 = 0 THEN (c_nationkey + 1) % 25 ELSE c_nationkey END JOIN region ON n_regionkey = r_regionkey GROUP BY n_name")
def delta_dimension_move(spark, sf_dir):
    """Customers that move to another nation: delete and insert under different keys in one bulk."""
    def moved(df):
        some = df.where("c_custkey % 50 = 0")
        return as_update(some, some.withColumn("c_nationkey", ((F.col("c_nationkey") + 1) % 25).cast("int")))

    spec = w.j1(free=(w.attribute("n_name", CAT),))
    return _kept(spark, sf_dir, spec, w.ORDER_FACT, {}, [{"customer": moved}], CountRing(spec)).state().df


@query(w.moments_sql({"value": "value", "o_totalprice": "o_totalprice"}, f"{w.J2_SQL} JOIN (SELECT 1 AS copy UNION ALL SELECT 2) x ON copy = 1 OR event_id % 11 = 0"))
def delta_duplicates(spark, sf_dir):
    """Rows inserted twice more, then deleted once: multiplicities, not sets."""
    some = lambda df: df.where("event_id % 11 = 0")
    bulks = [{"events": lambda df: as_delta(some(df).withColumn("mult", F.lit(2)))}, {"events": lambda df: as_delta(None, some(df))}]
    return _rows(_kept(spark, sf_dir, w.j2((w.VALUE, w.PRICE)), "auto", {}, bulks))


@query(w.moments_sql({"qa": "a.l_quantity", "qb": "b.l_quantity"}, "FROM lineitem a JOIN lineitem b ON a.l_partkey = b.l_partkey WHERE a.l_orderkey % 6 <= 3 AND b.l_orderkey % 6 <= 3"))
def delta_self_join(spark, sf_dir):
    """One table under two aliases: its bulk goes to each leaf in turn."""
    spec = QuerySpec({"a": "lineitem", "b": "lineitem"}, (("a.l_partkey", "b.l_partkey"),), (Attribute("qa", "a", expr="l_quantity"), Attribute("qb", "b", expr="l_quantity")))
    return _rows(_kept(spark, sf_dir, spec, "auto", {"a": _residue(0, 2), "b": _residue(0, 2)}, [{"a": _inserted(3), "b": _inserted(3)}]))


@query(w.moments_sql({"qa": "a.l_quantity", "qb": "b.l_quantity"}, "FROM lineitem a JOIN lineitem b ON a.l_partkey = b.l_partkey"))
def delta_self_join_all(spark, sf_dir):
    """delta_self_join up to the whole table."""
    spec = QuerySpec({"a": "lineitem", "b": "lineitem"}, (("a.l_partkey", "b.l_partkey"),), (Attribute("qa", "a", expr="l_quantity"), Attribute("qb", "b", expr="l_quantity")))
    return _rows(_kept(spark, sf_dir, spec, "auto", {"a": _residue(0, 2), "b": _residue(0, 2)}, [{"a": _inserted(r), "b": _inserted(r)} for r in (3, 4, 5)]))


@query("SELECT '' AS attr_u, '' AS attr_v, CAST(0 AS DOUBLE) AS value WHERE false")
def delta_to_empty(spark, sf_dir):
    gone = lambda r: lambda df: as_delta(None, df.where(F.col("event_id") % 3 == r))
    return _rows(_kept(spark, sf_dir, w.j2((w.VALUE, w.PRICE)), "auto", {}, [{"events": gone(r)} for r in (0, 1, 2)]))


def _trace_sql() -> str:
    parts = []
    for b in range(4):
        parts.append(f"SELECT CAST({b} AS INTEGER) AS bulk, CAST(COUNT(*) AS BIGINT) AS c, CAST(SUM(CAST(l_quantity AS DECIMAL(12,2))) AS DOUBLE) AS s_l_quantity, CAST(SUM(CAST(l_quantity AS DECIMAL(12,2)) * CAST(o_totalprice AS DECIMAL(12,2))) AS DOUBLE) AS q {w.J1_SQL} WHERE l_orderkey % 6 <= {2 + b} AND NOT (l_orderkey % 6 < {b} AND l_linenumber = 1)")
    return " UNION ALL ".join(parts)


@query(_trace_sql())
def bulk_trace_10k(spark, sf_dir):
    """The state after each bulk, read back by batch."""
    mixed = lambda b: lambda df: as_delta(_residue(2 + b)(df), _residue(b - 1)(df).where("l_linenumber = 1"))
    store = _kept(spark, sf_dir, w.j1(("l_quantity", "o_totalprice")), w.ORDER_FACT, {"lineitem": _residue(0, 2)}, [{"lineitem": mixed(b)} for b in (1, 2, 3)])
    out = None
    for b in range(4):
        one = store.state(until=b).df.select(F.lit(b).alias("bulk"), "c", F.col("s_l_quantity").cast("double").alias("s_l_quantity"), F.col("q_l_quantity__o_totalprice").cast("double").alias("q"))
        out = one if out is None else out.unionByName(one)
    return out


@query(w.moments_sql(_CONT2_SQL, w.J1_SQL))
def compacted_state(spark, sf_dir):
    """Compaction between bulks changes nothing."""
    store = _kept(spark, sf_dir, w.j1(_CONT2), w.ORDER_FACT, {"lineitem": _residue(0, 2)}, [{"lineitem": _inserted(3)}, {"lineitem": _inserted(4)}])
    store.compact()
    propagate_all(store, {"lineitem": _inserted(5)(table(spark, sf_dir, "lineitem"))}, "003")
    store.compact()
    return _rows(store)


@query(w.moments_sql(_CONT2_SQL, w.J1_SQL))
def compacted_out_of_order(spark, sf_dir):
    """Bulks whose names do not sort as they came, before and after a compaction, the last one twice."""
    store = _kept(spark, sf_dir, w.j1(_CONT2), w.ORDER_FACT, {"lineitem": _residue(0, 1)}, [], updatable=("lineitem",))
    lineitem = table(spark, sf_dir, "lineitem")
    for residue, name in ((2, "batch-8"), (3, "batch-9")):
        propagate_all(store, {"lineitem": _inserted(residue)(lineitem)}, name)
    store.compact()
    for residue, name in ((4, "batch-10"), (5, "a-late-one"), (5, "a-late-one")):
        propagate_all(store, {"lineitem": _inserted(residue)(lineitem)}, name)
    store.compact()
    return _rows(store)


_WIDE_STATE = "WHERE NOT (l_orderkey % 6 < 3 AND l_linenumber = 1)"


@query(w.wide_sql(f"{w.J1_SQL} {_WIDE_STATE}"))
def moments_wide_j1_bulks(spark, sf_dir):
    """1,128 aggregates over the five-relation join, kept as blocks under three bulks of inserts and deletes."""
    spec = w.wide_j1()
    mixed = lambda b: lambda df: as_delta(_residue(2 + b)(df), _residue(b - 1)(df).where("l_linenumber = 1"))
    store = _kept(spark, sf_dir, spec, w.ORDER_FACT, {"lineitem": _residue(0, 2)}, [{"lineitem": mixed(b)} for b in (1, 2, 3)], block.ring_for(spec))
    return store.ring.entries(store.state())


_FACTORED = "(SELECT user_id, value FROM events UNION ALL SELECT c_custkey, CAST(p_size AS DOUBLE) FROM customer, (SELECT DISTINCT p_size FROM part) p WHERE c_nationkey = 3)"


@query(w.moments_sql({"value": "value", "o_totalprice": "o_totalprice"}, f"FROM {_FACTORED} e JOIN orders ON user_id = o_custkey"))
def delta_factored_j2(spark, sf_dir):
    """A bulk of all pairs of some customers and some values, found to be a product and pushed up as its factors."""
    customer, part = tables(spark, sf_dir, "customer", "part")
    users = customer.where("c_nationkey = 3").select(F.col("c_custkey").alias("user_id"))
    values = part.select(F.col("p_size").cast("double").alias("value")).distinct()
    bulk = users.join(F.broadcast(values.groupBy().agg(F.collect_list("value").alias("all")))).select("user_id", F.explode("all").alias("value"), F.lit(1).cast("long").alias("mult"))
    store = _kept(spark, sf_dir, w.j2((w.VALUE, w.PRICE)), "auto", {}, [], updatable=("events",))
    propagate_factored_all(store, {"events": factor_delta(bulk, [["user_id"], ["value"]])}, "grid")
    return _rows(store)


def _toy(spark, sf_dir, kinds, ring):
    r, s, new, old = w.toy_relations(*tables(spark, sf_dir, "orders", "events"))
    spec = w.toy_spec(kinds)
    store = ViewStore(spark, build_view_tree(spec), ring(spec), updatable=("R",)).initialise({"R": r, "S": s})
    propagate_all(store, {"R": as_delta(new, old)}, "1")
    return store


@query(w.toy_sql("SELECT CAST(COUNT(*) AS BIGINT) AS c FROM t"))
def toy_count(spark, sf_dir):
    """The worked example after its bulk: multiplicities."""
    return _toy(spark, sf_dir, {}, CountRing).state().df


@query(w.toy_sql("SELECT '1' AS attr_u, '1' AS attr_v, CAST(COUNT(*) AS DOUBLE) AS value FROM t UNION ALL SELECT '1', 'b', SUM(b) FROM t UNION ALL SELECT '1', 'd', SUM(d) FROM t UNION ALL SELECT 'b', 'b', SUM(b * b) FROM t UNION ALL SELECT 'b', 'd', SUM(b * d) FROM t UNION ALL SELECT 'd', 'd', SUM(d * d) FROM t"))
def toy_moments(spark, sf_dir):
    """The worked example with continuous attributes."""
    return _rows(_toy(spark, sf_dir, {"b": "cont", "d": "cont"}, w.decimal_ring))


_NULL = "CAST(NULL AS VARCHAR)"


@query(w.toy_sql(f"SELECT '1' AS attr_u, {_NULL} AS cat_u, '1' AS attr_v, {_NULL} AS cat_v, CAST(COUNT(*) AS DOUBLE) AS value FROM t UNION ALL SELECT '1', {_NULL}, 'b', {_NULL}, SUM(b) FROM t UNION ALL SELECT '1', {_NULL}, 'd', {_NULL}, SUM(d) FROM t UNION ALL SELECT '1', {_NULL}, 'cc', cc, COUNT(*) FROM t GROUP BY cc UNION ALL SELECT 'b', {_NULL}, 'b', {_NULL}, SUM(b * b) FROM t UNION ALL SELECT 'b', {_NULL}, 'd', {_NULL}, SUM(b * d) FROM t UNION ALL SELECT 'd', {_NULL}, 'd', {_NULL}, SUM(d * d) FROM t UNION ALL SELECT 'b', {_NULL}, 'cc', cc, SUM(b) FROM t GROUP BY cc UNION ALL SELECT 'cc', cc, 'd', {_NULL}, SUM(d) FROM t GROUP BY cc UNION ALL SELECT 'cc', cc, 'cc', cc, COUNT(*) FROM t GROUP BY cc"))
def toy_mixed(spark, sf_dir):
    """The worked example with one categorical attribute: entries are little relations."""
    store = _toy(spark, sf_dir, {"b": "cont", "cc": CAT, "d": "cont"}, lambda s: SparseMomentRing(s, "decimal"))
    return w.entry_rows(store.ring, store.ring.live(store.state())).drop("n")


@query(w.mi_sql({"b": "b", "cc": "cc", "d": "d"}, "FROM t").replace("WITH ", w.toy_sql("").rstrip() + ", ", 1))
def toy_mi(spark, sf_dir):
    """The worked example with categorical attributes only, as mutual information."""
    store = _toy(spark, sf_dir, {"b": CAT, "cc": CAT, "d": CAT}, SparseMomentRing)
    return digits(information.mutual_information(store.ring.live(store.state())), "mi", 8)


@query("SELECT o_orderkey, o_custkey, CAST(1 AS BIGINT) AS mult FROM orders WHERE o_orderkey % 5 = 1 AND o_orderkey % 3 <> 0")
def consolidate_delta(spark, sf_dir):
    """Inserts and deletes of the same rows cancel before they reach a view."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    some = orders.where("o_orderkey % 5 = 1")
    return consolidate(as_delta(some, some.where("o_orderkey % 3 = 0")))


@query("SELECT CAST(COUNT(*) AS BIGINT) AS n, CAST(SUM(r_regionkey * n_nationkey) AS BIGINT) AS v FROM region, nation")
def factor_delta_product(spark, sf_dir):
    """A bulk of all combinations of some values is found to be a product and kept as its factors."""
    r, n = table(spark, sf_dir, "region").select("r_regionkey"), table(spark, sf_dir, "nation").select("n_nationkey")
    bulk = r.withColumn("k", F.lit(1)).join(n.withColumn("k", F.lit(1)), "k").select("r_regionkey", "n_nationkey", F.lit(1).cast("long").alias("mult"))
    a, b = factor_delta(bulk, [["r_regionkey"], ["n_nationkey"]])
    sums = a.agg(F.sum("mult").alias("na"), F.sum(F.col("mult") * F.col("r_regionkey")).alias("sa"), F.lit(1).alias("k")).join(b.agg(F.sum("mult").alias("nb"), F.sum(F.col("mult") * F.col("n_nationkey")).alias("sb"), F.lit(1).alias("k")), "k")
    return sums.select((F.col("na") * F.col("nb")).alias("n"), (F.col("sa") * F.col("sb")).alias("v"))


# Baselines


@query(w.moments_sql(_CONT2_SQL, w.J1_SQL))
def recompute_j1(spark, sf_dir):
    spec = w.j1(_CONT2)
    _, data = w.opened(spark, sf_dir, spec)
    ring = w.decimal_ring(spec)
    return w.entry_rows(ring, baselines.recompute(spec, data, ring))


@query(w.moments_sql(_CONT2_SQL, w.J1_SQL))
def first_order_j1(spark, sf_dir):
    """Old root plus one delta query over base tables."""
    spec = w.j1(_CONT2)
    _, data = w.opened(spark, sf_dir, spec)
    ring = w.decimal_ring(spec)
    before = {**data, "lineitem": _residue(0, 4)(data["lineitem"])}
    change = baselines.first_order_delta(spec, before, "lineitem", _inserted(5)(data["lineitem"]), ring)
    return w.entry_rows(ring, ring.state(ring.union([baselines.recompute(spec, before, ring), change]), ()))


@query(w.moments_sql({"value": "value", "l_quantity": "l_quantity"}, f"{w.J3_SQL} WHERE {_EVENTS_STATE}"))
def join_maintained_j3(spark, sf_dir):
    """The join itself kept under the same bulks as delta_mixed_j3."""
    spec = w.j3((w.VALUE, Attribute("l_quantity", "lineitem")))
    _, data = w.opened(spark, sf_dir, spec)
    kept = baselines.JoinMaintainer(spec, {**data, "events": _first_half(data["events"])})
    for b in (1, 2, 3):
        kept.apply("events", _events_bulk(b)(data["events"]))
    ring = w.decimal_ring(spec)
    return w.entry_rows(ring, kept.moments(ring))


@query(w.moments_sql({"value": "value", "o_totalprice": "o_totalprice"}, w.J2_SQL))
def per_aggregate_j2(spark, sf_dir):
    """Each aggregate by a tree of its own."""
    spec = w.j2((w.VALUE, w.PRICE))
    tree, data = w.opened(spark, sf_dir, spec)
    return baselines.per_aggregate(spec, tree, data).withColumn("value", F.col("value").cast("double"))


@query(w.moments_sql(_CONT2_SQL, w.J1_SQL))
def tree_from_scratch_j1(spark, sf_dir):
    spec = w.j1(_CONT2)
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    ring = w.decimal_ring(spec)
    return w.entry_rows(ring, baselines.evaluate_from_scratch(tree, data, ring))


@query(f"""WITH j AS (SELECT o_orderpriority AS p, CAST(value AS DECIMAL(12,2)) AS x {w.J2_SQL}) SELECT '1' AS attr_u, 'o_orderpriority=' || p AS attr_v, CAST(COUNT(*) AS DOUBLE) AS value FROM j GROUP BY p
UNION ALL SELECT 'o_orderpriority=' || p, 'value', CAST(SUM(x) AS DOUBLE) FROM j GROUP BY p""")
def one_hot_moments(spark, sf_dir):
    """Explicit indicator columns; the cells that compact entries hold too."""
    spec = w.j2((w.VALUE, w.PRIORITY))
    _, data = w.opened(spark, sf_dir, spec)
    e = baselines.one_hot_moments(spec, data).withColumn("value", F.col("value").cast("double"))
    return e.where("(attr_u = '1' and attr_v like 'o_orderpriority=%') or (attr_u like 'o_orderpriority=%' and attr_v = 'value')")


@query("SELECT CAST(COUNT(*) AS BIGINT) AS n, CAST(SUM(o_orderkey) AS BIGINT) AS keys FROM orders WHERE o_orderkey % 6 <= 3 AND o_orderkey % 6 <> 0")
def anti_join_apply(spark, sf_dir):
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    pick = lambda lo, hi: orders.where(F.col("o_orderkey") % 6 >= lo).where(F.col("o_orderkey") % 6 <= hi)
    out = baselines.apply_with_anti_join(pick(0, 2), pick(3, 3), pick(0, 0), ["o_orderkey"])
    return out.agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("keys"))


def _online_sql() -> str:
    ctes = [f"j AS (SELECT event_id % 5 AS r, CAST(o_totalprice AS DOUBLE) AS x, CAST(value AS DOUBLE) AS y {w.J2_SQL})", "z AS (SELECT avg(x) AS mx, stddev_samp(x) AS dx, avg(y) AS my, stddev_samp(y) AS dy FROM j)"]
    ctes += ["b AS (SELECT r, avg((x - mx) / dx) AS u, avg((y - my) / dy) AS v, avg(power((x - mx) / dx, 2)) AS uu, avg((x - mx) / dx * (y - my) / dy) AS uv FROM j, z GROUP BY r)", "t0 AS (SELECT 0.0 AS a, 0.0 AS c)"]
    ctes += [f"t{r + 1} AS (SELECT a - 0.05 * (a + c * u - v) AS a, c - 0.05 * (a * u + c * uu - uv) AS c FROM t{r}, b WHERE r = {r})" for r in range(5)]
    return f"WITH {', '.join(ctes)} SELECT '1' AS attr, round(a, 6) + 0.0 AS theta FROM t5 UNION ALL SELECT 'o_totalprice', round(c, 6) + 0.0 FROM t5"


@query(_online_sql())
def online_learner(spark, sf_dir):
    """Gradient steps on arriving joined rows: what can't take deletes back."""
    spec = w.j2((w.VALUE, w.PRICE))
    _, data = w.opened(spark, sf_dir, spec)
    flat = baselines.joined_rows(spec, data)
    s = flat.agg(F.avg("o_totalprice"), F.stddev("o_totalprice"), F.avg("value"), F.stddev("value")).first()
    theta = baselines.online_sgd([baselines.joined_rows(spec, {**data, "events": data["events"].where(F.col("event_id") % 5 == r)}) for r in range(5)], ["o_totalprice"], "value", scale={"o_totalprice": (s[0], s[1]), "value": (s[2], s[3])})
    return digits(spark.createDataFrame(list(theta.items()), "attr string, theta double"), "theta", 6)


# Listings, factorised results, matrices


@query(f"SELECT r_name, c_mktsegment, o_orderpriority, CAST(COUNT(*) AS BIGINT) AS mult {w.J1_SQL} GROUP BY r_name, c_mktsegment, o_orderpriority")
def listing_j1(spark, sf_dir):
    spec = w.j1((), ("r_name", "c_mktsegment", "o_orderpriority"))
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    return evaluate(tree, data, ListingRing(spec, ("r_name", "c_mktsegment", "o_orderpriority"))).df


@query(f"SELECT CAST(COUNT(*) AS BIGINT) AS flat {w.J3_SQL}")
def factorised_count_j3(spark, sf_dir):
    """Rows of the join by counting over the tree that also keeps it factorised."""
    spec = w.j3(())
    tree, data = w.opened(spark, sf_dir, spec)
    return factorised.result_count(tree, data).select(F.col("c").alias("flat"))


@query(f"SELECT CAST(SUM(value * 100) AS BIGINT) AS v, CAST(COUNT(*) AS BIGINT) AS n FROM (SELECT CAST(value AS DECIMAL(12,2)) AS value {w.J2_SQL})")
def enumerate_j2(spark, sf_dir):
    """All result rows read from the factorised views."""
    spec = w.j2((w.VALUE, w.PRIORITY))
    tree, data = w.opened(spark, sf_dir, spec)
    rows = factorised.enumerate_result(tree, data, ("value", "o_orderpriority"))
    return rows.agg(F.sum(F.col("value").cast("decimal(12,2)") * 100 * F.col("mult")).cast("long").alias("v"), F.sum("mult").alias("n"))


@query(f"SELECT r_name, c_mktsegment, CAST(COUNT(*) AS BIGINT) AS n {w.J1_SQL} GROUP BY r_name, c_mktsegment")
def enumerate_j1(spark, sf_dir):
    spec = w.j1((), ("r_name", "c_mktsegment"))
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    return factorised.enumerate_result(tree, data, ("r_name", "c_mktsegment")).groupBy("r_name", "c_mktsegment").agg(F.sum("mult").alias("n"))


@query(f"""SELECT (SELECT CAST(COUNT(*) AS BIGINT) FROM (SELECT DISTINCT user_id FROM events) e WHERE user_id IN (SELECT o_custkey FROM orders)) AS event_rows, (SELECT CAST(COUNT(*) AS BIGINT) FROM (SELECT DISTINCT o_custkey, o_orderkey FROM orders) o WHERE o_custkey IN (SELECT user_id FROM events) AND o_orderkey IN (SELECT l_orderkey FROM lineitem)) AS order_rows""")
def factorised_rows_j3(spark, sf_dir):
    """Sizes of two of the factors, after reduction."""
    spec = w.j3(())
    tree, data = w.opened(spark, sf_dir, spec)
    views = factorised.factorised_views(tree, data, ())
    e = views["events"].agg(F.count("*").alias("event_rows"), F.lit(1).alias("k"))
    return e.join(views["orders"].agg(F.count("*").alias("order_rows"), F.lit(1).alias("k")), "k").drop("k")


@query("""WITH p AS (SELECT DISTINCT o_custkey, o_orderkey FROM orders JOIN customer ON o_custkey = c_custkey JOIN lineitem ON o_orderkey = l_orderkey WHERE c_custkey % 3 = 0 AND l_partkey % 5 = 0)
SELECT (SELECT CAST(COUNT(DISTINCT o_custkey) AS BIGINT) FROM p) AS customer_rows, (SELECT CAST(COUNT(*) AS BIGINT) FROM p) AS order_rows, (SELECT CAST(COUNT(DISTINCT o_orderkey) AS BIGINT) FROM p) AS line_rows""")
def factorised_dangling(spark, sf_dir):
    """A chain with the middle table named first, most of whose tuples join with nothing on one side."""
    spec = QuerySpec({"orders": "orders", "customer": "customer", "lineitem": "lineitem"}, (("customer.c_custkey", "orders.o_custkey"), ("orders.o_orderkey", "lineitem.l_orderkey")), where={"customer": "c_custkey % 3 = 0", "lineitem": "l_partkey % 5 = 0"})
    tree, data = w.opened(spark, sf_dir, spec)
    views = factorised.factorised_views(tree, data, ())
    count = lambda a, c: views[a].agg(F.count("*").alias(c), F.lit(1).alias("k"))
    return count("customer", "customer_rows").join(count("orders", "order_rows"), "k").join(count("lineitem", "line_rows"), "k").drop("k")


def _chain(spark, sf_dir):
    orders, customer, nation = tables(spark, sf_dir, "orders", "customer", "nation")
    a = orders.groupBy(F.year("o_orderdate").alias("i"), F.col("o_custkey").alias("j")).agg(F.count("*").alias("v"))
    b = customer.select(F.col("c_custkey").alias("i"), F.col("c_nationkey").alias("j"), F.lit(1).cast("long").alias("v"))
    c = nation.select(F.col("n_nationkey").alias("i"), F.col("n_regionkey").alias("j"), F.lit(1).cast("long").alias("v"))
    return [a, b, c]


_CHAIN = "SELECT CAST(year(o_orderdate) AS INTEGER) AS i, n_regionkey AS j, CAST(COUNT(*) AS BIGINT) AS v FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2"


@query(_CHAIN)
def matrix_chain_cnr(spark, sf_dir):
    return matrix.matrix_chain(_chain(spark, sf_dir), [7, 1500, 25, 5])


@query("SELECT i, j, CAST(SUM(v) AS BIGINT) AS v FROM (" + _CHAIN + " UNION ALL SELECT CAST(1992 AS INTEGER) AS i, n_regionkey, CAST(COUNT(*) * 3 AS BIGINT) FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE c_custkey % 10 = 0 GROUP BY n_regionkey) GROUP BY i, j")
def matrix_chain_delta(spark, sf_dir):
    """A rank-one change of the first factor, pushed through as two vectors."""
    chain = _chain(spark, sf_dir)
    u = spark.createDataFrame([(1992, 3)], "i int, v long")
    v = table(spark, sf_dir, "customer").where("c_custkey % 10 = 0").select(F.col("c_custkey").alias("j"), F.lit(1).cast("long").alias("v"))
    x, y = matrix.matrix_chain_rank_one(chain, 0, u, v)
    return matrix.added(matrix.matrix_chain(chain), matrix.rank_one(x, y))


# Further learners


@query("""WITH j AS (SELECT least(CAST(floor(n_chars / 500.0) AS BIGINT), 20) AS b, quality AS y FROM documents d JOIN labels l ON d.doc_id = l.doc_id), n AS (SELECT CAST(COUNT(*) AS DOUBLE) AS n FROM j),
c AS (SELECT DISTINCT b AS cut FROM j), s AS (SELECT cut, y, b <= cut AS side FROM j, c), p AS (SELECT cut, y, side, CAST(COUNT(*) AS DOUBLE) AS cxy FROM s GROUP BY cut, y, side),
x AS (SELECT cut, side, SUM(cxy) AS cx FROM p GROUP BY cut, side), y AS (SELECT cut, y, SUM(cxy) AS cy FROM p GROUP BY cut, y)
SELECT p.cut, round(SUM(cxy / n * ln(n * cxy / (cx * cy))), 8) + 0.0 AS gain FROM p JOIN x ON p.cut = x.cut AND p.side = x.side JOIN y ON p.cut = y.cut AND p.y = y.y, n WHERE p.cut < (SELECT MAX(b) FROM j) GROUP BY p.cut""")
def split_gain_quality(spark, sf_dir):
    docs, labels = tables(spark, sf_dir, "documents", "labels")
    flat = docs.join(labels, "doc_id").select("quality", bin_width(F.col("n_chars"), 0.0, 500.0, 20).alias("b"))
    return digits(information.split_gain(flat, "quality", "b"), "gain", 8)


@query("""WITH j AS (SELECT label AS x, list_position(embedding[1:10], list_max(embedding[1:10])) AS y FROM embeddings), n AS (SELECT CAST(COUNT(*) AS DOUBLE) AS n FROM j),
p AS (SELECT x, y, CAST(COUNT(*) AS DOUBLE) AS cxy FROM j GROUP BY x, y), a AS (SELECT x, SUM(cxy) AS cx FROM p GROUP BY x), b AS (SELECT y, SUM(cxy) AS cy FROM p GROUP BY y)
SELECT round(SUM(cxy / n * ln(n * cxy / (cx * cy))), 8) + 0.0 AS mi, round(SUM(cxy / n * ln(n * cxy / (cx * cy))) / sqrt((SELECT -SUM(cx / n * ln(cx / n)) FROM a, n) * (SELECT -SUM(cy / n * ln(cy / n)) FROM b, n)), 8) + 0.0 AS normalised FROM p JOIN a USING (x) JOIN b USING (y), n""")
def clustering_similarity(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings")
    first = F.slice("embedding", 1, 10)
    out = information.clustering_similarity(e.select("label", F.array_position(first, F.array_max(first)).alias("other")), "label", "other")
    return digits(digits(out, "mi", 8), "normalised", 8)


@query()
def stepwise_forward(spark, sf_dir):
    """Features added while AIC falls, by solving blocks of the moment matrix."""
    spec = w.j1(("l_quantity", "l_discount", "l_tax", "o_totalprice", "c_acctbal", "l_extendedprice"), label="l_extendedprice")
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    ring = w.decimal_ring(spec)
    m = ridge.collected(ring, evaluate(tree, data, ring), [a.name for a in spec.attributes if a.name != "l_extendedprice"], "l_extendedprice")
    steps = [("forward", *s) for s in learners.stepwise(m)] + [("backward", *s) for s in learners.stepwise(m, "backward")]
    return digits(digits(spark.createDataFrame(steps, "direction string, step int, attr string, mse double, aic double"), "mse", 3), "aic", 3)


def _degree4():
    return w.j2((Attribute("v", "events", expr="value / 100"), Attribute("p", "orders", expr="o_totalprice / 100000")))


def _degree4_sql() -> str:
    parts = []
    for d in range(5):
        for a in range(d, -1, -1):
            term = "*".join(["p"] * a + ["v"] * (d - a)) or "1"
            parts.append(f"SELECT '{term}' AS term, round(AVG({' * '.join(['p'] * a + ['v'] * (d - a)) or '1.0'}), 6) + 0.0 AS mean FROM j")
    return f"WITH j AS (SELECT value / 100 AS v, o_totalprice / 100000 AS p {w.J2_SQL}) " + " UNION ALL ".join(parts)


@query(_degree4_sql())
def poly_moments_degree4(spark, sf_dir):
    """Means of all monomials up to degree 4 across two tables."""
    spec = _degree4()
    tree, data = w.opened(spark, sf_dir, spec)
    v = evaluate(tree, data, SparseMomentRing(spec, "double", 4)).df
    n = v.where("size(term) = 0").select(F.col("v").alias("total"), F.lit(1).alias("k"))
    name = F.when(F.size("term") == 0, "1").otherwise(F.array_join(F.transform("term", lambda f: f["a"]), "*"))
    return digits(v.withColumn("k", F.lit(1)).join(n, "k").select(name.alias("term"), (F.col("v") / F.col("total")).alias("mean")), "mean", 6)


@query()
def factorisation_machine(spark, sf_dir):
    """Losses of a rank-1 machine fitted on moments of degree 4; they only fall."""
    spec = w.j3((Attribute("v", "events", expr="value / 100"), Attribute("p", "orders", expr="o_totalprice / 100000"), Attribute("q", "lineitem", expr="l_quantity / 10")))
    tree, data = w.opened(spark, sf_dir, spec)
    terms = learners.term_values(evaluate(tree, data, SparseMomentRing(spec, "double", 4)).df.select("term", "v").collect())
    *_, losses = learners.fm_fit(terms, ["p", "q"], "v", 1, 50)
    return spark.createDataFrame([(i, round(float(x), 8)) for i, x in enumerate(losses)], "step int, loss double")


# Strategy and session


_DIMENSIONS = {
    "at_n_regionkey": "SELECT DISTINCT n_nationkey FROM nation JOIN region ON n_regionkey = r_regionkey", "at_c_nationkey": "SELECT DISTINCT c_custkey FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
    "leaf_lineitem": "SELECT DISTINCT l_orderkey FROM lineitem", "leaf_customer": "SELECT DISTINCT c_custkey, c_nationkey FROM customer", "leaf_nation": "SELECT DISTINCT n_nationkey, n_regionkey FROM nation", "leaf_region": "SELECT DISTINCT r_regionkey FROM region",
}


def _orders_sql(where: str = "") -> dict[str, str]:
    return {
        "leaf_orders": f"SELECT DISTINCT o_orderkey, o_custkey FROM orders {where}", "at_l_orderkey": f"SELECT DISTINCT 1 {w.J1_SQL} {where}",
        "at_o_custkey": f"SELECT DISTINCT o_orderkey FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey {where}",
    }


def _keys_sql(strategy: str, views: dict[str, str]) -> str:
    counts = " UNION ALL ".join(f"SELECT '{v}' AS view, CAST(COUNT(*) AS BIGINT) AS n_keys FROM ({q}) x" for v, q in views.items())
    return f"SELECT t.*, n_keys FROM ({strategy}) t JOIN ({counts}) n ON t.view = n.view"


@query(_keys_sql("""SELECT * FROM (VALUES ('leaf_lineitem', 'at_l_orderkey', 'l_orderkey', CAST(NULL AS VARCHAR), 'l_quantity', true), ('leaf_orders', 'at_o_custkey', 'l_orderkey,o_custkey', NULL, 'o_totalprice', false), ('leaf_customer', 'at_c_nationkey', 'o_custkey,c_nationkey', NULL, '', false),
('leaf_nation', 'at_n_regionkey', 'c_nationkey,n_regionkey', NULL, '', false), ('leaf_region', 'at_n_regionkey', 'n_regionkey', NULL, '', false), ('at_n_regionkey', 'at_c_nationkey', 'c_nationkey', 'n_regionkey', '', false), ('at_c_nationkey', 'at_o_custkey', 'o_custkey', 'c_nationkey', '', true),
('at_o_custkey', 'at_l_orderkey', 'l_orderkey', 'o_custkey', 'o_totalprice', true), ('at_l_orderkey', NULL, '', 'l_orderkey', 'l_quantity,o_totalprice', true)) AS t(view, parent, keys, summed_out, attributes, kept)""", _DIMENSIONS | _orders_sql()))
def strategy_j1(spark, sf_dir):
    """The views of the five-relation join if line items and orders change, which of them are kept, and their numbers of keys."""
    tree, data = w.opened(spark, sf_dir, w.j1(("l_quantity", "o_totalprice")), w.ORDER_FACT)
    return explain.explain_tree(spark, tree, ("lineitem", "orders"), "moments").drop("sql").join(explain.view_keys(tree, data, tree.nodes()), "view")


@query(_keys_sql("SELECT * FROM (VALUES (CAST(1 AS INTEGER), 'leaf_orders', '', 'l_orderkey,o_custkey'), (2, 'at_o_custkey', 'at_c_nationkey', 'l_orderkey'), (3, 'at_l_orderkey', 'leaf_lineitem', '')) AS t(step, view, siblings, keys)", _orders_sql("WHERE o_orderkey % 6 = 5")))
def strategy_delta_orders(spark, sf_dir):
    """The views that an update of orders passes, and how many keys a bulk of a sixth of the orders changes in each."""
    tree, data = w.opened(spark, sf_dir, w.j1(("l_quantity", "o_totalprice")), w.ORDER_FACT)
    changed = explain.view_keys(tree, {**data, "orders": _residue(5, key="o_orderkey")(data["orders"])}, tree.path("orders"))
    return explain.explain_delta(spark, tree, "orders").drop("sql").join(changed, "view")


def _emitted(entries: DataFrame) -> DataFrame:
    """Rows of emitted SQL as entries; the diagonal of categories is implied there."""
    one = lambda c: F.when(F.col(c) == "", "1").otherwise(F.col(c))
    flip = F.col("a2") == ""
    u, v = F.when(flip, F.lit("1")).otherwise(F.col("a1")), F.when(flip, one("a1")).otherwise(F.col("a2"))
    return entries.select(u.alias("attr_u"), F.when(~flip, F.col("k1")).alias("cat_u"), v.alias("attr_v"), F.when(flip, F.col("k1")).otherwise(F.col("k2")).alias("cat_v"), F.when(F.abs("v") > 1e9, F.round(F.col("v") / 1e6, 2)).otherwise(F.round(F.col("v"), 1)).alias("value"))


_MIXED_ROUNDED = "WITH e AS ({}) SELECT attr_u, cat_u, attr_v, cat_v, CASE WHEN abs(value) > 1e9 THEN round(value / 1e6, 2) ELSE round(value, 1) END AS value FROM e WHERE NOT (attr_u = attr_v AND cat_u IS NOT NULL)"


@query(_MIXED_ROUNDED.format(_mixed_sql()))
def strategy_mixed_sql(spark, sf_dir):
    """The emitted SQL of payloads with categories, run as it stands."""
    tree, data = w.opened(spark, sf_dir, _mixed(), w.ORDER_FACT)
    return _emitted(explain.run_sql(spark, tree, data, "mixed"))


@query(_MIXED_ROUNDED.format(_mixed_sql()))
def strategy_delta_sql(spark, sf_dir):
    """The emitted SQL of a bulk's path, run over kept views: the old root and its change, summed."""
    spec = _mixed()
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    mark = uuid.uuid4().hex[:8]
    old = {**data, "orders": _residue(0, 4, "o_orderkey")(data["orders"])}
    named = {n.name: f"{n.name}_{mark}" for n in tree.nodes()}
    for n in tree.nodes():
        source = None
        if n.alias is not None:
            source = f"t_{n.alias}_{mark}"
            old[n.alias].withColumn("mult", F.lit(1)).createOrReplaceTempView(source)
        spark.sql(explain.view_sql(tree, n, "mixed", named, source)).createOrReplaceTempView(named[n.name])
    _residue(5, key="o_orderkey")(data["orders"]).withColumn("mult", F.lit(1)).createOrReplaceTempView(f"d_orders_{mark}")
    below = None
    for n in tree.path("orders"):
        names = {**named, **({below.name: f"d_{named[below.name]}"} if below else {})}
        spark.sql(explain.view_sql(tree, n, "mixed", names, None if below else f"d_orders_{mark}")).createOrReplaceTempView(f"d_{named[n.name]}")
        below = n
    both = spark.table(named[tree.root.name]).unionByName(spark.table(f"d_{named[tree.root.name]}"))
    return _emitted(both.groupBy("a1", "k1", "a2", "k2").agg(F.sum("v").alias("v")))


@query(f"SELECT CAST(COUNT(*) AS BIGINT) AS c, round(SUM(l_quantity), 2) + 0.0 AS s_l_quantity {w.J1_SQL}")
def strategy_sql_runs(spark, sf_dir):
    """The emitted SQL, run as it stands."""
    spec = w.j1(("l_quantity", "o_totalprice"))
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    return digits(explain.run_sql(spark, tree, data).select("c", "s_l_quantity"), "s_l_quantity", 2)


_PANEL_ATTRS = {a: a for a in ("n_name", "r_name", "c_mktsegment", "l_returnflag")}


def _state_of(b: int) -> str:
    return f"WHERE l_orderkey % 6 <= {2 + b} AND NOT (l_orderkey % 6 < {b} AND l_linenumber = 1)"


def _panels_sql() -> str:
    """One SELECT per bulk; each has its CTEs inside, so that nothing is shared."""
    out = []
    for b in (1, 2):
        ctes, parts = w.mi_parts(_PANEL_ATTRS, f"{w.J1_SQL} {_state_of(b)}")
        tree = _TREE_OF.format(ctes=ctes, parts=parts)
        matrix = f"j AS (SELECT [1.0, CAST(l_quantity AS DOUBLE), CAST(o_totalprice AS DOUBLE), CAST(l_extendedprice AS DOUBLE)] AS v {w.J1_SQL} {_state_of(b)}), matrix AS (SELECT [" + ", ".join("[" + ", ".join(f"avg(v[{i}] * v[{j}])" for j in range(1, 5)) + "]" for i in range(1, 5)) + "] AS m FROM j)"
        bulk = f"CAST({b} AS INTEGER) AS bulk"
        out.append(f"SELECT * FROM ({tree} SELECT {bulk}, 'tree' AS panel, u || '-' || v AS item, round(mi, 8) + 0.0 AS value FROM t)")
        out.append(f"SELECT * FROM (WITH {ctes}, mi AS ({parts}) SELECT {bulk}, 'selection' AS panel, CASE WHEN attr_u = 'r_name' THEN attr_v ELSE attr_u END || CASE WHEN mi > 0.5 THEN ' +' ELSE '' END AS item, round(mi, 8) + 0.0 AS value FROM mi WHERE (attr_u = 'r_name') <> (attr_v = 'r_name'))")
        out.append(f"SELECT * FROM (WITH RECURSIVE {w.solved_sql(matrix, 1e-3)} SELECT {bulk}, 'regression' AS panel, CASE i WHEN 1 THEN '1' WHEN 2 THEN 'l_quantity' ELSE 'o_totalprice' END AS item, round(theta, CASE i WHEN 1 THEN 3 WHEN 2 THEN 5 ELSE 8 END) + 0.0 AS value FROM theta)")
        out.append(f"SELECT {bulk}, 'updates' AS panel, 'rows' AS item, CAST(COUNT(*) AS DOUBLE) AS value FROM lineitem WHERE l_orderkey % 6 = {2 + b} OR (l_orderkey % 6 = {b - 1} AND l_linenumber = 1)")
    return " UNION ALL ".join(out)


@query(_panels_sql())
def session_panels(spark, sf_dir):
    """An interactive session over two bulks: what the panels show after each. Selection (attributes above the threshold have
    a +), regression, tree, and the number of updates."""
    spec = w.j1(("l_quantity", "o_totalprice", "l_extendedprice"), label="l_extendedprice")
    counts = w.j1((), tuple(_PANEL_ATTRS))
    s = LiveSession(spark, spec, w.decimal_ring(spec), counts, JointMomentRing(counts), w.ORDER_FACT, ("lineitem",))
    _, data = w.opened(spark, sf_dir, spec)
    initial, bulks = feeds.lineitem_bulks(data["lineitem"], bulks=2, deletes=True)
    s.start({**data, "lineitem": initial})
    rows = []
    for i, b in enumerate(bulks, 1):
        s.apply_bulk({"lineitem": b}, f"{i:03d}")
        panels = s.panels("r_name", 0.5, ["l_quantity", "o_totalprice"], "l_extendedprice", 1e-3, tol=1e-13)
        rows += [(i, "selection", r["attr"] + (" +" if r["selected"] else ""), round(r["mi"], 8) + 0.0) for r in panels["selection"]]
        rows += [(i, "tree", "-".join(sorted((r["parent"], r["child"]))), round(r["mi"], 8) + 0.0) for r in panels["tree"]]
        shown = {"1": 3, "l_quantity": 5, "o_totalprice": 8}
        rows += [(i, "regression", a, round(t, shown[a]) + 0.0) for (a, _), t in panels["regression"].theta.items()]
        rows.append((i, "updates", "rows", float(s.log.rows[-1]["updates"])))
    return spark.createDataFrame(rows, "bulk int, panel string, item string, value double")


_TREE_ATTRS = {"l_returnflag": "l_returnflag", "l_linestatus": "l_linestatus", "o_orderpriority": "o_orderpriority", "c_mktsegment": "c_mktsegment", "r_name": "r_name", "p_brand": "p_brand", "p_type": "p_type", "size_bin": "CAST(floor(p_size / 10.0) AS BIGINT)", "quantity_bin": "CAST(floor(l_quantity / 5.0) AS BIGINT)", "discount_bin": "CAST(round(l_discount * 100) AS BIGINT)"}


def _tree_spec():
    owner = {**w.OWNER, "p": "part", "s": "part", "q": "lineitem", "d": "lineitem"}
    attributes = tuple(Attribute(a, owner[a[0]], CAT, e) for a, e in _TREE_ATTRS.items())
    return QuerySpec({**w.J1_TABLES, "part": "part"}, (*w.J1_JOINS, ("lineitem.l_partkey", "part.p_partkey")), attributes)


def _tree_bulks_sql() -> str:
    states = []
    for b in range(4):
        ctes, parts = w.mi_parts(_TREE_ATTRS, f"{w.J1_SQL} JOIN part ON l_partkey = p_partkey {_state_of(b)}")
        states.append(f"e{b} AS (SELECT * FROM ({_TREE_OF.format(ctes=ctes, parts=parts)} SELECT u, v, mi FROM t))")
    rows = ["SELECT CAST(0 AS INTEGER) AS bulk, u, v, round(mi, 8) + 0.0 AS mi, 'came' AS change FROM e0"]
    for b in range(1, 4):
        rows.append(f"SELECT CAST({b} AS INTEGER), coalesce(y.u, x.u), coalesce(y.v, x.v), round(y.mi, 8) + 0.0, CASE WHEN x.u IS NULL THEN 'came' WHEN y.u IS NULL THEN 'went' ELSE 'stayed' END FROM e{b - 1} x FULL JOIN e{b} y ON x.u = y.u AND x.v = y.v")
    return f"WITH {', '.join(states)} " + " UNION ALL ".join(rows)


@query(_tree_bulks_sql())
def tree_per_bulk(spark, sf_dir):
    """Ten attributes of six tables, three of them in bins: the tree after the load and after each bulk of inserts and deletes, and
    which edges came, stayed and went."""
    spec = _tree_spec()
    data = {a: table(spark, sf_dir, a) for a in spec.tables}
    spec.validate(data)
    initial, bulks = feeds.lineitem_bulks(data["lineitem"], deletes=True)
    store = ViewStore(spark, build_view_tree(spec, ("l_orderkey", "o_custkey", "c_nationkey", "n_regionkey", "l_partkey")), LateMomentRing(spec, ("l_orderkey",)), updatable=("lineitem",)).initialise({**data, "lineitem": initial})
    out = before = None
    for b in range(4):
        if b:
            propagate_all(store, {"lineitem": bulks[b - 1]}, f"{b:03d}")
        now = deptree.dependency_tree(information.mutual_information(store.ring.live(store.state())))
        edges = now.select(F.least("parent", "child").alias("u"), F.greatest("parent", "child").alias("v"), "mi")
        if before is None:
            one = edges.withColumn("change", F.lit("came"))
        else:
            gone = deptree.tree_changes(before, now)
            one = edges.withColumn("k", F.lit("stayed")).join(gone, ["u", "v"], "full_outer").select("u", "v", "mi", F.coalesce("change", "k").alias("change"))
        one = one.select(F.lit(b).alias("bulk"), "u", "v", "mi", "change")
        out, before = (one if out is None else out.unionByName(one)), now
    return digits(out, "mi", 8)


def _selected_bulks_sql() -> str:
    rows = []
    for b in range(4):
        ctes, parts = w.mi_parts(_PANEL_ATTRS, f"{w.J1_SQL} {_state_of(b)}")
        rows.append(f"SELECT CAST({b} AS INTEGER) AS bulk, * FROM ({_selected_sql(ctes, parts, 'l_returnflag', 2e-5)})")
    return " UNION ALL ".join(rows)


@query(_selected_bulks_sql())
def selection_per_bulk(spark, sf_dir):
    """The ranking for a label after the load and after each bulk, from the kept counts."""
    spec = w.j1((), tuple(_PANEL_ATTRS))
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    initial, bulks = feeds.lineitem_bulks(data["lineitem"], deletes=True)
    store = ViewStore(spark, tree, JointMomentRing(spec), updatable=("lineitem",)).initialise({**data, "lineitem": initial})
    out = None
    for b in range(4):
        if b:
            propagate_all(store, {"lineitem": bulks[b - 1]}, f"{b:03d}")
        one = selection.select_features(information.mutual_information(store.ring.terms(store.ring.live(store.state()))), "l_returnflag", 2e-5).withColumn("bulk", F.lit(b))
        out = one if out is None else out.unionByName(one)
    return digits(out, "mi", 8)


@query("""WITH a AS (SELECT (SELECT COUNT(*) FROM lineitem) + (SELECT COUNT(*) FROM orders) + (SELECT COUNT(*) FROM events) AS base), j AS (SELECT COUNT(*) AS n FROM events JOIN orders ON user_id = o_custkey JOIN lineitem ON o_orderkey = l_orderkey),
k AS (SELECT COUNT(DISTINCT l_orderkey) AS lines FROM lineitem), m AS (SELECT COUNT(DISTINCT o_custkey) AS met FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem))
SELECT CAST(base AS BIGINT) AS base_rows, CAST(n AS BIGINT) AS join_rows, CAST(lines + met + 1 AS BIGINT) AS view_rows, round(n / base, 6) + 0.0 AS fan_out FROM a, j, k, m""")
def fan_out_sizes(spark, sf_dir):
    """Rows of the tables, of the join, and of the views kept instead for updates of events and orders."""
    spec = w.j3(())
    tree, data = w.opened(spark, sf_dir, spec, tuple(spec.variables()))
    base, n, ratio = metrics.repetition(tree, data)
    store = ViewStore(spark, tree, CountRing(spec), updatable=("events", "orders")).initialise(data)
    sizes = {r["view"]: r["rows"] for r in metrics.view_sizes(store).collect()}
    rows = sum(v for k, v in sizes.items() if k != "leaf_events")
    return spark.createDataFrame([(base, n, rows, round(ratio, 6))], "base_rows long, join_rows long, view_rows long, fan_out double")


@query(f"""WITH {_MIXED_J}, c AS (SELECT 'c_mktsegment' AS a, CAST(COUNT(DISTINCT c_mktsegment) AS BIGINT) AS k FROM j UNION ALL SELECT 'l_returnflag', COUNT(DISTINCT l_returnflag) FROM j UNION ALL SELECT 'r_name', COUNT(DISTINCT r_name) FROM j)
SELECT x.a AS attr_u, y.a AS attr_v, CASE WHEN x.a = y.a THEN x.k ELSE CASE x.a || y.a WHEN 'c_mktsegmentl_returnflag' THEN (SELECT COUNT(*) FROM (SELECT DISTINCT c_mktsegment, l_returnflag FROM j)) WHEN 'c_mktsegmentr_name' THEN (SELECT COUNT(*) FROM (SELECT DISTINCT c_mktsegment, r_name FROM j)) ELSE (SELECT COUNT(*) FROM (SELECT DISTINCT l_returnflag, r_name FROM j)) END END AS live,
CASE WHEN x.a = y.a THEN x.k ELSE x.k * y.k END AS possible FROM c x JOIN c y ON x.a <= y.a""")
def cell_sparsity(spark, sf_dir):
    """Live entries of each categorical cell against the possible ones."""
    e = _mixed_entries(spark, sf_dir)[1].where("(cat_u is not null or attr_u = '1') and (cat_v is not null or attr_v = '1')")
    return metrics.sparsity(e)


def _drift_sql() -> str:
    sides = []
    for b in (0, 3):
        ctes, parts = w.mi_parts(_PANEL_ATTRS, f"{w.J1_SQL} {_state_of(b)}")
        sides.append(f"(SELECT * FROM (WITH {ctes}, mi AS ({parts}) SELECT * FROM mi)) m{b}")
    return f"SELECT m0.attr_u, m0.attr_v, round(m3.mi - m0.mi, 8) + 0.0 AS change FROM {sides[0]} JOIN {sides[1]} ON m0.attr_u = m3.attr_u AND m0.attr_v = m3.attr_v"


@query(_drift_sql())
def mi_drift(spark, sf_dir):
    """How far mutual information moved over three bulks."""
    spec = w.j1((), tuple(_PANEL_ATTRS))
    tree, data = w.opened(spark, sf_dir, spec, w.ORDER_FACT)
    initial, bulks = feeds.lineitem_bulks(data["lineitem"], deletes=True)
    store = ViewStore(spark, tree, JointMomentRing(spec), updatable=("lineitem",)).initialise({**data, "lineitem": initial})
    of = lambda until: information.mutual_information(store.ring.terms(store.ring.live(store.state(until=until))))
    for i, b in enumerate(bulks):
        propagate_all(store, {"lineitem": b}, f"b{i}")
    return digits(metrics.drift(of(0), of(None)), "change", 8)


# Surrounding operators


@query("""WITH s AS (SELECT ts, user_id, CAST(SUM(1) OVER (PARTITION BY user_id ORDER BY event_id) AS BIGINT) AS n FROM events WHERE event_id % 7 = 0)
SELECT e.event_id, coalesce(s.n, 0) AS n FROM events e ASOF LEFT JOIN (SELECT ts, user_id, MAX(n) AS n FROM s GROUP BY ts, user_id) s ON e.user_id = s.user_id AND e.ts >= s.ts WHERE e.event_id % 5 = 0""")
def asof_snapshot(spark, sf_dir):
    """The latest snapshot of a customer's count at or before an event."""
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id")
    n = F.count("*").over(Window.partitionBy("user_id").orderBy("event_id"))
    snaps = events.where("event_id % 7 = 0").withColumn("n", n).groupBy("ts", "user_id").agg(F.max("n").alias("n"))
    return relational.asof_join(events.where("event_id % 5 = 0"), snaps, "ts", ["user_id"], ["n"]).select("event_id", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


@query("""WITH s AS (SELECT ts, user_id, COUNT(*) OVER (PARTITION BY user_id ORDER BY event_id) AS n FROM events)
SELECT e.event_id, CAST(coalesce(s.n, 0) AS BIGINT) AS n FROM events e ASOF LEFT JOIN (SELECT ts, user_id, MAX(n) AS n FROM s GROUP BY ts, user_id) s ON e.user_id = s.user_id AND e.ts >= s.ts""")
def asof_snapshot_all(spark, sf_dir):
    """asof_snapshot with every event as a snapshot and as a probe, time in eight ranges."""
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id")
    n = F.count("*").over(Window.partitionBy("user_id").orderBy("event_id"))
    snaps = events.withColumn("n", n).groupBy("ts", "user_id").agg(F.max("n").alias("n"))
    return relational.asof_join(events, snaps, "ts", ["user_id"], ["n"], 8).select("event_id", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


@query("""WITH b AS (SELECT p_size AS band, MIN(p_retailprice) - 900 AS low, MIN(p_retailprice) - 890 AS high FROM part GROUP BY p_size) SELECT band, CAST(COUNT(*) AS BIGINT) AS n FROM events JOIN b ON value >= low AND value < high GROUP BY band""")
def range_band_join(spark, sf_dir):
    part, events = tables(spark, sf_dir, "part", "events")
    bands = part.groupBy(F.col("p_size").alias("band")).agg((F.min("p_retailprice") - 900).alias("low"), (F.min("p_retailprice") - 890).alias("high"))
    return relational.range_join(events.select("event_id", "value"), "value", bands, "low", "high", 10.0).groupBy("band").agg(F.count("*").alias("n"))


@query("SELECT CAST(COUNT(*) AS BIGINT) AS n FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_orderkey % 60 = 3)")
def semi_affected_keys(spark, sf_dir):
    orders, lineitem = tables(spark, sf_dir, "orders", "lineitem")
    return relational.affected(orders, lineitem.where("l_orderkey % 60 = 3").select(F.col("l_orderkey").alias("o_orderkey")), ["o_orderkey"]).agg(F.count("*").alias("n"))


@query("SELECT CAST(COUNT(*) AS BIGINT) AS n FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def anti_dangling(spark, sf_dir):
    docs, labels = tables(spark, sf_dir, "documents", "labels")
    return relational.dangling(docs, labels, [("doc_id", "doc_id")]).agg(F.count("*").alias("n"))


@query(f"""WITH {_A2_MI[0]}, mi AS ({_A2_MI[1]}) SELECT attr_u, attr_v, CAST(rank() OVER (ORDER BY round(mi, 8) DESC) AS INTEGER) AS rank, CAST(ntile(4) OVER (ORDER BY mi DESC, attr_u, attr_v) AS INTEGER) AS quarter, round(lag(mi) OVER (ORDER BY mi DESC, attr_u, attr_v), 8) + 0.0 AS above FROM mi WHERE attr_u <> attr_v""")
def window_mi_rank(spark, sf_dir):
    mi = _j1_mi(spark, sf_dir).where("attr_u <> attr_v")
    order = Window.orderBy(F.desc("mi"), "attr_u", "attr_v")
    return digits(mi.select("attr_u", "attr_v", F.rank().over(Window.orderBy(F.desc(F.round("mi", 8)))).alias("rank"), F.ntile(4).over(order).alias("quarter"), F.lag("mi").over(order).alias("above")), "above", 8)


@query("""WITH b AS (SELECT CAST(event_id % 10 AS BIGINT) AS bulk, CAST(COUNT(*) AS BIGINT) AS c, SUM(CAST(value AS DECIMAL(12,2))) AS s FROM events GROUP BY 1)
SELECT bulk, CAST(SUM(c) OVER (ORDER BY bulk ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS c, CAST(SUM(s) OVER (ORDER BY bulk ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS DOUBLE) AS s, CAST(SUM(c) OVER (ORDER BY bulk) AS BIGINT) AS c_all FROM b""")
def sliding_bulks(spark, sf_dir):
    """Moments of the last three bulks and of all so far, per bulk."""
    bulks = table(spark, sf_dir, "events").groupBy((F.col("event_id") % 10).alias("bulk")).agg(F.count("*").alias("c"), F.sum(F.col("value").cast("decimal(12,2)")).alias("s"))
    last = relational.sliding_bulks(bulks, "bulk", ["c", "s"], 3)
    return last.join(relational.running(bulks, "bulk", ["c"]).withColumnRenamed("c", "c_all"), "bulk").select("bulk", "c", F.col("s").cast("double").alias("s"), "c_all")


@query(f"WITH {_A2_MI[0]}, mi AS ({_A2_MI[1]}) SELECT attr_u, attr_v, round(mi, 8) + 0.0 AS mi FROM mi WHERE attr_u <> attr_v ORDER BY mi.mi DESC, attr_u, attr_v LIMIT 5")
def top_pairs(spark, sf_dir):
    return digits(relational.top_k(_j1_mi(spark, sf_dir).where("attr_u <> attr_v"), 5, F.desc("mi"), F.asc("attr_u"), F.asc("attr_v")), "mi", 8)


@query("SELECT o_custkey, CAST(SUM(m) AS BIGINT) AS mult FROM (SELECT o_custkey, 1 AS m FROM orders WHERE o_orderkey % 2 = 0 UNION ALL SELECT o_custkey, -1 FROM orders WHERE o_orderkey % 3 = 0) GROUP BY o_custkey HAVING SUM(m) <> 0")
def set_symdiff(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    return relational.symmetric_difference(orders.where("o_orderkey % 2 = 0").select("o_custkey"), orders.where("o_orderkey % 3 = 0").select("o_custkey"))


@query("""SELECT event_type, CAST(COUNT(*) AS BIGINT) AS c, CAST(SUM(k) AS BIGINT) AS s, CAST(SUM(k * k) AS BIGINT) AS q FROM (SELECT event_type, CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS BIGINT) AS k FROM events) GROUP BY event_type""")
def json_props_moments(spark, sf_dir):
    k = F.get_json_object("props", "$.k").cast("long")
    return table(spark, sf_dir, "events").select("event_type", k.alias("k")).groupBy("event_type").agg(F.count("*").alias("c"), F.sum("k").alias("s"), F.sum(F.col("k") * F.col("k")).alias("q"))


@query("SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(quarter(o_orderdate) AS INTEGER) AS q, CAST(COUNT(*) AS BIGINT) AS n, CAST(COUNT(DISTINCT o_custkey) AS BIGINT) AS customers FROM orders GROUP BY 1, 2")
def date_bins(spark, sf_dir):
    return table(spark, sf_dir, "orders").groupBy(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q")).agg(F.count("*").alias("n"), F.countDistinct("o_custkey").alias("customers"))


@query("SELECT lower(lang) AS lang, split_part(url_path, '/', 1) AS first_part, CAST(COUNT(*) AS BIGINT) AS n, CAST(SUM(length(html)) AS BIGINT) AS chars FROM (SELECT regexp_extract(url, 'https?://[^/]+/(.*)', 1) AS url_path, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS lang, html FROM pages) GROUP BY 1, 2")
def string_features(spark, sf_dir):
    pages = table(spark, sf_dir, "pages")
    path = F.regexp_extract("url", "https?://[^/]+/(.*)", 1)
    return pages.groupBy(F.lower(F.regexp_extract("html", '<html lang="([a-z]+)"', 1)).alias("lang"), F.split_part(path, F.lit("/"), F.lit(1)).alias("first_part")).agg(F.count("*").alias("n"), F.sum(F.length("html")).cast("long").alias("chars"))


@query("SELECT l_returnflag, CAST(COUNT(*) AS DOUBLE) AS c, round(SUM(l_quantity), 2) + 0.0 AS s, round(SUM(l_quantity * l_quantity), 2) + 0.0 AS q FROM lineitem GROUP BY l_returnflag")
def array_payload_sum(spark, sf_dir):
    """Payload blocks as arrays, added entry by entry."""
    part = table(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").cast("double").alias("c"), F.sum("l_quantity").alias("s"), F.sum(F.col("l_quantity") * F.col("l_quantity")).alias("q"))
    blocks = part.select("l_returnflag", F.array("c", "s", "q").alias("block")).groupBy("l_returnflag").agg(F.collect_list("block").alias("blocks"))
    total = F.aggregate("blocks", F.array(F.lit(0.0), F.lit(0.0), F.lit(0.0)), added_arrays)
    return digits(digits(blocks.select("l_returnflag", total.alias("t")).select("l_returnflag", F.col("t")[0].alias("c"), F.col("t")[1].alias("s"), F.col("t")[2].alias("q")), "s", 2), "q", 2)


@query("SELECT o_orderpriority AS cat, CAST(SUM(CASE WHEN o_orderkey % 2 = 0 THEN 1 ELSE -1 END) AS BIGINT) AS n FROM orders GROUP BY o_orderpriority HAVING SUM(CASE WHEN o_orderkey % 2 = 0 THEN 1 ELSE -1 END) <> 0")
def map_payload_merge(spark, sf_dir):
    """Category maps merged; what cancels out is gone."""
    orders = table(spark, sf_dir, "orders")
    side = lambda r, s: orders.where(F.col("o_orderkey") % 2 == r).groupBy("o_orderpriority").agg((F.count("*") * s).alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("o_orderpriority", "n"))).alias(f"m{r}"), F.lit(1).alias("k"))
    both = side(0, 1).join(side(1, -1), "k")
    return both.select(F.explode(merged_maps(F.col("m0"), F.col("m1"))).alias("cat", "n"))


@query("SELECT i, j, round(v, 2) + 0.0 AS v FROM (SELECT CAST(0 AS INTEGER) AS i, CAST(0 AS INTEGER) AS j, CAST(COUNT(*) AS DOUBLE) AS v FROM lineitem UNION ALL SELECT 0, 1, SUM(l_quantity) FROM lineitem UNION ALL SELECT 1, 1, SUM(l_quantity * l_quantity) FROM lineitem)")
def udtf_unpack(spark, sf_dir):
    spark.udtf.register("unpack_entries", UnpackEntries)
    table(spark, sf_dir, "lineitem").agg(F.array(F.count("*").cast("double"), F.sum("l_quantity"), F.sum(F.col("l_quantity") * F.col("l_quantity"))).alias("block")).createOrReplaceTempView("packed_moments")
    return digits(spark.sql("SELECT u.i, u.j, u.v FROM packed_moments, LATERAL unpack_entries(block, 2) u"), "v", 2)


@query("SELECT CAST(COUNT(*) AS BIGINT) AS n, CAST(SUM(o_orderkey) AS BIGINT) AS keys FROM events JOIN orders ON user_id = o_custkey")
def salted_join(spark, sf_dir):
    events, orders = tables(spark, sf_dir, "events", "orders")
    out = relational.salted_join(events.select(F.col("user_id").alias("k"), "event_id"), orders.select(F.col("o_custkey").alias("k"), "o_orderkey"), ["k"])
    return out.agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("keys"))


@query("SELECT CAST(b AS BIGINT) AS bin, CAST(COUNT(*) AS BIGINT) AS n FROM (SELECT CASE WHEN value >= 300 THEN 3 WHEN value >= 100 THEN 2 WHEN value >= 50 THEN 1 ELSE 0 END AS b FROM events) GROUP BY b")
def edge_bins(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(bin_edges("value", [50, 100, 300]).alias("bin")).agg(F.count("*").alias("n"))


@query("""WITH h AS (SELECT value FROM events WHERE event_id < (SELECT COUNT(*) * 0.5 FROM events)), e AS (SELECT DISTINCT unnest(quantile_disc(value, [0.125, 0.25, 0.375, 0.5, 0.625, 0.75, 0.875])) AS edge FROM h)
SELECT bin, CAST(COUNT(*) AS BIGINT) AS n FROM (SELECT (SELECT CAST(COUNT(*) AS BIGINT) FROM e WHERE edge <= value) AS bin FROM events) GROUP BY bin""")
def quantile_bins(spark, sf_dir):
    """Edges frozen on the initial half of the events, all events counted by bin."""
    events = table(spark, sf_dir, "events")
    edges = quantile_edges(_first_half(events), "value", 8)
    return events.groupBy(bin_edges("value", edges).alias("bin")).agg(F.count("*").alias("n"))


@query(f"WITH {_A2_MI[0]}, mi AS ({_A2_MI[1]}), m AS (SELECT * FROM mi UNION ALL SELECT attr_v, attr_u, mi FROM mi WHERE attr_u <> attr_v) SELECT attr_u, " + ", ".join(f"round(MAX(CASE WHEN attr_v = '{a}' THEN mi END), 8) + 0.0 AS {a}" for a in sorted(w.A2_CAT)) + " FROM m GROUP BY attr_u")
def pivot_mi(spark, sf_dir):
    wide = relational.pivoted(information.symmetric(_j1_mi(spark, sf_dir)), list(w.A2_CAT))
    for a in w.A2_CAT:
        wide = digits(wide, a, 8)
    return wide


# Streams


def _event_stream(spark, sf_dir):
    schema = table(spark, sf_dir, "events").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parquet*")
    return windows.event_time(raw)


def _streamed(spark, df: DataFrame, name: str) -> DataFrame:
    """Run to the end of what is there; the complete result is written anew by each micro-batch."""
    path = new_folder(spark, name)

    def keep(batch: DataFrame, _: int) -> None:
        batch.coalesce(1).write.mode("overwrite").parquet(f"{path}/out")

    df.writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    out = spark.read.parquet(f"{path}/out")
    shown = [F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias(c) if c in ("start", "end") else F.col(c).cast("double").alias(c) if c in ("s", "q") else F.col(c) for c in out.columns]
    return out.select(*shown)


_M = "CAST(COUNT(*) AS BIGINT) AS c, CAST(SUM(CAST(value AS DECIMAL(12,2))) AS DOUBLE) AS s, CAST(SUM(CAST(value AS DECIMAL(12,2)) * CAST(value AS DECIMAL(12,2))) AS DOUBLE) AS q"
_T = "'%Y-%m-%d %H:%M:%S'"


@query(f"SELECT strftime(date_trunc('day', ts), {_T}) AS start, strftime(date_trunc('day', ts) + INTERVAL 1 DAY, {_T}) AS \"end\", event_type, {_M} FROM events GROUP BY 1, 2, 3")
def stream_moments_tumbling(spark, sf_dir):
    return _streamed(spark, windows.tumbling(_event_stream(spark, sf_dir), ["event_type"], "value", "1 day"), "tumbling")


@query(f"SELECT strftime(d, {_T}) AS start, strftime(d + INTERVAL 2 DAY, {_T}) AS \"end\", event_type, {_M} FROM (SELECT date_trunc('day', ts) AS d, * FROM events UNION ALL SELECT date_trunc('day', ts) - INTERVAL 1 DAY AS d, * FROM events) GROUP BY d, event_type")
def stream_sliding(spark, sf_dir):
    return _streamed(spark, windows.sliding(_event_stream(spark, sf_dir), ["event_type"], "value", "2 days", "1 day"), "sliding")


@query(f"""WITH g AS (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY event_type ORDER BY ts) + INTERVAL 30 MINUTE OR lag(ts) OVER (PARTITION BY event_type ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS new FROM events),
s AS (SELECT *, SUM(new) OVER (PARTITION BY event_type ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT strftime(date_trunc('second', MIN(ts)), {_T}) AS start, strftime(date_trunc('second', MAX(ts) + INTERVAL 30 MINUTE), {_T}) AS "end", event_type, {_M} FROM s GROUP BY event_type, k""")
def stream_session(spark, sf_dir):
    return _streamed(spark, windows.sessions(_event_stream(spark, sf_dir), ["event_type"], "value", "30 minutes"), "session")


@query(w.moments_sql(_CONT2_SQL, w.J1_SQL))
def stream_bulks_state(spark, sf_dir):
    """Three bulk files through a stream into the view store; the state read back."""
    spec = w.j1(_CONT2)
    _, data = w.opened(spark, sf_dir, spec)
    initial, bulks = feeds.lineitem_bulks(data["lineitem"])
    path = new_folder(spark, "feed")
    feeds.write_bulks(bulks, f"{path}/bulks")
    s = LiveSession(spark, spec, w.decimal_ring(spec), order=w.ORDER_FACT, updatable=("lineitem",)).start({**data, "lineitem": initial})
    s.run(feeds.stream_bulks(spark, f"{path}/bulks", data["lineitem"]), "lineitem", f"{path}/state").awaitTermination()
    return _rows(s.store)
