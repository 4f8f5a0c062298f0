import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from deltaring.llm import resample as rs
from deltaring.llm.common import cut_at, written
from deltaring.llm.ngrams import NgramModel


def test_weights_against_brute_force(small, labels):
    model = NgramModel(slots=1024)
    texts = {r.doc_id: r.text for r in small.collect()}
    good = {r.doc_id for r in labels.where("quality = 1").collect()}
    raw, target = np.zeros(1024), np.zeros(1024)
    for d, t in texts.items():
        n = np.bincount(rs.gram_slots(t, 1024), minlength=1024)
        raw += n
        target += n * (d in good)
    want = np.log(target + 16) - np.log(raw * target.sum() / raw.sum() + 16)
    assert np.allclose(rs.fitted_ratios(small, labels, model), want)
    fitted = rs.fitted_ratios(small, labels.where(~rs.held_out(labels)), model)
    rows = rs.sampled(small, labels, model=model).collect()
    want = fitted
    weights = {x.doc_id: want[rs.gram_slots(x.text, 1024)].sum() for x in rows}
    for x in rows:
        assert math.isclose(x.log_weight, weights[x.doc_id], abs_tol=1e-6)
    order = sorted(rows, key=lambda x: -x.gumbel_key)
    held = {r.doc_id for r in labels.where(rs.held_out(labels)).collect()} & good
    bad = {r.doc_id for r in labels.where(rs.held_out(labels)).where("quality = 0").collect()}
    cost = lambda c: sum(weights[d] < c for d in held) / len(held) + rs.BAD_COST * sum(weights[d] >= c for d in bad) / len(bad)
    costs = {c: round(cost(c), 9) for c in sorted(weights[d] for d in held | bad)}
    equal = [c for c, x in costs.items() if x == min(costs.values())]
    cut = equal[len(equal) // 2] - rs.NOISE
    size = sum(w >= cut - 1e-9 for w in weights.values())
    assert 10 < len(held) < len(good) / 2 and {x.doc_id for x in rows if x.selected} == {x.doc_id for x in order[:size]}
    half = rs.sampled(small, labels, 0.5, model=model).collect()
    assert {x.doc_id for x in half if x.selected} == {x.doc_id for x in order[: len(rows) // 2]}
    assert not any(x.selected for x in rs.sampled(small, labels, 0.0, model=model).collect())


def test_held_out_accuracy(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    rows = rs.resampled_documents(docs, labels.where("doc_id % 3 <> 0")).join(labels.where("doc_id % 3 = 0"), "doc_id").collect()
    good, bad = ([r.selected for r in rows if r.quality == q] for q in (1, 0))
    assert sum(good) >= 0.97 * len(good) and sum(bad) <= 0.5 * len(bad)


def test_size_follows_the_weights(spark):
    """With hardly any bad documents hardly any go, and with many, many go: the share of bad labels does not matter."""
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    mostly_good = labels.where("quality = 1 or doc_id % 10 = 0")
    few = docs.join(labels.where("quality = 0"), "doc_id", "left_anti")
    for d in (docs, few):
        rows = rs.resampled_documents(d, mostly_good).join(labels, "doc_id", "left").collect()
        good, bad = ([r.selected for r in rows if r.quality == q] for q in (1, 0))
        assert sum(good) >= 0.995 * len(good) and sum(bad) <= 0.2 * len(bad)


def test_columns_with_clashing_names(spark, odd_labels):
    df = spark.createDataFrame([(1, "a b", 0.5, 2.5, "x", True)], "doc_id long, text string, log_weight double, GUMBEL_KEY double, __key string, selected boolean")
    row = rs.sampled(df, odd_labels).first()
    assert row[:6] == (1, "a b", 0.5, 2.5, "x", True) and row["selected_"] and row["log_weight_"] is not None


def test_gumbel_noise(spark):
    g = np.array([r.g for r in spark.range(20_000).select(rs.gumbel(1, F.col("id")).alias("g")).collect()])
    assert abs(g.mean() - 0.5772) < 0.03 and abs(g.std() - math.pi / 6**0.5) < 0.03


@pytest.mark.parametrize("k", [0, 1, 7, 50, 99, 100, 200])
def test_cut_is_exact(spark, k):
    values = [(x * 37) % 41 - 20 for x in range(99)] + [10**15]
    df = written(spark.createDataFrame([(v,) for v in values], "key long"), "keys")
    t, left = cut_at(df, "key", k, fan=4)
    if k >= 100:
        assert t is None
    elif k:
        assert sum(v > t for v in values) == k - left and 1 <= left <= sum(v == t for v in values)


def test_odd_rows(odd, empty, odd_labels):
    rows = rs.resampled_documents(odd, odd_labels).collect()
    assert len(rows) == odd.count() and all(r.log_weight == 0 for r in rows if r.doc_id in (3, 4, 5))
    assert rs.resampled_documents(empty, odd_labels).count() == 0
    assert all(r.selected for r in rs.resampled_documents(odd, odd_labels.limit(0)).collect())
