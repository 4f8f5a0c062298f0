import re
from collections import Counter

import pytest

from deltaring.llm import mixing as mx

WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def water_fill(sizes, weights, repeats=3):
    """Targets by sharing again and again."""
    total, target, open_ = sum(sizes), [0.0] * len(sizes), [i for i in range(len(sizes))]
    left = float(total)
    while open_:
        w = sum(weights[i] for i in open_)
        full = [i for i in open_ if left * weights[i] / w > repeats * sizes[i] + 1e-9]
        if not full:
            for i in open_:
                target[i] = left * weights[i] / w
            break
        for i in full:
            target[i] = repeats * sizes[i]
            left -= target[i]
            open_.remove(i)
    return target


def seats(targets, n):
    """Sainte-Laguë, one seat after another."""
    got = [0] * len(targets)
    for _ in range(n):
        best = max(range(len(targets)), key=lambda i: (targets[i] / (2 * got[i] + 1), -i))
        got[best] += 1
    return got


@pytest.mark.parametrize("sizes", [[100, 900, 40, 7, 300, 0, 55], [1], [0, 0], [10**6, 3, 3, 3, 3], list(range(1, 60))])
def test_targets_and_seats(spark, sizes):
    df = spark.createDataFrame([(f"s{i:03d}", n) for i, n in enumerate(sizes)], "source string, source_size long")
    t = mx.source_targets(df).orderBy("rank")
    weights = [(5, 2, 1)[i % 3] for i in range(len(sizes))]
    got = t.collect()
    want = water_fill(sizes, weights)
    assert all(abs(r.target - x) < 1e-6 * max(1, x) for r, x in zip(got, want))
    q = mx.block_quotas(mx.source_targets(df), 4).orderBy("rank").collect()
    total = int(sum(sizes) / 4 + 0.5)
    if sum(sizes):
        limit = [3 * -(-n // 4) for n in sizes]
        assert [r.quota for r in q] == [min(a, b) for a, b in zip(seats([r.target for r in got], total), limit)]


def check(rows, docs):
    sizes = Counter()
    for d in docs:
        sizes[d.source] += len(WORDS.findall(d.text or ""))
    names = sorted([s for s in sizes if s is not None], key=lambda s: s.encode()) + ([None] if None in sizes else [])
    want = dict(zip(names, water_fill([sizes[s] for s in names], [(5, 2, 1)[i % 3] for i in range(len(names))])))
    taken = Counter()
    for r in rows:
        assert 0 <= r.taken <= 3 * r.size and r.source_size == sizes[r.source] and abs(r.target - want[r.source]) < 1e-6 * max(1, want[r.source])
        taken[r.source] += r.taken
    for s in names:
        assert abs(taken[s] - want[s]) <= 3.5 * mx.BLOCK_WORDS
    assert sorted(r.size for r in rows) == sorted(len(WORDS.findall(d.text or "")) for d in docs)


def test_whole_table(spark, small):
    rows = mx.mixture(small).collect()
    check(rows, small.collect())
    a = sorted(mx.mixed_documents(small).collect())
    spark.conf.set("spark.sql.shuffle.partitions", "23")
    try:
        assert sorted(mx.mixed_documents(small.repartition(5)).collect()) == a
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")


def test_texts_hold_the_taken_words(small):
    takes = {r.doc_id: r.taken for r in mx.mixed_documents(small).collect() if r.taken}
    got = Counter()
    whole = {r.doc_id: r.text for r in small.collect()}
    for r in mx.mixed_texts(small).collect():
        got[r.doc_id] += len(WORDS.findall(r.text))
        assert set(WORDS.findall(r.text)) <= set(WORDS.findall(whole[r.doc_id])) and r.n_chars == len(r.text)
    assert got == takes


def test_odd_rows(odd, empty):
    check(mx.mixture(odd).collect(), odd.collect())
    assert mx.mixed_documents(empty).count() == 0 and mx.mixed_texts(empty).count() == 0
    assert mx.mixed_texts(odd).columns == ["doc_id", "text", "lang", "source", "n_chars"]


def test_plan_has_no_python(small):
    plan = mx.mixed_documents(small)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow|Cartesian|NestedLoop", plan)
