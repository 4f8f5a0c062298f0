import os
import re

import numpy as np
import pytest

from deltaring.llm import neardup as nd
from deltaring.llm.common import Working, scratch

WORDS = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def shingles(text):
    w = WORDS.findall((text or "").translate(LOWER))
    return frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])


def brute(rows):
    sets, root = {}, {}
    for doc, text in rows:
        sets.setdefault(doc, shingles(text))
        root[doc] = doc

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = [d for d in sets if sets[d]]
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            small, large = sorted((len(sets[a]), len(sets[b])))
            if 100 * small < 75 * large:
                continue
            n = len(sets[a] & sets[b])
            if n and 100 * n >= 75 * (len(sets[a]) + len(sets[b]) - n):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), find(d)) for d in sets}


@pytest.mark.parametrize("options", [{}, {"long_list": 2, "block_rows": 4}])
def test_whole_table_against_brute_force(small, options):
    want = brute([(r.doc_id, r.text) for r in small.select("doc_id", "text").collect()])
    got = nd.near_duplicates(small, nd.Matching(**options)).collect()
    assert len(got) == small.count()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == want
    assert all(r.kept == (r.doc_id == r.component_id) for r in got)


def test_group_of_near_copies_and_chains(spark):
    r = np.random.default_rng(5)
    base = [f"w{i}" for i in range(120)]
    rows = []
    for d in range(150):
        w = list(base)
        for k in r.integers(0, 120, r.integers(1, 6)):
            w[k] = f"e{d}_{k}"
        rows.append((1000 - d, " ".join(w)))
    chain = [f"c{i}" for i in range(100)]
    for d in range(8):  # each links with the next only
        rows.append((d, " ".join(chain[d * 8 : d * 8 + 60])))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {x.doc_id: (x.n_shingles, x.component_id) for x in nd.near_duplicates(df, nd.Matching(long_list=16, block_rows=32)).collect()}
    assert got == brute(rows)


def test_odd_rows(odd, empty):
    got = nd.near_duplicates(odd).collect()
    assert len(got) == odd.count()
    by = {r.doc_id: r for r in got if r.doc_id is not None}
    assert by[2].component_id == 1 and not by[2].kept and by[1].kept
    assert by[7].component_id == 6 and by[4].component_id == 4 and by[4].n_shingles == 0 and by[5].kept
    assert all(r.component_id is None and r.kept for r in got if r.doc_id is None)
    assert nd.near_duplicates(empty).count() == 0


def test_common_counts():
    r = np.random.default_rng(1)
    a = [np.unique(r.integers(0, 50, 20)).astype(np.int64) for _ in range(7)]
    b = [np.unique(r.integers(0, 50, 15)).astype(np.int64) for _ in range(5)]
    want = [[len(np.intersect1d(x, y)) for y in b] for x in a]
    assert (nd.common_counts(a, b, width=8) == np.array(want)).all()


def test_components(spark):
    edges = spark.createDataFrame([(5, 4), (4, 3), (3, 2), (9, 8), (8, 7), (2, 1), (7, 7)], "a long, b long")
    assert {r.id: r.root for r in nd.components(edges, Working(spark, "t")).collect()} == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 7: 7, 8: 7, 9: 7}


def test_no_pair_near_the_limit_is_missed(spark):
    """300 pairs of likeness 0.75 to 0.8, in lists short and long alike, and as many just below it."""
    rows, want = [], []
    for i in range(300):
        n = 200 + i
        a = [f"w{i}x{j}" for j in range(n)]
        common = -(-3 * (2 * (n - 4)) // 7)  # shingles of both, so that common / (2 n - common) is 0.75 or a little more
        keep = common + 4 + i % 5 - (8 if i >= 150 else 0)
        b = a[:keep] + [f"v{i}x{j}" for j in range(n - keep)]
        rows += [(2 * i, " ".join(a)), (2 * i + 1, " ".join(b))]
        both = keep - 4
        want.append(100 * both >= 75 * (2 * (n - 4) - both))
    assert 140 < sum(want) < 160
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for m in (nd.Matching(), nd.Matching(long_list=1, block_rows=8)):
        got = {r.doc_id: r.component_id for r in nd.near_duplicates(df, m).collect()}
        assert [got[2 * i + 1] == 2 * i for i in range(300)] == want


def test_long_lists_and_hot_groups(spark):
    """A list above 150 members, a group of copies of a third of all rows, and many blank texts."""
    base = [f"b{j}" for j in range(120)]
    rows = [(i, " ".join([*base[: 100 + i % 7], *[f"z{i}y{j}" for j in range(8)]])) for i in range(200)]
    rows += [(1000 + i, "the very same words again and again") for i in range(200)] + [(2000 + i, " " * i) for i in range(100)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(8)
    want = brute(rows)
    for m in (nd.Matching(), nd.Matching(long_list=16, block_rows=32, hub_rounds=1, most_hub_rounds=1)):
        assert {x.doc_id: (x.n_shingles, x.component_id) for x in nd.near_duplicates(df, m).collect()} == want


def test_working_tables_go(spark):
    df = spark.createDataFrame([(1, "a b c d e f g"), (2, "a b c d e f g"), (3, "a b c d e f g h")], "doc_id long, text string")
    out = nd.near_duplicates(df)
    folder = spark.conf.get("spark.checkpoint.dir").replace("file://", "") + "/deltaring"
    assert not [x for x in os.listdir(folder) if x.startswith("near-duplicates-")]
    assert out.count() == 3


def test_working_tables_start_no_process_on_the_driver(spark, small):
    """A marker in a table is a file that the driver makes itself, with a chmod process on local storage."""
    def marked():
        top = scratch(spark, "x").rsplit("/", 1)[0].removeprefix("file://")
        return {os.path.join(at, n) for at, _, names in os.walk(top) for n in names if n == "_SUCCESS"}

    before = marked()
    assert nd.near_duplicates(small).count() == small.count()
    assert marked() == before
