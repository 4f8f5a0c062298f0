"""The as-of join against brute force, with time whole and cut into ranges."""

import random

import pytest

from deltaring.operators import relational


@pytest.mark.parametrize("by", [[], ["k"]])
@pytest.mark.parametrize("parts", [None, 1, 3, 16])
def test_asof_join(spark, by, parts):
    draw = random.Random(5)
    key = lambda: draw.choice([1, 1, 1, 1, 2, 3, None])
    events = [(i, key(), draw.choice([None, *range(60)])) for i in range(300)]
    snaps = [(k, t, 100 * t + k) for k in (1, 2) for t in draw.sample(range(60), 12 * k)] + [(None, 5, -1), (1, None, -2)]
    if not by:
        snaps = list({s[1]: s for s in snaps if s[0] is not None}.values())
    df, sf = spark.createDataFrame(events, "id int, k int, t int"), spark.createDataFrame(snaps, "k int, t int, v int")
    joined = relational.asof_join(df, sf.select(*by, "t", "v"), "t", by, ["v"], parts)
    want = {}
    for i, k, t in events:
        seen = [s for s in snaps if None not in (t, s[1]) and s[1] <= t and (not by or k is not None and s[0] == k)]
        want[i] = max(((s[1], s[2]) for s in seen), default=(None, None))
    assert {r.id: (r.t_asof, r.v) for r in joined.collect()} == want and joined.count() == len(events)
    cut = "__part" in joined._jdf.queryExecution().analyzed().toString()
    assert cut == bool(parts and parts > 1)
    assert relational.asof_join(df.limit(0), sf.limit(0).select(*by, "t", "v"), "t", by, ["v"], parts).count() == 0
