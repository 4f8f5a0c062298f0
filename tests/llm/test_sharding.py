import re
import zlib

import pytest
from pyspark.sql import functions as F

from deltaring.llm import sharding as sh

MASK = (1 << 64) - 1


def jump(key, n):
    key, b, j = key & MASK, -1, 0
    while j < n:
        b = j
        key = (key * 2862933555777941757 + 1) & MASK
        j = int((b + 1) * (float(1 << 31) / float((key >> 33) + 1)))
    return b


@pytest.mark.parametrize("n", [1, 2, 24, 500])
def test_equals_the_published_hash(spark, n):
    keys = [0, 1, -1, 2**63 - 1, -(2**63), *[x * 7919**3 - 5 for x in range(300)]]
    rows = spark.createDataFrame([(k,) for k in keys], "k long").select("k", sh.jump_shards(F.col("k"), n).alias("j")).collect()
    assert all((r.j.shard, r.j.grown) == (jump(r.k, n), jump(r.k, n + 1)) for r in rows)


def test_whole_table(small):
    rows = sh.sharded_documents(small).collect()
    texts = {r.doc_id: r.text for r in small.collect()}
    assert len(rows) == len(texts)
    for r in rows:
        raw = texts[r.doc_id].encode()
        assert (r.size, r.text_crc32, r.law) == (len(raw) + 8, zlib.crc32(raw), "key")
        assert r.grown_shard in (r.shard, 24) and 0 <= r.shard < 24
    for s in range(24):
        assert sorted(r.slot for r in rows if r.shard == s) == list(range(sum(r.shard == s for r in rows)))


def test_partitions_do_not_matter(spark, small):
    a = sorted(sh.sharded_documents(small).collect())
    spark.conf.set("spark.sql.shuffle.partitions", "19")
    try:
        assert sorted(sh.sharded_documents(small.repartition(7)).collect()) == a
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")


def test_odd_rows(odd, empty):
    rows = sh.sharded_documents(odd).collect()
    assert len(rows) == odd.count() and [r.size for r in rows if r.doc_id == 3] == [8]
    assert len({r.shard for r in rows if r.doc_id is None}) == 1
    assert sh.sharded_documents(empty).count() == 0


def test_plan_has_no_python(small):
    plan = sh.sharded_documents(small)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow|Cartesian|NestedLoop", plan)
