import os

from pyspark.sql import functions as F

from deltaring import workloads as w
from deltaring.operators.delta import recomputed
from deltaring.operators.metrics import bulk_timings, throughput
from deltaring.operators.rings import MomentRing
from deltaring.operators.sparse import SparseMomentRing
from deltaring.plans.spec import load
from deltaring.sources import feeds
from deltaring.streaming import windows
from deltaring.streaming.live import LiveSession

SF = "/root/testdata/sf0.001"


def opened(spark, **options):
    spec = w.j1(("l_quantity", "o_totalprice"))
    counts = w.j1((), ("r_name", "n_name", "l_returnflag"))
    data = load(spark, SF, spec)
    initial, bulks = feeds.lineitem_bulks(data["lineitem"], deletes=True)
    s = LiveSession(spark, spec, MomentRing(spec, "decimal"), counts, SparseMomentRing(counts), w.ORDER_FACT, ("lineitem",), **options)
    return s.start({**data, "lineitem": initial}), data, initial, bulks


def final(s, data, initial, bulks):
    rows = initial.withColumn("mult", F.lit(1).cast("long"))
    for b in bulks:
        rows = rows.unionByName(b.select(rows.columns))
    return recomputed(s.tree, s.ring, {**data, "lineitem": rows}).df.collect()


def test_stream_of_bulks_and_restart(spark, tmp_path):
    s, data, initial, bulks = opened(spark)
    feeds.write_bulks(bulks[:2], f"{tmp_path}/feed")
    seen = []
    s.run(feeds.stream_bulks(spark, f"{tmp_path}/feed", data["lineitem"]), "lineitem", f"{tmp_path}/state", after=lambda x, b: seen.append((b, x.select("r_name", 0.5).where("selected").count()))).awaitTermination()
    assert s.store.committed() == ["000000000", "000000001"] and [b for b, _ in seen] == [0, 1] and all(n == 1 for _, n in seen)
    feeds.write_bulks(bulks[2:], f"{tmp_path}/feed")
    s.run(feeds.stream_bulks(spark, f"{tmp_path}/feed", data["lineitem"]), "lineitem", f"{tmp_path}/state").awaitTermination()
    assert len(s.store.committed()) == 3
    assert s.store.state().df.collect() == final(s, data, initial, bulks)
    assert not s.apply_bulk({"lineitem": bulks[0]}, "000000000")  # delivered again
    assert s.store.state().df.collect() == final(s, data, initial, bulks)
    assert throughput(s.log) > 0 and bulk_timings(spark, s.log).where("part = 'total'").count() == 3


def test_session_panels(spark):
    s, data, initial, bulks = opened(spark)
    s.apply_bulk({"lineitem": bulks[0]}, "1")
    assert s.dependency_tree().count() == 2
    a = s.ridge(["l_quantity"], "o_totalprice", 0.1)
    s.apply_bulk({"lineitem": bulks[1]}, "2")
    b = s.ridge(["l_quantity"], "o_totalprice", 0.1)
    assert a is not b and b.iterations <= a.iterations + 1
    assert s.strategy().count() == len(s.tree.nodes())


def events(spark, tmp_path, rows):
    for i, part in enumerate(rows):
        spark.createDataFrame(part, "event_id long, ts string, event_type string, value double").withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1).write.parquet(f"{tmp_path}/in{i}")
        for file in (tmp_path / f"in{i}").glob("part-*"):
            os.utime(file, (1_700_000_000 + 60 * i,) * 2)  # the stream takes files by age
    schema = spark.read.parquet(f"{tmp_path}/in0").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in*")


def run(df, mode, tmp_path, name):
    spark = df.sparkSession
    df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{tmp_path}/{name}").trigger(availableNow=True).start().awaitTermination()
    return spark.table(name).collect()


DAY = "2024-01-01 {:02d}:{:02d}:00"


def test_windows_and_late_rows(spark, tmp_path):
    rows = [[(1, DAY.format(0, 5), "a", 1.0), (2, DAY.format(0, 50), "a", 2.0)], [(3, DAY.format(3, 0), "a", 4.0)], [(6, DAY.format(3, 1), "a", 4.0)], [(4, DAY.format(0, 10), "a", 100.0), (5, DAY.format(3, 5), "b", 1.0)]]
    stream = windows.event_time(events(spark, tmp_path, rows), late="10 minutes")
    out = run(windows.tumbling(stream, ["event_type"], "value", "1 hour"), "append", tmp_path, "tumble")
    assert [(r.event_type, r.c, float(r.s), float(r.q)) for r in out] == [("a", 2, 3.0, 5.0)]  # the late row of 100 is dropped


def test_repeated_deliveries(spark, tmp_path):
    rows = [[(1, DAY.format(0, 5), "a", 1.0), (1, DAY.format(0, 5), "a", 1.0)], [(1, DAY.format(0, 5), "a", 1.0), (2, DAY.format(0, 6), "a", 1.0)]]
    stream = windows.deduplicated(windows.event_time(events(spark, tmp_path, rows)), ["event_id"])
    assert len(run(stream, "append", tmp_path, "dedup")) == 2


def test_keyed_state(spark, tmp_path):
    rows = [[(1, DAY.format(0, 5), "a", 1.0), (2, DAY.format(0, 6), "b", 2.0)], [(3, DAY.format(0, 7), "a", 3.0)]]
    out = run(windows.keyed_moments(events(spark, tmp_path, rows), "event_type", "value"), "update", tmp_path, "keyed")
    last = {r.event_type: (r.c, r.s, r.q) for r in sorted(out, key=lambda r: r.c)}
    assert last == {"a": (2, 4.0, 10.0), "b": (1, 2.0, 4.0)}


def test_feeds_by_file(spark, tmp_path):
    table = spark.read.parquet(f"{SF}/orders.parquet").select("o_orderkey", "o_custkey", "o_totalprice")
    bulk = table.where("o_orderkey % 50 = 0").withColumn("mult", F.lit(1).cast("long"))
    for kind in ("parquet", "csv", "json"):
        feeds.write_bulks([bulk, bulk], f"{tmp_path}/{kind}", kind)
        back = feeds.read_updates(spark, f"{tmp_path}/{kind}", table, kind)
        assert back.count() == 2 * bulk.count() and {r.bulk for r in back.collect()} == {1, 2}
