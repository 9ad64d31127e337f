import datetime as dt

import pytest
from pyspark.sql import functions as F

from flowblocks.functions import slots
from flowblocks.operators import cells, regions
from flowblocks.queries import QUERIES
from flowblocks.sources import files, trips
from flowblocks.streaming import cells as stream

DAY = dt.datetime(2024, 1, 6)  # a Saturday


def test_slots(spark):
    t = spark.createDataFrame([(DAY + dt.timedelta(hours=h, minutes=m),) for h, m in ((0, 0), (9, 0), (9, 29), (9, 30), (23, 59))], "ts timestamp_ntz")
    got = t.select(slots.uniform(F.col("ts")).alias("u"), slots.custom(F.col("ts"), [9 * 3600, 9 * 3600 + 1800]).alias("c"), slots.classed(F.col("ts"), slots.uniform(F.col("ts")), 48).alias("k")).collect()
    assert [r.u for r in got] == [0, 18, 18, 19, 47] and [r.c for r in got] == [0, 1, 1, 2, 2] and [r.k for r in got] == [49, 67, 67, 68, 96]
    many = spark.range(1000).select((F.lit(DAY) + F.make_interval(secs=F.col("id") * 60)).alias("ts"))
    by = many.groupBy(slots.custom(F.col("ts"), slots.equi_depth_bounds(many, 4)).alias("s")).count().collect()
    assert sorted(r["count"] for r in by) == [250] * 4


def test_trips_that_do_not_count(spark):
    t = spark.createDataFrame([(1, 1, 0, 5), (1, None, 0, 5), (1, 2, 0, 0), (1, 2, 0, 4), (1, 2, None, 1)], "o int, d int, t int, pax bigint")
    assert [tuple(r) for r in cells.aggregate(trips.valid(t)).collect()] == [(1, 2, 0, 4)]


def test_counted_trips_leave_out_hops_without_cents(spark, tmp_path):
    rows = [(i, DAY + dt.timedelta(minutes=i), 1, v, f'{{"k":{4 * (i % 2)}}}') for i, v in enumerate((1.0, 0.004, 2.0, None, 3.0, 1.0))]
    spark.createDataFrame(rows, "event_id bigint, ts timestamp_ntz, user_id bigint, value double, props string").write.parquet(f"{tmp_path}/events.parquet")
    assert sorted(tuple(r) for r in cells.aggregate(trips.clicks(spark, str(tmp_path), flow="trips")).collect()) == [(0, 1, 0, 3)]


def test_nearest_and_clusters(spark):
    p = spark.createDataFrame([(1, [0.0, 0.1], 0), (2, [5.0, 5.0], 1), (3, [0.2, 0.0], 0), (4, [5.1, 5.0], 1), (5, None, 1)], "id bigint, v array<float>, label int")
    c = regions.centres(p, "label", "v")
    assert {r.id: r.r for r in regions.nearest(p, c, "id", "v").collect()} == {1: 0, 2: 1, 3: 0, 4: 1}
    with pytest.raises(ValueError):
        regions.nearest(p, c.limit(0), "id", "v")
    k = {r.id: r.r for r in regions.cluster(p, "id", "v", 2).collect()}
    assert k[1] == k[3] != k[2] == k[4]


def test_files(spark, tmp_path):
    b = spark.createDataFrame([(3, [0], [1], 0, 0, 1, 1), (4, [0, 2], [1], 0, 0, 2, 2)], files.BLOCKS)
    files.write_blocks(b, f"{tmp_path}/b")
    assert sorted(files.read_blocks(spark, f"{tmp_path}/b").collect()) == sorted(b.collect())
    assert "PartitionFilters: [isnotnull(level" in files.read_blocks(spark, f"{tmp_path}/b").where("level = 4")._jdf.queryExecution().toString()
    (tmp_path / "bad.csv").write_text("u,v\n1,x\n")
    with pytest.raises(Exception):
        files.read(spark, f"{tmp_path}/bad.csv", files.EDGES, "csv").collect()


def events(spark, rows):
    return spark.createDataFrame([(u, i, DAY + dt.timedelta(minutes=m), k, 1) for i, (u, m, k) in enumerate(rows)], "user_id bigint, event_id bigint, ts timestamp, k int, pax bigint")


def test_streams_equal_batches(spark):
    rows = [(1, 0, 3), (1, 10, 4), (2, 15, 1), (1, 100, 5), (2, 130, 2), (1, 105, 6), (3, 200, 9), (3, 201, 8)]
    hops, _ = stream.run(stream.hops(stream.replay(events(spark, rows), 3)))
    assert {(r.o, r.d, r.ts.hour * 60 + r.ts.minute) for r in hops.collect()} == {(3, 4, 0), (4, 5, 10), (5, 6, 100), (1, 2, 15), (9, 8, 200)}
    s, _ = stream.run(stream.sessions(stream.replay(events(spark, rows), 2)))
    assert {(r.user_id, r.o, r.d, r.n) for r in s.where("user_id is not null").collect()} == {(1, 3, 4, 2), (1, 5, 6, 2), (2, 1, 1, 1), (2, 2, 2, 1), (3, 9, 8, 2)}


def test_late_rows_are_counted(spark):
    t = events(spark, [(1, 0, 1), (1, 300, 1), (1, 301, 1)]).select("ts", F.lit(1).alias("o"), F.lit(2).alias("d"), "pax")
    early = t.where("hour(ts) < 1").unionByName(t.where("hour(ts) > 1"))
    root = stream.shared_folder(spark) + "/late"
    t.where("hour(ts) > 1").coalesce(1).write.mode("append").parquet(root)
    out = stream.tumbling(spark.readStream.schema(early.schema).option("maxFilesPerTrigger", 1).parquet(root))
    q = out.writeStream.format("memory").queryName("late_cells").outputMode("append").option("checkpointLocation", root + "-log").start()
    q.processAllAvailable()
    t.where("hour(ts) < 1").coalesce(1).write.mode("append").parquet(root)
    q.processAllAvailable()
    assert sum(op["numRowsDroppedByWatermark"] for p in q.recentProgress for op in p["stateOperators"]) == 1
    q.stop()


def test_store_adds_a_batch_once(spark):
    store = stream.CellStore(spark)
    one = spark.createDataFrame([(1, 2, 0, 4)], "o int, d int, t int, pax bigint")
    for batch in (0, 1, 1):
        store.add(one, batch)
    assert [tuple(r) for r in store.now.collect()] == [(1, 2, 0, 8)]


def test_path_over_the_regions_of_events(spark, tmp_path):
    spark.createDataFrame([(i, DAY, 1, 1.0, f'{{"k":{k}}}') for i, k in enumerate((0, 5, 9, 9, 20))], "event_id bigint, ts timestamp_ntz, user_id bigint, value double, props string").write.parquet(f"{tmp_path}/events.parquet")
    assert sorted(tuple(r) for r in QUERIES["graph_path_edges"](spark, str(tmp_path)).collect()) == [(0, 1), (1, 0), (1, 2), (2, 1)]


def _orders(spark, at, months):
    spark.createDataFrame([(i, dt.datetime(2024, m, 1)) for i, m in enumerate(months)], "o_orderkey bigint, o_orderdate timestamp_ntz").write.parquet(f"{at}/orders.parquet")


def test_windows_over_the_months_of_orders(spark, tmp_path):
    _orders(spark, tmp_path, (1, 2, 3, 3, 6, 11, 12))
    assert sorted(tuple(r) for r in QUERIES["window_pool"](spark, str(tmp_path)).collect()) == [(0, 0, 1), (1, 1, 2), (2, 10, 11)]


def test_costs_of_the_sizes_in_tables(spark, tmp_path):
    _orders(spark, tmp_path, (1, 2, 3, 3))
    spark.createDataFrame([(1, 4), (2, 5), (3, 4)], "c_custkey bigint, c_nationkey int").write.parquet(f"{tmp_path}/customer.parquet")
    got = dict(tuple(r) for r in QUERIES["cost_formulas"](spark, str(tmp_path)).collect())
    assert got == {"levelwise": 12, "bounded": 12, "partners": 4, "prefix": 36, "pool": 8, "sampling": 256, "combinations": 0}
