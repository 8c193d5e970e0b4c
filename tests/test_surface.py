"""Streams with late rows, the as-of join by brute force, views."""

import datetime as dt
import random

from pyspark.sql import functions as F

from graphsplit.functions import views
from graphsplit.operators.asof import asof
from graphsplit.sources import generators
from graphsplit.streaming import edges as stream


def events(spark, folder, batches):
    """A stream with one batch for each list of (event_id, day, user_id, event_type)."""
    for k, rows in enumerate(batches):
        data = [(i, dt.datetime(2024, 1, 1, 12) + dt.timedelta(days=d), u, t) for i, d, u, t in rows]
        spark.createDataFrame(data, "event_id long, ts timestamp, user_id long, event_type string").coalesce(1).write.parquet(f"{folder}/{k}")
    return spark.readStream.schema("event_id long, ts timestamp, user_id long, event_type string").option("maxFilesPerTrigger", 1).option("latestFirst", False).parquet(f"{folder}/*").withWatermark("ts", "1 day")


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    found = {}
    # a batch's late rows are told by the watermark of the batch before it, so day 1 is late in the fourth one
    s = events(spark, tmp_path / "in", [[(0, 0, 7, "a"), (1, 0, 7, "a")], [(2, 9, 7, "b")], [(3, 9, 7, "b")], [(4, 1, 8, "a"), (5, 20, 7, "a")], [(6, 21, 7, "a")]])
    rows = stream.finished(stream.edge_windows(s), "append", found).select(F.dayofmonth("window.start").alias("day"), "user_id", "event_type", "w").collect()
    assert sorted(tuple(r) for r in rows) == [(1, 7, "a", 2), (10, 7, "b", 2)]
    assert found["late"] == 1 and found["batches"] >= 5


def test_arrivals_go_to_the_block_of_most_events(spark, tmp_path):
    anchors = spark.createDataFrame([("a", 2), ("b", 0), ("c", 1)], "anchor string, block int")
    s = events(spark, tmp_path / "in", [[(0, 0, 7, "a"), (1, 0, 7, "a"), (2, 0, 7, "b"), (3, 0, 8, "c"), (4, 0, 8, "a"), (5, 0, 9, "x")], [(6, 9, 7, "b")], [(7, 30, 7, "b")]])
    rows = stream.finished(stream.arrivals(s, F.col("event_type"), anchors), "append").select(F.dayofmonth("window.start"), "user_id", "block", "w").collect()
    assert sorted(tuple(r) for r in rows) == [(1, 7, 2, 2), (1, 8, 1, 1), (10, 7, 0, 1)]


def test_empty_stream(spark, tmp_path):
    (tmp_path / "in").mkdir()
    s = spark.readStream.schema("event_id long, ts timestamp, user_id long, event_type string").parquet(str(tmp_path / "in")).withWatermark("ts", "1 day")
    assert stream.finished(stream.edge_windows(s), "append").count() == 0


def test_asof_by_brute_force(spark):
    rng = random.Random(5)
    left = [(i, rng.choice([1, 1, 1, 2, 3, None]), rng.choice([None, *range(-40, 60)])) for i in range(300)]
    right = [(rng.choice([1, 2, 2, None]), rng.choice([None, *range(-45, 50, 3)]), i) for i in range(60)]
    want = {i: max(((a, t) for k, a, t in right if k is not None and k == u and a is not None and at is not None and a <= at), default=(None, None))[1] for i, u, at in left}
    a, b = spark.createDataFrame(left, "id int, k int, at int"), spark.createDataFrame(right, "k int, at int, tag int")
    for slot in (1.0, 7.0, 1000.0):
        got = asof(a, b, "k", "at", slot)
        assert {r["id"]: r["t"] for r in got.select("id", F.col("found.tag").alias("t")).collect()} == want
        assert got.count() == len(left)
    assert asof(a, b.limit(0), "k", "at", 7.0).filter("found is not null").count() == 0


def test_measures_as_sql(spark):
    g = generators.planted(spark, 4, 10, 6, 1)
    views.create_views(g, g.vertices.select("vid", F.floor(F.col("vid") / 10).cast("int").alias("block")))
    cut = g.edges.filter("floor(src / 10) <> floor(dst / 10)").count() // 2
    assert views.measure(spark, "cut").first()["cut"] == cut
    assert views.measure(spark, "feasible", 4).first()["feasible"]
    assert [tuple(r) for r in views.measure(spark, "block_weights", 5).orderBy("block").collect()] == [(0, 10, 10), (1, 10, 10), (2, 10, 10), (3, 10, 10), (4, 0, 0)]
    assert [tuple(r) for r in spark.sql("SELECT first, span FROM block_spans(5) WHERE level = 2 ORDER BY block").collect()] == [(0, 2), (2, 1), (3, 1), (4, 1)]
