"""Streams against their batch twins, repeats of batches and lost runs."""

from pyspark.sql import functions as F

from edgemill.config import Layout
from edgemill.scratch import fresh_path
from edgemill.streaming import edges as streams


def arriving(spark, rows, parts=3):
    df = spark.createDataFrame(rows, "eid long, src long, ts timestamp_ntz, part int").withColumn("ts", F.col("ts").cast("timestamp"))
    return streams.staged(df, "part", parts)


def made(n=60):
    import datetime

    at = datetime.datetime(2024, 1, 1)
    return [(k, k * 7 % 10, at + datetime.timedelta(minutes=10 * k), k * 3 // n) for k in range(n)]


def test_routing_survives_a_repeated_batch_and_a_restart(spark):
    path, state, layout = fresh_path(spark, "owned"), fresh_path(spark, "state"), Layout(10, 2, 1)
    stream = arriving(spark, made())
    for _ in range(2):  # the second run finds nothing new behind the same checkpoint
        out = streams.route_to_owners(stream, layout, path, state)
        assert sorted(r.eid for r in out.collect()) == list(range(60))
    assert {(r.bucket, r.batch) for r in out.collect()} == {(b, k) for b in (0, 1) for k in range(3)}
    assert all(r.bucket == r.src * 2 // 10 for r in out.collect())


def test_degrees_and_packets(spark):
    got = {r.src: r.deg for r in streams.running_degrees(arriving(spark, made())).collect()}
    assert got == {s: 6 for s in range(10)}
    sent = spark.createDataFrame([(k % 2, k, k // 20) for k in range(50)] + [(0, None, 3), (1, None, 3)], "bucket int, eid long, part int")
    out = streams.collected(streams.packets(streams.staged(sent, "part", 4), 8)).drop("batch").collect()
    assert sorted(tuple(r) for r in out) == [(b, p, 8 if p < 3 else 1, b + 16 * p) for b in (0, 1) for p in range(4)]


def test_late_edges_are_kept_apart(spark):
    rows = [(e, s, t, (2, 0, 1)[p]) for e, s, t, p in made()]  # the oldest third arrives last
    out = {r.eid: r.late for r in streams.split_late(arriving(spark, rows), "3 hours", fresh_path(spark, "late")).collect()}
    assert out == {k: k < 20 for k in range(60)}


def test_no_events(spark):
    empty = arriving(spark, made()[:0])
    assert streams.running_degrees(empty).count() == 0
    assert streams.windowed_degrees(arriving(spark, made()[:1]), "1 hour").count() == 1
