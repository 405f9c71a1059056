"""Streaming operators as queries: each runs a stream to its end, its SQL is the batch twin."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgemill.catalogue import NB, PACKET, SEED, entry, longs, sql_perm, sql_rmat, sql_with
from edgemill.config import GenSpec, Layout
from edgemill.operators import permute
from edgemill.scratch import fresh_path, materialise
from edgemill.sources import tables
from edgemill.streaming import edges as streams

BATCHES = 4
SMALL = GenSpec(scale=8, edge_factor=16, seed=SEED, backend="portable")
SQL_USERS = "dims AS (SELECT max(user_id) + 1 AS n FROM events)"


def events(spark, sf_dir: str, *columns) -> DataFrame:
    # a watermark needs an instant; the table's times are wall times of the session's zone
    return tables.table(spark, sf_dir, "events").select(F.col("event_id").alias("eid"), F.col("user_id").alias("src"), F.col("ts").cast("timestamp").alias("ts"), *columns)


def event_stream(spark, sf_dir: str, *columns) -> DataFrame:
    """The events in batches by time."""
    rows = events(spark, sf_dir, *columns)
    return streams.staged(materialise(rows.select("*", streams.batch_of("part", ["ts", "eid"], BATCHES)), "events"), "part", BATCHES)


def users(spark, sf_dir: str) -> int:
    return tables.table(spark, sf_dir, "events").agg(F.max("user_id") + 1).first()[0]


@entry("Z1 S8", sql_with(sql_rmat(SMALL)) + " SELECT eid, src, dst FROM edges")
def stream_generate(spark, sf_dir):
    """Edge numbers arrive in batches and leave as edges."""
    numbers = spark.range(SMALL.edges).select(F.col("id").alias("eid"), (F.col("id") % BATCHES).alias("part"))
    return streams.collected(streams.generate_edges(streams.staged(numbers, "part", BATCHES), SMALL)).drop("batch")


@entry("Z1 S3", "SELECT CAST(4096 AS BIGINT) AS edges, CAST(4096 AS BIGINT) AS ids, CAST(0 AS BIGINT) AS outside")
def stream_source(spark, sf_dir):
    """The stream reader of the custom source, to its end: number of edges and ids, no end outside."""
    from edgemill.sources.datasource import register

    register(spark)
    path = fresh_path(spark, "rmat-stream")
    source = spark.readStream.format("rmat").option("scale", 8).option("rowsPerBatch", 1000).load()
    query = source.writeStream.foreachBatch(streams.into_batches(path)).option("checkpointLocation", fresh_path(spark, "stream-state")).start()
    query.processAllAvailable()
    query.stop()
    outside = ~F.col("src").between(0, 255) | ~F.col("dst").between(0, 255)
    return streams.stored(spark, path, source.schema).agg(F.count(F.lit(1)).alias("edges"), F.countDistinct("eid").alias("ids"), F.sum(outside.cast("long")).alias("outside"))


@entry("Z2", sql_with(SQL_USERS, "ids AS (SELECT unnest(range(n)) AS id FROM dims)", sql_perm()) + " SELECT event_id AS eid, label AS src FROM events JOIN perm ON user_id = id")
def stream_relabel(spark, sf_dir):
    perm = materialise(permute.by_sort(spark, users(spark, sf_dir), SEED, "portable"), "permutation")
    return streams.collected(streams.relabel_stream(event_stream(spark, sf_dir).select("eid", "src"), perm)).drop("batch")


@entry("Z3 S4 S8", f"WITH {SQL_USERS} SELECT (user_id * {NB}) // n AS bucket, count(*) AS edges, CAST(sum(event_id) AS BIGINT) AS eids, CAST({BATCHES} AS BIGINT) AS batches FROM events, dims GROUP BY ALL")
def stream_route(spark, sf_dir):
    """Edges appended to the owners' folders, batch by batch; the second batch is sent twice and counts once."""
    layout = Layout(users(spark, sf_dir), NB, 1)
    path = fresh_path(spark, "owned-stream")
    edges = event_stream(spark, sf_dir).select("eid", "src")
    listed = streams.route_to_owners(edges, layout, path)
    again = materialise(listed.where("batch = 1").drop("batch"), "again")
    streams.into_batches(path, ["bucket"])(again, 1)
    return longs(streams.stored(spark, path, again.schema).groupBy("bucket").agg(F.count(F.lit(1)).alias("edges"), F.sum("eid").alias("eids"), F.countDistinct("batch").alias("batches")))


@entry("Z4", "SELECT user_id AS src, count(*) AS deg FROM events GROUP BY ALL")
def stream_degrees(spark, sf_dir):
    return streams.running_degrees(event_stream(spark, sf_dir))


def _window_sql(width: str, starts: str) -> str:
    return f"""SELECT strftime(b, '%Y-%m-%d %H:%M:%S') AS start, strftime(b + INTERVAL {width}, '%Y-%m-%d %H:%M:%S') AS "end", user_id AS src, count(*) AS deg
FROM (SELECT user_id, {starts} AS b FROM events) GROUP BY ALL"""


@entry("Z5 scalar time", _window_sql("1 HOUR", "date_trunc('hour', ts)"))
def stream_tumbling(spark, sf_dir):
    return streams.windowed_degrees(event_stream(spark, sf_dir), "1 hour")


@entry("Z5", _window_sql("6 HOUR", "unnest([time_bucket(INTERVAL 3 HOUR, ts), time_bucket(INTERVAL 3 HOUR, ts) - INTERVAL 3 HOUR])"))
def stream_sliding(spark, sf_dir):
    return streams.windowed_degrees(event_stream(spark, sf_dir), "6 hours", "3 hours")


@entry("Z5", """WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 4 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS nth FROM g) SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, user_id AS src, count(*) AS deg FROM s GROUP BY user_id, nth""")
def stream_sessions(spark, sf_dir):
    return streams.session_degrees(event_stream(spark, sf_dir), "4 hours")


@entry("Z6", f"""WITH p AS (SELECT event_id AS eid, ts, (event_id * 7) % {BATCHES} AS batch FROM events),
m AS (SELECT b.batch, max(p.ts) AS newest FROM (SELECT DISTINCT batch FROM p) b LEFT JOIN p ON p.batch < b.batch GROUP BY b.batch)
SELECT eid, coalesce(ts < newest - INTERVAL 10 DAY, false) AS late, CAST(p.batch AS BIGINT) AS batch FROM p JOIN m USING (batch)""")
def stream_late(spark, sf_dir):
    """Events in a shuffled order of files; those over ten days behind are told apart, none is lost."""
    rows = events(spark, sf_dir).withColumn("part", F.col("eid") * 7 % BATCHES)
    out = streams.split_late(streams.staged(rows, "part", BATCHES), "10 days", fresh_path(spark, "late-edges"))
    return out.select("eid", "late", "batch")


@entry("Z7", "SELECT event_id AS eid, user_id AS src FROM events")
def stream_dedup(spark, sf_dir):
    """Every event is sent twice, the second time a batch later."""
    rows = materialise(events(spark, sf_dir).select("*", streams.batch_of("part", ["ts", "eid"], BATCHES - 1)), "events")
    twice = rows.unionByName(rows.withColumn("part", F.col("part") + 1))
    edges = streams.without_copies(streams.staged(twice, "part", BATCHES), ["eid"], "40 days")
    return streams.collected(edges.select("eid", "src")).drop("batch")


@entry("Z8", f"""WITH {SQL_USERS}, p AS (SELECT (user_id * {NB}) // n AS bucket, event_id AS eid, (row_number() OVER (PARTITION BY (user_id * {NB}) // n ORDER BY event_id) - 1) // {PACKET} AS packet_no FROM events, dims)
SELECT bucket, packet_no, count(*) AS edges, min(eid) AS first_eid FROM p GROUP BY ALL""")
def stream_packets(spark, sf_dir):
    """Packets by owner; the last batch holds each sender's end, which sends what is left."""
    n = users(spark, sf_dir)
    owner = F.call_function("div", F.col("src") * F.lit(NB).cast("long"), F.lit(n).cast("long")).cast("int").alias("bucket")
    rows = events(spark, sf_dir).select(owner, "eid", streams.batch_of("part", ["eid"], BATCHES))
    ends = spark.range(NB).select(F.col("id").cast("int").alias("bucket"), F.lit(None).cast("long").alias("eid"), F.lit(BATCHES).alias("part"))
    sent = streams.packets(streams.staged(materialise(rows.unionByName(ends), "sent"), "part", BATCHES + 1), PACKET)
    return longs(streams.collected(sent).drop("batch"))


@entry("Z9", """SELECT a.user_id AS src, a.event_id AS eid, b.event_id AS next_eid FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR
WHERE a.event_type = 'click' AND b.event_type = 'purchase'""")
def stream_interval_join(spark, sf_dir):
    """Clicks and the same user's purchases within an hour, stream to stream."""
    edges = event_stream(spark, sf_dir, "event_type")
    clicks, purchases = (edges.where(F.col("event_type") == kind) for kind in ("click", "purchase"))
    return streams.collected(streams.followed_by(clicks, purchases, "1 hour")).drop("batch")
