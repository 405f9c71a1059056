"""The rest of the surface as queries: table functions, bucketed tables, sort aggregates, pivots, arrays, maps, JSON, times."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from edgemill.catalogue import NB, RMAT10, SEED, SQL_BASE, SQL_BASE_RMAT, SQL_CSR, SQL_CUSTOMER_PERM, entry, longs, perm_sort, relabelled, rmat10, same, sql_hash
from edgemill.config import GenSpec, Layout
from edgemill.functions.partition import register_sql
from edgemill.operators import csr, permute, redistribute, relabel
from edgemill.operators.positions import dense_position
from edgemill.scratch import materialise
from edgemill.sources import rmat, tables


@entry("F2 P7", SQL_CUSTOMER_PERM + f" SELECT id, label FROM perm, dims WHERE (id * {NB}) // n = 1")
def perm_range_function(spark, sf_dir):
    """One range of a stored permutation through a SQL table function."""
    from edgemill.functions import tablefunctions

    n = tables.size_of(spark, sf_dir, "customer")
    permute.store_ranges(perm_sort(spark, sf_dir), n, NB).createOrReplaceTempView("served_permutation")
    tablefunctions.register(spark, "served_permutation")
    return spark.sql("SELECT id, label FROM perm_range(1)")


@entry("F3 K5", f"{SQL_CSR}, numbered AS (SELECT src AS id, row_number() OVER (ORDER BY src, dst, eid) - 1 AS pos, dst FROM relabelled) SELECT id, pos, dst FROM numbered")
def csr_neighbors_function(spark, sf_dir):
    """The neighbours of every vertex through a lateral SQL table function."""
    from edgemill.functions import tablefunctions

    edges, layout, _ = relabelled(spark, sf_dir)
    tablefunctions.register_csr(spark, csr.csr_ordered(edges, layout))
    spark.range(layout.n).createOrReplaceTempView("wanted_vertices")
    return spark.sql("SELECT w.id, f.pos, f.dst FROM wanted_vertices w, LATERAL csr_neighbors(w.id) f")


@entry("S5 RL1", SQL_BASE_RMAT + " SELECT e.eid, e.src, d.label AS dst FROM edges e JOIN perm d ON e.dst = d.id")
def relabel_bucketed(spark, sf_dir):
    """One end through bucketed tables: both are stored by the same buckets, so the join exchanges nothing (raises if its plan does)."""
    from edgemill.plans.inspect import plan_summary

    edges, perm, _ = rmat10(spark, sf_dir)
    mark = uuid.uuid4().hex[:12]
    for df, name, key in ((edges, "edges", "dst"), (perm, "perm", "id")):
        df.write.bucketBy(NB, key).sortBy(key).format("parquet").saveAsTable(f"bucketed_{name}_{mark}")
    joined = relabel.relabel_endpoint(spark.table(f"bucketed_edges_{mark}"), spark.table(f"bucketed_perm_{mark}"), "dst", "merge")
    if plan_summary(joined)["exchanges"]:
        raise RuntimeError("the join of bucketed tables exchanges rows")
    out = materialise(joined, "relabelled")
    for name in ("edges", "perm"):
        spark.sql(f"DROP TABLE bucketed_{name}_{mark}")
    return out


@entry("E1f X21", "SELECT CAST(16384 AS BIGINT) AS edges, CAST(16384 AS BIGINT) AS ids, CAST(0 AS BIGINT) AS strays, CAST(0 AS BIGINT) AS outside, CAST(1 AS BIGINT) AS fewer_exchanges")
def relabel_born_aligned(spark, sf_dir):
    """Edges born with their destination's owner, relabelled in place: no edge lost, each part's labels are those of its range, one exchange of the edges fewer."""
    from edgemill.plans.inspect import plan_summary

    spec, layout = GenSpec(scale=10, seed=SEED), Layout(1024, NB, 1)
    perm = materialise(permute.by_sort(spark, 1024, SEED), "permutation")
    parts = rmat.aligned_parts(spark, spec, NB)
    new = relabel.relabel_aligned(parts, perm, layout)
    plain = relabel.relabel_merge(rmat.rmat_edges(spark, spec), perm)
    fewer = plan_summary(plain)["exchanges"] > plan_summary(new)["exchanges"]
    old = rmat.rmat_edges_aligned(spark, spec, NB).join(perm, F.col("dst") == F.col("id")).select("eid", F.col("label").alias("expected"))
    outside = ~F.col("src").between(0, 1023) | ~F.col("dst").between(0, 1023)
    return new.join(old, "eid").agg(
        F.count(F.lit(1)).alias("edges"), F.countDistinct("eid").alias("ids"), F.sum((F.col("dst") != F.col("expected")).cast("long")).alias("strays"), F.sum(outside.cast("long")).alias("outside"),
        F.lit(int(fewer)).cast("long").alias("fewer_exchanges"),
    )


@entry("AG2 K4", """SELECT user_id AS src, string_agg(event_type, ' ' ORDER BY ts, event_id) AS types FROM events GROUP BY user_id""")
def agg_sort(spark, sf_dir):
    """Lists by key, whose buffers no hash table holds at a fixed size: an object-hash aggregate that falls back to sorting."""
    rows = tables.table(spark, sf_dir, "events")
    listed = F.sort_array(F.collect_list(F.struct("ts", "event_id", "event_type")))
    return rows.groupBy(F.col("user_id").alias("src")).agg(F.array_join(F.transform(listed, lambda x: x["event_type"]), " ").alias("types"))


@entry("AG6 C6", f"""WITH e AS (SELECT (eid * {NB}) // m AS from_bucket, (src * {NB}) // n AS to_bucket FROM relabelled, dims)
SELECT from_bucket, {', '.join(f'count(*) FILTER (WHERE to_bucket = {k}) AS to_{k}' for k in range(NB))} FROM e GROUP BY from_bucket""".replace("WITH e", f"{SQL_BASE}, e"))
def agg_pivot(spark, sf_dir):
    """The message matrix of the part-supplier edges, a column for each receiver."""
    new, layout, m = relabelled(spark, sf_dir)
    routed = new.select(redistribute.sender_of(F.col("eid"), m, NB).alias("from_bucket"), F.concat(F.lit("to_"), redistribute.owner_of(F.col("src"), layout.n, NB).cast("string")).alias("receiver"))
    return routed.groupBy("from_bucket").pivot("receiver", [f"to_{k}" for k in range(NB)]).agg(F.count(F.lit(1))).na.fill(0)


@entry("array A3", f"""WITH n AS (SELECT user_id AS src, list_sort(list_distinct(list(CAST(json_extract_string(props, '$.k') AS BIGINT)))) AS nbrs FROM events GROUP BY user_id)
SELECT a.src, len(a.nbrs) AS deg, a.nbrs[1] AS least, list_sum(list_filter(a.nbrs, lambda x: x % 2 = 0)) AS even_sum, array_to_string(a.nbrs[1:3], ',') AS head,
  len(list_intersect(a.nbrs, b.nbrs)) AS common FROM n a JOIN n b ON b.src = a.src + 1""")
def scalar_arrays(spark, sf_dir):
    """Neighbour arrays: distinct, sort, slice, filter, aggregate, intersect with the next user's."""
    k = F.get_json_object("props", "$.k").cast("long")
    nbrs = tables.table(spark, sf_dir, "events").groupBy(F.col("user_id").alias("src")).agg(F.sort_array(F.array_distinct(F.collect_list(k))).alias("nbrs"))
    other = nbrs.select((F.col("src") - 1).alias("src"), F.col("nbrs").alias("next"))
    even = F.filter("nbrs", lambda x: x % 2 == 0)
    total = F.when(F.size(even) > 0, F.aggregate(even, F.lit(0).cast("long"), lambda a, x: a + x))
    return longs(nbrs.join(other, "src").select(
        "src", F.size("nbrs").alias("deg"), F.col("nbrs")[0].alias("least"), total.alias("even_sum"), F.array_join(F.slice("nbrs", 1, 3), ",").alias("head"), F.size(F.array_intersect("nbrs", "next")).alias("common"),
    ))


@entry("array A16", f"{SQL_BASE_RMAT}, z AS (SELECT eid // 4 AS row, eid % 4 AS nth, src, dst FROM relabelled) SELECT row, nth, src, dst FROM z")
def scalar_zipped(spark, sf_dir):
    """Packets as two arrays zipped, nested, flattened and exploded again."""
    edges, perm, _ = rmat10(spark, sf_dir)
    rows = relabel.relabel_merge(edges, materialise(perm, "permutation")).groupBy(F.call_function("div", F.col("eid"), F.lit(4).cast("long")).alias("row")).agg(F.sort_array(F.collect_list(F.struct("eid", "src", "dst"))).alias("e"))
    halves = F.flatten(F.array(F.slice("e", 1, 2), F.slice("e", 3, 2)))
    zipped = F.arrays_zip(F.transform(halves, lambda x: x["src"]).alias("src"), F.transform(halves, lambda x: x["dst"]).alias("dst"))
    return rows.select("row", F.posexplode(zipped).alias("nth", "pair")).select("row", F.col("nth").cast("long").alias("nth"), F.col("pair")["src"].alias("src"), F.col("pair")["dst"].alias("dst"))


@entry("map A14", """WITH d AS (SELECT event_id // 512 AS chunk, user_id AS src, count(*) AS deg FROM events GROUP BY ALL)
SELECT chunk, CAST(count(*) AS BIGINT) AS keys, CAST(sum(deg * 2) AS BIGINT) AS doubled, CAST(max(CASE WHEN src = 7 THEN deg END) AS BIGINT) AS of_seven, CAST(min(src) AS BIGINT) AS least_key FROM d GROUP BY chunk""")
def scalar_maps(spark, sf_dir):
    """Degree maps of chunks: built from entries, values transformed, looked up, keys and values read back."""
    counts = tables.table(spark, sf_dir, "events").groupBy(F.call_function("div", F.col("event_id"), F.lit(512).cast("long")).alias("chunk"), F.col("user_id").alias("src")).agg(F.count(F.lit(1)).alias("deg"))
    maps = counts.groupBy("chunk").agg(F.map_from_entries(F.collect_list(F.struct("src", "deg"))).alias("held"))
    twice = F.transform_values(F.map_concat("held", F.map_from_arrays(F.array().cast("array<bigint>"), F.array().cast("array<bigint>"))), lambda k, v: v * 2)
    total = F.aggregate(F.map_values(twice), F.lit(0).cast("long"), lambda a, x: a + x)
    return maps.select("chunk", F.size("held").cast("long").alias("keys"), total.alias("doubled"), F.try_element_at("held", F.lit(7).cast("long")).alias("of_seven"), F.array_min(F.map_keys("held")).alias("least_key"))


@entry("json struct", """SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, concat('{"src":', user_id, ',"dst":', json_extract_string(props, '$.k'), '}') AS edge FROM events""")
def scalar_json(spark, sf_dir):
    """JSON read through a schema, and edges written as JSON."""
    parsed = tables.table(spark, sf_dir, "events").withColumn("p", F.from_json("props", "k long"))
    edge = F.to_json(F.struct(F.col("user_id").alias("src"), F.col("p.k").alias("dst")))
    return parsed.select("event_id", F.col("p.k").alias("k"), edge.alias("edge"))


@entry("scalar time", """SELECT event_id, strftime(date_trunc('month', ts), '%Y-%m-%d') AS month, CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS BIGINT) AS day, strftime(ts + INTERVAL 36 HOUR, '%Y-%m-%d %H:%M:%S') AS later,
  CAST(extract(DOW FROM ts) + 1 AS BIGINT) AS weekday FROM events""")
def scalar_times(spark, sf_dir):
    ts = F.col("ts")
    return tables.table(spark, sf_dir, "events").select(
        "event_id", F.date_format(F.date_trunc("month", ts), "yyyy-MM-dd").alias("month"), F.datediff(ts.cast("date"), F.lit("2024-01-01").cast("date")).cast("long").alias("day"),
        F.date_format(ts + F.expr("INTERVAL 36 HOURS"), "yyyy-MM-dd HH:mm:ss").alias("later"), F.dayofweek(ts).cast("long").alias("weekday"),
    )


same("scalar_try_cast", "scalar null type", "SELECT try_cast(substr(url, length(url) - 2, 3) AS BIGINT) AS tail, count(*) AS pages FROM pages GROUP BY try_cast(substr(url, length(url) - 2, 3) AS BIGINT)", "pages")
same("scalar_position", "scalar string", "SELECT page_id, CAST(position('/' IN url) AS BIGINT) AS slash, replace(url, 'http', 'x') AS replaced, trim(concat('  ', url, ' ')) = url AS trimmed FROM pages", "pages")


@entry("C18 N4", "SELECT o_orderkey, row_number() OVER (ORDER BY o_custkey, o_orderkey) - 1 AS at FROM orders")
def dense_positions(spark, sf_dir):
    """Gapless places in an order that is not the table's, in two passes."""
    orders = tables.table(spark, sf_dir, "orders").select("o_custkey", "o_orderkey")
    return dense_position(orders, ["o_custkey", "o_orderkey"], "at").select("o_orderkey", "at")


@entry("hash", "SELECT event_id, md5(event_type || ':' || event_id) AS m, sha256(event_type) AS s, CAST('0x' || substr(md5(CAST(event_id AS VARCHAR)), 1, 8) AS BIGINT) % 64 AS cell FROM events")
def scalar_hashes(spark, sf_dir):
    """Digests as text and as small numbers."""
    digest = F.conv(F.substring(F.md5(F.col("event_id").cast("string")), 1, 8), 16, 10).cast("long")
    return tables.table(spark, sf_dir, "events").select("event_id", F.md5(F.concat_ws(":", "event_type", "event_id")).alias("m"), F.sha2("event_type", 256).alias("s"), (digest % 64).alias("cell"))


@entry("F1 B1", f"WITH ids AS (SELECT o_orderkey AS id FROM orders) {sql_hash('id', 1 << 24)}")
def sql_hash_function(spark, sf_dir):
    """The collision-free hash as a SQL function."""
    register_sql(spark)
    tables.register_views(spark, sf_dir, ["orders"])
    return spark.sql("SELECT o_orderkey AS id, bijective_hash(o_orderkey) AS label FROM orders")
