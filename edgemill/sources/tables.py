"""Graph views over the given tables; every view is (eid, src, dst) with ids dense from 0."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from edgemill.operators.positions import dense_position

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, names: list[str] = TABLES) -> None:
    for name in names:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def size_of(spark: SparkSession, sf_dir: str, name: str) -> int:
    return table(spark, sf_dir, name).count()


def edges_from_table(df: DataFrame, src, dst, order: list[str]) -> DataFrame:
    """Edges of any table; eid is the row's dense position in a total order."""
    return dense_position(df, order).select("eid", F.expr(src).cast("long").alias("src") if isinstance(src, str) else src.cast("long").alias("src"), F.expr(dst).cast("long").alias("dst") if isinstance(dst, str) else dst.cast("long").alias("dst"))


LINE_ORDER = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]


def part_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = size_of(spark, sf_dir, "part")
    return edges_from_table(table(spark, sf_dir, "lineitem"), "l_partkey", f"{parts} + l_suppkey", LINE_ORDER)


def part_supplier_vertices(spark: SparkSession, sf_dir: str) -> int:
    return size_of(spark, sf_dir, "part") + size_of(spark, sf_dir, "supplier")


def order_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = size_of(spark, sf_dir, "orders")
    return edges_from_table(table(spark, sf_dir, "lineitem"), "l_orderkey", f"{orders} + l_partkey", LINE_ORDER)


def customer_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = size_of(spark, sf_dir, "customer")
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("eid"), F.col("o_custkey").alias("src"), (F.lit(customers).cast("long") + F.col("o_orderkey")).alias("dst"))


def user_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From the user of each event to the user of the next in time; the order is total, positions are dense in two levels."""
    steps = dense_position(table(spark, sf_dir, "events").select("ts", "event_id", "user_id"), ["ts", "event_id"])
    after = steps.select((F.col("eid") - 1).alias("eid"), F.col("user_id").alias("dst"))
    return steps.join(after, "eid").select("eid", F.col("user_id").alias("src"), "dst")


def user_event(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events")
    users = events.agg(F.max("user_id") + 1).first()[0]
    return events.select(F.col("event_id").alias("eid"), F.col("user_id").alias("src"), (F.lit(users).cast("long") + F.col("event_id")).alias("dst"), "ts")


def geo_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Regions, nations, suppliers and customers, each under its parent; ids in that order."""
    r, n, s = (size_of(spark, sf_dir, t) for t in ("region", "nation", "supplier"))
    one = lambda t, key, parent, a, b: table(spark, sf_dir, t).select((F.col(key) + a).cast("long").alias("src"), (F.col(parent) + b).cast("long").alias("dst"))
    every = one("nation", "n_nationkey", "n_regionkey", r, 0).unionByName(one("supplier", "s_suppkey", "s_nationkey", r + n, r)).unionByName(one("customer", "c_custkey", "c_nationkey", r + n + s, r))
    return every.select((F.col("src") - r).alias("eid"), "src", "dst")


def encode_vertices(df: DataFrame, column: str, name: str = "id") -> DataFrame:
    """Dense ids of the distinct values of a column, in their order."""
    return dense_position(df.select(column).where(F.col(column).isNotNull()).distinct(), [column], name)


def page_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From pages to the targets of their links; targets come after pages, in text order."""
    pages = table(spark, sf_dir, "pages")
    n = pages.count()
    links = pages.select("page_id", F.posexplode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("nth", "target"))
    coded = links.join(encode_vertices(links, "target"), "target")
    return dense_position(coded, ["page_id", "nth"]).select("eid", F.col("page_id").alias("src"), (F.lit(n).cast("long") + F.col("id")).alias("dst"))


def document_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, word, times): lower-cased runs of ASCII letters; the heavy tail of natural text."""
    words = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.regexp_extract_all("text", F.lit("[A-Za-z]+"), 0)).alias("word"))
    return words.groupBy("doc_id", F.lower("word").alias("word")).agg(F.count(F.lit(1)).alias("times"))


def conversation_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = dense_position(table(spark, sf_dir, "conversations").select("conv_id", "turn"), ["conv_id", "turn"], "id")
    after = turns.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("id").alias("dst"))
    return turns.join(after, ["conv_id", "turn"]).select(F.col("id").alias("src"), "dst")


def label_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From documents to their quality (0, 1) and toxicity (2, 3) marks."""
    labels = table(spark, sf_dir, "labels")
    return labels.select(F.col("doc_id").alias("src"), F.explode(F.array(F.col("quality").cast("long"), F.col("toxic").cast("long") + 2)).alias("dst"))


def vector_label_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("src"), F.col("label").cast("long").alias("dst"))


def benchmark_overlap(spark: SparkSession, sf_dir: str, n: int = 8) -> DataFrame:
    """Documents and benchmark items that share a word n-gram."""
    def grams(name: str, key: str) -> DataFrame:
        words = F.transform(F.regexp_extract_all("text", F.lit("[A-Za-z]+"), 0), lambda w: F.lower(w))
        rows = table(spark, sf_dir, name).select(F.col(key), words.alias("w")).where(F.size("w") >= n)
        each = F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - n + 1), lambda k: F.array_join(F.slice("w", k, n), " ")))
        return rows.select(key, each.alias("gram")).distinct()

    # the items' n-grams are the small side; the join planner sees their size
    return grams("documents", "doc_id").join(grams("benchmark", "item_id"), "gram").groupBy(F.col("doc_id").alias("src"), F.col("item_id").alias("dst")).agg(F.count(F.lit(1)).alias("shared"))


def event_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From users to the key in their events' properties, with times."""
    k = F.get_json_object("props", "$.k").cast("long")
    return table(spark, sf_dir, "events").groupBy(F.col("user_id").alias("src"), k.alias("dst")).agg(F.count(F.lit(1)).alias("times"))


def require_endpoints(edges: DataFrame, n: int) -> dict[str, int]:
    """Counts of null, negative and too large endpoints; raises if any is not 0."""
    bad = lambda f: F.coalesce(F.sum((f("src") | f("dst")).cast("long")), F.lit(0))
    r = edges.agg(
        bad(lambda c: F.col(c).isNull()).alias("null"), bad(lambda c: F.coalesce(F.col(c) < 0, F.lit(False))).alias("negative"), bad(lambda c: F.coalesce(F.col(c) >= n, F.lit(False))).alias("too_large")
    ).first()
    if any(r):
        raise ValueError(f"endpoints outside [0, {n}): {r.asDict()}")
    return r.asDict()
