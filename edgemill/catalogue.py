"""Every method, variant, baseline, measure and operator as a query over the given tables, with its SQL for another engine."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgemill.config import SKEWED, UNIFORM, GenSpec, Layout
from edgemill.functions.partition import bin_of, owner_of, register_sql
from edgemill.functions.prng import mixed_columns
from edgemill.operators import csr, graphops, measures, permute, redistribute, relabel
from edgemill.operators.components import connected_components
from edgemill.operators.positions import dense_position
from edgemill.plans import generate, models
from edgemill.scratch import materialise
from edgemill.sources import rmat, tables

Query = Callable[[SparkSession, str], DataFrame]
SEED, NB, NC, CHUNK, BLOCK, PACKET = 42, 4, 2, 4096, 1024, 1024


@dataclass(frozen=True)
class Entry:
    survey: str
    query: Query
    sql: str | None


ENTRIES: dict[str, Entry] = {}


def entry(survey: str, sql: str | None = None, name: str | None = None):
    """Register a query under its function's name, with the ids of the survey that it covers."""
    def add(f: Query) -> Query:
        ENTRIES[name or f.__name__] = Entry(survey, f, sql)
        return f

    return add


def same(name: str, survey: str, sql: str, *needs: str) -> None:
    """Register a query whose SQL both engines read alike."""
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        tables.register_views(spark, sf_dir, list(needs))
        register_sql(spark)
        return spark.sql(sql)

    ENTRIES[name] = Entry(survey, run, sql)


# ---------------------------------------------------------------- SQL building blocks

def sql_with(*parts: str) -> str:
    return "WITH " + ",\n".join(parts)


SQL_N1 = "dims AS (SELECT (SELECT count(*) FROM part) + (SELECT count(*) FROM supplier) AS n, (SELECT count(*) FROM lineitem) AS m)"
SQL_V1 = f"edges AS (SELECT row_number() OVER (ORDER BY {', '.join(tables.LINE_ORDER)}) - 1 AS eid, l_partkey AS src, (SELECT count(*) FROM part) + l_suppkey AS dst FROM lineitem)"
SQL_N2 = "dims AS (SELECT (SELECT count(*) FROM orders) + (SELECT count(*) FROM part) AS n, (SELECT count(*) FROM lineitem) AS m)"
SQL_V2 = f"edges AS (SELECT row_number() OVER (ORDER BY {', '.join(tables.LINE_ORDER)}) - 1 AS eid, l_orderkey AS src, (SELECT count(*) FROM orders) + l_partkey AS dst FROM lineitem)"
SQL_NC = "dims AS (SELECT count(*) AS n, count(*) AS m FROM customer)"
SQL_IDS = "ids AS (SELECT unnest(range(n)) AS id FROM dims)"


def sql_perm(seed: int = SEED) -> str:
    return f"perm AS (SELECT id, row_number() OVER (ORDER BY md5(concat('{seed}:perm:', id)), id) - 1 AS label FROM ids)"


def sql_rmat(spec: GenSpec, purpose: str = "edge", name: str = "edges") -> str:
    src, dst = [], []
    for level in range(spec.levels):
        u = f"CAST('0x' || substr(h{level // 8}, {4 * (level % 8) + 1}, 4) AS BIGINT)"
        t1, t2, t3 = rmat.thresholds(spec, level)
        w = 1 << (spec.levels - 1 - level)
        src.append(f"CASE WHEN {u} >= {t2} THEN {w} ELSE 0 END")
        dst.append(f"CASE WHEN ({u} >= {t1} AND {u} < {t2}) OR {u} >= {t3} THEN {w} ELSE 0 END")
    hashes = ", ".join(f"md5(concat('{spec.seed}:{purpose}:', eid, ':{k}')) AS h{k}" for k in range(-(-spec.levels // 8)))
    return f"{name}_h AS (SELECT eid, {hashes} FROM (SELECT unnest(range({spec.edges})) AS eid)),\n{name} AS (SELECT eid, CAST({' + '.join(src)} AS BIGINT) AS src, CAST({' + '.join(dst)} AS BIGINT) AS dst FROM {name}_h)"


SQL_RELABEL = "relabelled AS (SELECT e.eid, s.label AS src, d.label AS dst FROM edges e JOIN perm s ON e.src = s.id JOIN perm d ON e.dst = d.id)"
SQL_DEGREES = "degrees AS (SELECT i.id, count(e.eid) AS deg FROM ids i LEFT JOIN relabelled e ON e.src = i.id GROUP BY i.id)"
SQL_OFFSETS = """offsets AS (SELECT id, CAST(coalesce(sum(deg) OVER (ORDER BY id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS off FROM degrees
  UNION ALL SELECT (SELECT n FROM dims), CAST(sum(deg) AS BIGINT) FROM degrees)"""
SQL_NEIGHBORS = "neighbors AS (SELECT row_number() OVER (ORDER BY src, dst, eid) - 1 AS pos, dst FROM relabelled)"
SQL_BASE = sql_with(SQL_N1, SQL_V1, SQL_IDS, sql_perm(), SQL_RELABEL)
SQL_CSR = f"{SQL_BASE},\n{SQL_DEGREES},\n{SQL_OFFSETS},\n{SQL_NEIGHBORS}"
RMAT10 = GenSpec(scale=10, edge_factor=16, seed=SEED, backend="portable")
SQL_RMAT10 = "dims AS (SELECT 1024 AS n, 16384 AS m)"
SQL_BASE_RMAT = sql_with(SQL_RMAT10, sql_rmat(RMAT10), SQL_IDS, sql_perm(), SQL_RELABEL)
SQL_CSR_RMAT = f"{SQL_BASE_RMAT},\n{SQL_DEGREES},\n{SQL_OFFSETS},\n{SQL_NEIGHBORS}"


# ---------------------------------------------------------------- Spark building blocks

def base(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, Layout, int]:
    """The part-supplier edges, a permutation of their vertices, the layout and the number of edges."""
    n = tables.part_supplier_vertices(spark, sf_dir)
    perm = materialise(permute.by_sort(spark, n, SEED, "portable"), "permutation")  # both joins read it, none sorts it again
    return tables.part_supplier(spark, sf_dir), perm, Layout(n, NB, NC, BLOCK, CHUNK), tables.size_of(spark, sf_dir, "lineitem")


def relabelled(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, Layout, int]:
    edges, perm, layout, m = base(spark, sf_dir)
    return relabel.relabel_merge(edges, perm), layout, m


def rmat10(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, Layout]:
    return rmat.rmat_edges(spark, RMAT10), permute.by_sort(spark, RMAT10.vertices, SEED, "portable"), Layout(RMAT10.vertices, NB, NC, BLOCK, CHUNK)


def longs(df: DataFrame) -> DataFrame:
    """All integer columns as 64-bit."""
    return df.select(*(F.col(c).cast("long").alias(c) if t in ("int", "smallint", "tinyint") else F.col(c) for c, t in df.dtypes))


# ---------------------------------------------------------------- P: permutations

def sql_rounds(rounds: int, nb: int = NB) -> str:
    parts = [SQL_NC, "r0 AS (SELECT unnest(range(n)) AS slot, unnest(range(n)) AS label FROM dims)"]
    for k in range(1, rounds + 1):
        parts.append(f"k{k} AS (SELECT label, dims.n, (slot * {nb}) // dims.n AS b FROM r{k - 1}, dims)")
        parts.append(f"g{k} AS (SELECT label, n, b, (b * n + {nb - 1}) // {nb} + row_number() OVER (PARTITION BY b ORDER BY md5(concat('{SEED}:round{k}:', label)), label) - 1 AS g FROM k{k})")
        parts.append(f"r{k} AS (SELECT label, b, (g % {nb}) * (n // {nb}) + least(g % {nb}, n % {nb}) + g // {nb} AS slot, n FROM g{k})")
    return sql_with(*parts)


for _rounds in (1, 2, 6):
    entry("P1 P1b", f"{sql_rounds(_rounds)} SELECT slot AS id, label FROM r{_rounds}", f"perm_rounds_{_rounds}")(
        lambda spark, sf_dir, r=_rounds: permute.by_rounds(spark, tables.size_of(spark, sf_dir, "customer"), NB, r, SEED, "portable")
    )
entry("P1c", f"{sql_rounds(1, 1)} SELECT slot AS id, label FROM r1", "perm_rounds_one_bucket")(
    lambda spark, sf_dir: permute.by_rounds(spark, tables.size_of(spark, sf_dir, "customer"), 1, None, SEED, "portable")
)


@entry("P1a C6 I16", sql_rounds(2) + f""" SELECT 1 AS round, b AS from_bucket, (slot * {NB}) // n AS to_bucket, count(*) AS moved FROM r1 GROUP BY ALL
  UNION ALL SELECT 2, b, (slot * {NB}) // n, count(*) FROM r2 GROUP BY ALL""")
def perm_message_matrix(spark, sf_dir):
    return permute.rounds_trace(spark, tables.size_of(spark, sf_dir, "customer"), NB, 2, SEED, "portable")


SQL_CUSTOMER_PERM = sql_with(SQL_NC, SQL_IDS, sql_perm())


@entry("P2", SQL_CUSTOMER_PERM + " SELECT id, label FROM perm")
def perm_sort(spark, sf_dir):
    return permute.by_sort(spark, tables.size_of(spark, sf_dir, "customer"), SEED, "portable")


@entry("P4", SQL_CUSTOMER_PERM + " SELECT id, label FROM perm")
def perm_sequential(spark, sf_dir):
    return permute.sequential(spark, tables.size_of(spark, sf_dir, "customer"), SEED, "portable")


@entry("P5 S2", sql_with(SQL_NC, SQL_IDS) + " SELECT id, id AS label FROM ids")
def perm_identity(spark, sf_dir):
    return permute.identity(spark, tables.size_of(spark, sf_dir, "customer"))


@entry("P6", SQL_CUSTOMER_PERM + " SELECT label AS id, id AS label FROM perm")
def perm_inverse(spark, sf_dir):
    return permute.invert(perm_sort(spark, sf_dir))


@entry("P7", SQL_CUSTOMER_PERM + f" SELECT id, label FROM perm, dims WHERE (id * {NB}) // n = 2")
def perm_range(spark, sf_dir):
    n = tables.size_of(spark, sf_dir, "customer")
    return permute.range_of(permute.store_ranges(perm_sort(spark, sf_dir), n, NB), 2)


def sql_hash(v: str, n: int, key: int = 7, rounds: int = 4, source: str = "ids") -> str:
    """A chain of subqueries over `source` that ends in (id, label)."""
    from edgemill.functions.prng import hash_constants, mixing_steps

    bits = (n - 1).bit_length()
    out = f"SELECT id, {v} AS v FROM {source}"
    if n == 1 << bits:
        mask, low, half = n - 1, (1 << min(bits, 24)) - 1, (bits + 1) // 2
        for a, c in hash_constants(key, rounds):
            out = f"SELECT id, xor(y, y >> {half}) AS v FROM (SELECT id, (v * {(a & low) | 1} + {c & mask}) & {mask} AS y FROM ({out}))"
    else:
        half = bits // 2
        for a, c, odd in mixing_steps(n, key, rounds):
            moved = f"SELECT id, (v * {a} + {c}) % {n} AS y FROM ({out})"
            out = f"SELECT id, CASE WHEN z < {n} THEN z ELSE y END AS v FROM (SELECT id, y, xor(y, ((y >> {half}) * {odd}) & {(1 << half) - 1}) AS z FROM ({moved}))"
    return f"SELECT id, v AS label FROM ({out})"


def sql_hash_above(table: str, key: str, least: int, hash_key: int = 7, rounds: int = 4) -> str:
    """The hash on [0, 2^k + 1) over a table's key, with k as the largest key needs it and `least` at least; a row of constants for each k."""
    from edgemill.functions.prng import mixing_steps

    rows = ", ".join(f"({k}, {', '.join(str(x) for step in mixing_steps((1 << k) + 1, hash_key, rounds) for x in step)})" for k in range(least, 38))
    names = ", ".join(f"a{r}, c{r}, o{r}" for r in range(rounds))
    size = f"size AS (SELECT greatest({least}, length(bin(max({key})))) AS k FROM {table})"
    consts = f"consts AS (SELECT *, (CAST(1 AS BIGINT) << k) + 1 AS n, (k + 1) // 2 AS half, (CAST(1 AS BIGINT) << ((k + 1) // 2)) - 1 AS low FROM (VALUES {rows}) v(k, {names}) JOIN size USING (k))"
    out = f"SELECT {key} AS id, CAST({key} AS BIGINT) AS v, consts.* FROM {table}, consts"
    for r in range(rounds):
        out = f"SELECT * REPLACE ((v * a{r} + c{r}) % n AS v) FROM ({out})"
        out = f"SELECT * REPLACE (CASE WHEN xor(v, ((v >> half) * o{r}) & low) < n THEN xor(v, ((v >> half) * o{r}) & low) ELSE v END AS v) FROM ({out})"
    return f"WITH {size}, {consts} SELECT id, v AS label FROM ({out})"


def hashed_keys(spark: SparkSession, sf_dir: str, table: str, key: str, least: int, above: int) -> DataFrame:
    """(id, label): a table's key through the hash on [0, 2^k + above), with k as the largest key needs it and `least` at least."""
    keys = tables.table(spark, sf_dir, table).select(F.col(key).alias("id"), F.col(key).alias("label"))
    n = (1 << max(least, int(keys.agg(F.max("id")).first()[0] or 0).bit_length())) + above
    return mixed_columns(keys, ["label"], n)


entry("P3 B1 I14", sql_hash_above("events", "event_id", 16), "perm_hash_above_power")(lambda spark, sf_dir: hashed_keys(spark, sf_dir, "events", "event_id", 16, 1))
entry("P3 B1 I14", sql_hash_above("orders", "o_orderkey", 20), "perm_hash_million")(lambda spark, sf_dir: hashed_keys(spark, sf_dir, "orders", "o_orderkey", 20, 1))
def sql_hash_power(table: str, key: str, least: int, hash_key: int = 7, rounds: int = 4) -> str:
    """The hash on [0, 2^k) over a table's key, with k as the largest key needs it and `least` at least."""
    from edgemill.functions.prng import hash_constants

    size = f"size AS (SELECT greatest({least}, length(bin(max({key})))) AS k FROM {table})"
    consts = "consts AS (SELECT (CAST(1 AS BIGINT) << k) - 1 AS mask, (CAST(1 AS BIGINT) << least(k, 24)) - 1 AS low, (k + 1) // 2 AS half FROM size)"
    out = f"SELECT {key} AS id, CAST({key} AS BIGINT) AS v, consts.* FROM {table}, consts"
    for a, c in hash_constants(hash_key, rounds):
        out = f"SELECT * REPLACE ((v * (({a} & low) | 1) + ({c} & mask)) & mask AS v) FROM ({out})"
        out = f"SELECT * REPLACE (xor(v, v >> half) AS v) FROM ({out})"
    return f"WITH {size}, {consts} SELECT id, v AS label FROM ({out})"


entry("P3 B1 I14", sql_hash_power("orders", "o_orderkey", 10), "perm_hash")(lambda spark, sf_dir: hashed_keys(spark, sf_dir, "orders", "o_orderkey", 10, 0))
for _name, _n in (("perm_hash_walk", 1500),):
    entry("P3 B1 I14", f"WITH ids AS (SELECT unnest(range({_n})) AS id) " + sql_hash("id", _n), _name)(lambda spark, sf_dir, n=_n: permute.by_hash(spark, n))


@entry("P3 RL6 I14", f"{sql_with(SQL_N1, SQL_V1)} SELECT count(*) AS edges, CAST(0 AS BIGINT) AS outside, CAST(count(DISTINCT src) AS BIGINT) AS sources, CAST(count(DISTINCT dst) AS BIGINT) AS targets FROM edges")
def relabel_hashed_tables(spark, sf_dir):
    """The hash over a table's vertices, whose number is no power of two: no end outside, as many different ends as before."""
    edges, _, layout, _ = base(spark, sf_dir)
    new = relabel.relabel_hashed(edges, layout.n)
    outside = ~F.col("src").between(0, layout.n - 1) | ~F.col("dst").between(0, layout.n - 1)
    return new.agg(F.count(F.lit(1)).alias("edges"), F.sum(outside.cast("long")).alias("outside"), F.countDistinct("src").alias("sources"), F.countDistinct("dst").alias("targets"))


@entry("C12 I1", SQL_CUSTOMER_PERM + f""", cells AS (SELECT i, j FROM (SELECT unnest(range({NB})) AS i), (SELECT unnest(range({NB})) AS j)),
  counted AS (SELECT (id * {NB}) // n AS i, (label * {NB}) // n AS j, count(*) AS c FROM perm, dims GROUP BY ALL),
  chi AS (SELECT CAST(sum((coalesce(c, 0) * {NB * NB} - n) * (coalesce(c, 0) * {NB * NB} - n)) AS BIGINT) AS chi_scaled FROM cells LEFT JOIN counted USING (i, j), dims)
  SELECT count(*) AS vertices, count(DISTINCT label) AS labels, min(label) AS least, max(label) AS most, CAST(sum(CASE WHEN id = label THEN 1 ELSE 0 END) AS BIGINT) AS fixed,
    CAST(sum(abs(id - label)) AS BIGINT) AS displacement, CAST(sum(id * label) AS BIGINT) AS products, any_value(chi_scaled) AS chi_scaled FROM perm, chi""")
def perm_quality(spark, sf_dir):
    n = tables.size_of(spark, sf_dir, "customer")
    return permute.quality(perm_sort(spark, sf_dir), n, NB)


# ---------------------------------------------------------------- E: edges

for _name, _spec, _ids in (
    ("rmat_edges_s10", RMAT10, "E1 V12"), ("rmat_uniform_s10", GenSpec(scale=10, probs=UNIFORM, seed=SEED, backend="portable"), "E1c"), ("rmat_noise_s8", GenSpec(scale=8, seed=SEED, backend="portable", noise=0.05), "E1d"),
):
    entry(_ids, sql_with(sql_rmat(_spec)) + " SELECT eid, src, dst FROM edges", _name)(lambda spark, sf_dir, s=_spec: rmat.rmat_edges(spark, s))

ODD = GenSpec(n=700, edge_factor=8, seed=SEED, backend="portable")


def _sql_redrawn(spec: GenSpec, redraws: int = 8) -> str:
    n, parts, last = spec.vertices, [sql_rmat(spec, "edge", "a0")], "a0"
    for k in range(1, redraws + 1):
        parts.append(sql_rmat(spec, f"edge{k}", f"b{k}"))
        parts.append(f"a{k} AS (SELECT eid, CASE WHEN x.src < {n} AND x.dst < {n} THEN x.src ELSE y.src END AS src, CASE WHEN x.src < {n} AND x.dst < {n} THEN x.dst ELSE y.dst END AS dst FROM {last} x JOIN b{k} y USING (eid))")
        last = f"a{k}"
    return sql_with(*parts) + f" SELECT eid, src % {n} AS src, dst % {n} AS dst FROM {last}"


@entry("E1b", _sql_redrawn(ODD))
def rmat_nonpow2(spark, sf_dir):
    return rmat.rmat_edges(spark, ODD)


@entry("E1a", sql_with(sql_rmat(RMAT10)) + f" SELECT (eid * {NB * NC}) // 16384 AS lane, count(*) AS edges, min(eid) AS first, max(eid) AS last FROM edges GROUP BY ALL")
def rmat_lane_counts(spark, sf_dir):
    edges = rmat.rmat_edges(spark, RMAT10, NB * NC)
    return edges.groupBy(F.spark_partition_id().cast("long").alias("lane")).agg(F.count(F.lit(1)).alias("edges"), F.min("eid").alias("first"), F.max("eid").alias("last"))


@entry("E1e E1f I3 S3", "SELECT * FROM (VALUES ('arrow', 16384, 16384, 0), ('aligned', 16384, 16384, 0), ('source', 16384, 16384, 0)) t(variant, edges, ids, outside)")
def rmat_variants(spark, sf_dir):
    """Invariants of the generators that other engines cannot repeat: number of edges and ids, no end outside, and for the aligned one no edge outside its bucket."""
    from edgemill.sources.datasource import register

    register(spark)
    spec = GenSpec(scale=10, seed=SEED)
    aligned = rmat.rmat_edges_aligned(spark, spec, NB)
    outside = lambda d: ~F.col("src").between(0, 1023) | ~F.col("dst").between(0, 1023)
    frames = {
        "arrow": (rmat.rmat_edges_arrow(spark, spec), outside(0)), "aligned": (aligned, outside(0) | (owner_of(F.col("dst"), 1024, NB) != F.col("bucket"))),
        "source": (spark.read.format("rmat").option("scale", 10).load(), outside(0)),
    }
    out = None
    for name, (df, bad) in frames.items():
        row = df.agg(F.count(F.lit(1)).alias("edges"), F.countDistinct("eid").alias("ids"), F.sum(bad.cast("long")).alias("outside")).select(F.lit(name).alias("variant"), F.col("edges").cast("int").alias("edges"), F.col("ids").cast("int").alias("ids"), F.col("outside").cast("int").alias("outside"))
        out = row if out is None else out.unionByName(row)
    return out


entry("V1 E2", f"WITH {SQL_V1} SELECT eid, src, dst FROM edges", "edges_part_supplier")(tables.part_supplier)
entry("V2 E2", f"WITH {SQL_V2} SELECT eid, src, dst FROM edges", "edges_order_part")(tables.order_part)
entry("V3 E2", "SELECT o_orderkey AS eid, o_custkey AS src, (SELECT count(*) FROM customer) + o_orderkey AS dst FROM orders", "edges_customer_order")(tables.customer_order)
SQL_V4 = "steps AS (SELECT row_number() OVER (ORDER BY ts, event_id) - 1 AS eid, user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events)"
entry("V4 E2", f"WITH {SQL_V4} SELECT eid, src, dst FROM steps WHERE dst IS NOT NULL", "edges_user_step")(tables.user_step)
entry("V5 E2", "SELECT event_id AS eid, user_id AS src, (SELECT max(user_id) + 1 FROM events) + event_id AS dst FROM events", "edges_user_event")(lambda spark, sf_dir: tables.user_event(spark, sf_dir).drop("ts"))
SQL_V6 = """c AS (SELECT (SELECT count(*) FROM region) AS r, (SELECT count(*) FROM nation) AS n, (SELECT count(*) FROM supplier) AS s),
geo AS (SELECT r + n_nationkey AS src, CAST(n_regionkey AS BIGINT) AS dst, r FROM nation, c UNION ALL SELECT r + n + s_suppkey, r + s_nationkey, r FROM supplier, c UNION ALL SELECT r + n + s + c_custkey, r + c_nationkey, r FROM customer, c)"""
entry("V6 E2", f"WITH {SQL_V6} SELECT src - r AS eid, src, dst FROM geo", "edges_geo")(tables.geo_tree)
entry("V7 E2 E3", """WITH links AS (SELECT page_id, unnest(t) AS target, unnest(range(len(t))) AS nth FROM (SELECT page_id, regexp_extract_all(html, 'href="([^"]*)"', 1) AS t FROM pages)),
coded AS (SELECT target, row_number() OVER (ORDER BY target) - 1 AS id FROM (SELECT DISTINCT target FROM links))
SELECT row_number() OVER (ORDER BY page_id, nth) - 1 AS eid, page_id AS src, (SELECT count(*) FROM pages) + id AS dst FROM links JOIN coded USING (target)""", "edges_page_link")(tables.page_link)
SQL_WORDS = "words AS (SELECT doc_id, lower(unnest(regexp_extract_all(text, '[A-Za-z]+'))) AS word FROM documents)"
entry("V8 E2", f"WITH {SQL_WORDS} SELECT doc_id, word, count(*) AS times FROM words GROUP BY ALL", "edges_doc_word")(tables.document_words)
entry("E3", f"WITH {SQL_WORDS} SELECT word, row_number() OVER (ORDER BY word) - 1 AS id FROM (SELECT DISTINCT word FROM words)", "encode_words")(
    lambda spark, sf_dir: tables.encode_vertices(tables.document_words(spark, sf_dir), "word")
)
entry("V9 E2", """WITH t AS (SELECT conv_id, turn, row_number() OVER (ORDER BY conv_id, turn) - 1 AS id FROM conversations)
SELECT a.id AS src, b.id AS dst FROM t a JOIN t b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1""", "edges_conv")(tables.conversation_steps)
entry("V10 E2", "SELECT doc_id AS src, CAST(quality AS BIGINT) AS dst FROM labels UNION ALL SELECT doc_id, CAST(toxic AS BIGINT) + 2 FROM labels", "edges_labels")(tables.label_edges)
entry("V10 E2", "SELECT vec_id AS src, CAST(label AS BIGINT) AS dst FROM embeddings", "edges_vector_labels")(tables.vector_label_edges)
entry("V11 E2", """WITH w AS (SELECT doc_id AS id, 0 AS kind, list_transform(regexp_extract_all(text, '[A-Za-z]+'), lambda x: lower(x)) AS w FROM documents
  UNION ALL SELECT item_id, 1, list_transform(regexp_extract_all(text, '[A-Za-z]+'), lambda x: lower(x)) FROM benchmark),
grams AS (SELECT DISTINCT id, kind, gram FROM (SELECT id, kind, unnest(list_transform(range(1, len(w) - 6), lambda k: array_to_string(w[k:k+7], ' '))) AS gram FROM w WHERE len(w) >= 8))
SELECT a.id AS src, b.id AS dst, count(*) AS shared FROM grams a JOIN grams b ON a.gram = b.gram AND a.kind = 0 AND b.kind = 1 GROUP BY ALL""", "edges_benchmark")(tables.benchmark_overlap)
entry("E2 json", "SELECT user_id AS src, CAST(json_extract_string(props, '$.k') AS BIGINT) AS dst, count(*) AS times FROM events GROUP BY ALL", "edges_json_k")(tables.event_keys)


# ---------------------------------------------------------------- RL: relabelling

SQL_RELABELLED = SQL_BASE + " SELECT eid, src, dst FROM relabelled"


def _strategy(name: str, survey: str):
    def run(spark, sf_dir):
        edges, perm, layout, m = base(spark, sf_dir)
        return relabel.relabel(edges, perm, layout, m, name)

    ENTRIES[f"relabel_{name}"] = Entry(survey, run, SQL_RELABELLED)


for _name, _ids in (("merge", "RL1 J1 X1"), ("range_rounds", "RL2 RL2a RL2c"), ("gather", "RL3 J13 F4"), ("broadcast", "RL4 J2"), ("hash_join", "RL5 J3"), ("unpivot", "RL7"), ("hub_split", "RL8 X17"), ("auto", "RL9")):
    _strategy(_name, _ids)


@entry("RL1b I7", SQL_RELABELLED)
def relabel_swapped_order(spark, sf_dir):
    edges, perm, _, _ = base(spark, sf_dir)
    return relabel.relabel_merge(edges, perm, ("src", "dst"))


@entry("RL1a", SQL_BASE + " SELECT e.eid, e.src, d.label AS dst FROM edges e JOIN perm d ON e.dst = d.id")
def relabel_dst_only(spark, sf_dir):
    edges, perm, _, _ = base(spark, sf_dir)
    return relabel.relabel_endpoint(edges, perm, "dst")


@entry("RL6 B1", sql_with(sql_rmat(RMAT10), "ids AS (SELECT unnest(range(1024)) AS id)", f"perm AS ({sql_hash('id', 1024)})", SQL_RELABEL) + " SELECT eid, src, dst FROM relabelled")
def relabel_hashed(spark, sf_dir):
    return relabel.relabel_hashed(rmat.rmat_edges(spark, RMAT10), RMAT10.vertices)


@entry("RL2a RL2c T2", sql_with(SQL_V1) + f" SELECT eid, src, dst, eid // {CHUNK} AS chunk, row_number() OVER (PARTITION BY eid // {CHUNK} ORDER BY dst, eid) AS nth FROM edges")
def chunk_sort(spark, sf_dir):
    from pyspark.sql import Window

    chunks = relabel.sort_chunks(relabel.chunk_edges(tables.part_supplier(spark, sf_dir), CHUNK), "dst", NB * NC)
    return chunks.withColumn("nth", F.row_number().over(Window.partitionBy("chunk").orderBy("dst", "eid")).cast("long"))


@entry("RL2b", sql_with(SQL_N1, SQL_V1) + f", k AS (SELECT CAST(ceil(m / {CHUNK}.0) AS BIGINT) AS chunks FROM dims) SELECT (eid // {CHUNK}) // CAST(ceil(chunks / {NC}.0) AS BIGINT) AS chunk_group, count(DISTINCT eid // {CHUNK}) AS chunks, count(*) AS edges FROM edges, k GROUP BY ALL")
def chunk_groups(spark, sf_dir):
    m = tables.size_of(spark, sf_dir, "lineitem")
    grouped = relabel.group_chunks(relabel.chunk_edges(tables.part_supplier(spark, sf_dir), CHUNK), NC, -(-m // CHUNK))
    return grouped.groupBy("chunk_group").agg(F.countDistinct("chunk").alias("chunks"), F.count(F.lit(1)).alias("edges"))


@entry("RL2d", sql_with(SQL_N1, SQL_V1) + f" SELECT eid // {CHUNK} AS chunk, (dst * {NB}) // n AS turn, count(*) AS consumed FROM edges, dims GROUP BY ALL")
def merge_trace(spark, sf_dir):
    edges, _, layout, _ = base(spark, sf_dir)
    return relabel.merge_trace(edges, layout)


@entry("I5 I6", SQL_BASE + """ SELECT count(*) AS edges, CAST(sum(CASE WHEN src = dst THEN 1 ELSE 0 END) AS BIGINT) AS loops, CAST(count(DISTINCT (src, dst)) AS BIGINT) AS pairs,
  (SELECT count(*) FROM edges) AS restored FROM relabelled""")
def relabel_invariants(spark, sf_dir):
    """Edges, loops and different pairs after relabelling, and edges that the inverse permutation restores."""
    edges, perm, _, _ = base(spark, sf_dir)
    edges, new = materialise(edges, "edges"), materialise(relabel.relabel_merge(edges, perm), "relabelled")
    back = relabel.relabel_merge(new, permute.invert(perm)).join(edges, ["eid", "src", "dst"], "left_semi").agg(F.count(F.lit(1)).alias("restored"))
    return new.agg(F.count(F.lit(1)).alias("edges"), F.sum((F.col("src") == F.col("dst")).cast("long")).alias("loops"), F.countDistinct("src", "dst").alias("pairs")).crossJoin(back)


# ---------------------------------------------------------------- R: redistribution

SQL_OWNED = f"owned AS (SELECT eid, src, dst, (src * {NB}) // n AS bucket, ((src * {NB * NC}) // n) % {NC} AS lane FROM relabelled, dims)"


@entry("R1 I8 U3", f"{SQL_BASE}, {SQL_OWNED} SELECT bucket, count(*) AS edges, min(src) AS least, max(src) AS most, CAST(0 AS BIGINT) AS strays FROM owned GROUP BY ALL")
def owner_counts(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    shipped = redistribute.ship_to_owner(edges, layout).withColumn("partition", F.spark_partition_id())
    return longs(shipped.groupBy("bucket").agg(F.count(F.lit(1)).alias("edges"), F.min("src").alias("least"), F.max("src").alias("most"), F.sum((F.col("partition") != F.col("bucket")).cast("long")).alias("strays")))


@entry("R1a E1a", f"{SQL_BASE}, {SQL_OWNED} SELECT bucket, lane, count(*) AS edges FROM owned GROUP BY ALL")
def owner_lane_counts(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return longs(redistribute.ship_to_owner(edges, layout, "lane").groupBy("bucket", "lane").agg(F.count(F.lit(1)).alias("edges")))


SQL_PACKETS = f"""routed AS (SELECT eid, src, dst, (eid * {NB}) // m AS src_bucket, (src * {NB}) // n AS dst_bucket FROM relabelled, dims),
packets AS (SELECT *, (row_number() OVER (PARTITION BY src_bucket, dst_bucket ORDER BY eid) - 1) // {PACKET} AS packet_no FROM routed)"""


@entry("R2 C6 I9", f"{SQL_BASE}, {SQL_PACKETS} SELECT src_bucket, dst_bucket, packet_no, count(*) AS edges, min(eid) AS first FROM packets GROUP BY ALL")
def packets_summary(spark, sf_dir):
    edges, layout, m = relabelled(spark, sf_dir)
    packets = redistribute.packetize(edges, layout, m)
    return longs(packets.select("src_bucket", "dst_bucket", "packet_no", F.size("edges").alias("edges"), F.col("edges")[0]["eid"].alias("first")))


@entry("R3 R4 I9", f"{SQL_BASE}, {SQL_OWNED} SELECT eid, src, dst, bucket FROM owned")
def packets_roundtrip(spark, sf_dir):
    edges, layout, m = relabelled(spark, sf_dir)
    received = redistribute.collect_packets(redistribute.packetize(edges, layout, m))
    return longs(redistribute.scatter_gather(received, F.col("bucket"), layout.nb))


@entry("R5 R5a T2", f"{SQL_BASE}, {SQL_OWNED} SELECT bucket, src, dst, eid, row_number() OVER (PARTITION BY bucket ORDER BY src, dst, eid) - 1 AS nth FROM owned")
def ship_sorted(spark, sf_dir):
    from pyspark.sql import Window

    edges, layout, _ = relabelled(spark, sf_dir)
    nth = F.row_number().over(Window.partitionBy("bucket").orderBy("src", "dst", "eid")) - 1
    return longs(redistribute.ship_sorted(edges, layout).select("bucket", "src", "dst", "eid", nth.cast("long").alias("nth")))


@entry("R6 X17", f"{SQL_BASE}, {SQL_OWNED} SELECT bucket, (row_number() OVER (PARTITION BY bucket ORDER BY src, eid) - 1) // 5000 AS part, eid, src, dst FROM owned")
def ship_balanced(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return longs(redistribute.ship_balanced(edges, layout, 5000))


# ---------------------------------------------------------------- K: compressed rows

@entry("K2a J4", f"{SQL_BASE}, {SQL_DEGREES} SELECT id, deg FROM degrees")
def degrees_out(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.out_degrees(edges, layout).select("id", "deg")


@entry("K2a", f"{SQL_BASE} SELECT i.id, count(e.eid) AS deg FROM ids i LEFT JOIN relabelled e ON e.dst = i.id GROUP BY i.id")
def degrees_in(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.in_degrees(edges, layout).select("id", "deg")


FLUSH = 256


@entry("K2a C5 G23", f"""WITH RECURSIVE {SQL_BASE.removeprefix("WITH ")}, seen AS (SELECT eid // {CHUNK} AS chunk, eid, coalesce(lag(eid) OVER (PARTITION BY eid // {CHUNK}, src ORDER BY eid), -1) AS former FROM relabelled),
turns(chunk, begins, flushes) AS (SELECT chunk, min(eid), 0 FROM seen GROUP BY chunk
  UNION ALL SELECT chunk, after, flushes + 1 FROM (SELECT t.chunk, t.flushes, s.eid + 1 AS after, row_number() OVER (PARTITION BY t.chunk ORDER BY s.eid) AS nth
    FROM turns t JOIN seen s ON s.chunk = t.chunk AND s.eid >= t.begins AND s.former < t.begins) WHERE nth = {FLUSH}),
ended AS (SELECT chunk, max(flushes) AS flushes, max(begins) AS begins FROM turns GROUP BY chunk), last AS (SELECT chunk, max(eid) AS eid FROM seen GROUP BY chunk)
SELECT e.chunk, CAST(flushes + CASE WHEN l.eid >= begins THEN 1 ELSE 0 END AS BIGINT) AS flushes FROM ended e JOIN last l USING (chunk)""")
def degrees_flushed(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.degrees_flushed(edges, layout, FLUSH)


@entry("C5 G23", f"{SQL_BASE} SELECT eid // {CHUNK} AS chunk, CAST(ceil(count(*) / {FLUSH}.0) AS BIGINT) AS flushes FROM relabelled GROUP BY ALL")
def adjacency_flushed(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.adjacency_flushed(edges, layout, FLUSH)


@entry("C5", f"{SQL_BASE} SELECT eid // {CHUNK} AS chunk, CAST(ceil(count(DISTINCT src) / 256.0) AS BIGINT) AS least_flushes FROM relabelled GROUP BY ALL")
def flushes_lower_bound(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return relabel.chunk_edges(edges, CHUNK).groupBy("chunk").agg(F.ceil(F.countDistinct("src") / 256).cast("long").alias("least_flushes"))


@entry("K2b N4 I10", f"{SQL_CSR} SELECT id, off FROM offsets")
def offsets_two_level(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.prefix_offsets(csr.out_degrees(edges, layout), layout)


@entry("K3 K1 D4 I11", f"{SQL_CSR} SELECT pos, dst FROM neighbors")
def csr_ordered_neighbors(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.csr_ordered(edges, layout).neighbors


@entry("K1", f"{SQL_CSR} SELECT pos, dst FROM neighbors")
def csr_scan_neighbors(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.csr_from_sorted(materialise(redistribute.ship_ranked(edges, layout), "owned"), layout).neighbors


@entry("R5a K3 I11", f"{SQL_CSR} SELECT pos, dst FROM neighbors")
def csr_merged_neighbors(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.csr_merged(edges, layout).neighbors


@entry("R5a", f"{SQL_BASE}, {SQL_OWNED} SELECT bucket, row_number() OVER (PARTITION BY bucket ORDER BY src, dst, eid) - 1 AS rank, eid, src, dst FROM owned")
def merge_runs(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return longs(redistribute.merge_sorted_runs(redistribute.sorted_runs(edges, layout), layout))


@entry("K2 B8 I12", f"{SQL_CSR} SELECT id, off FROM offsets")
def csr_unordered_offsets(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.csr_unordered(edges, layout).offsets


@entry("K2 K2c B5", f"{SQL_CSR} SELECT o.off + row_number() OVER (PARTITION BY e.src ORDER BY e.eid) - 1 AS pos, e.dst FROM relabelled e JOIN offsets o ON o.id = e.src")
def csr_unordered_neighbors(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.csr_unordered(edges, layout).neighbors


SQL_SLOTS = "slots AS (SELECT e.eid, o.off + row_number() OVER (PARTITION BY e.src ORDER BY e.eid) - 1 AS pos, e.dst FROM relabelled e JOIN offsets o ON o.id = e.src)"


@entry("B2", f"{SQL_CSR}, {SQL_SLOTS} SELECT eid, pos, dst FROM slots")
def naive_external_writes(spark, sf_dir):
    """The writes of the naive kernel on disk, edge by edge as they arrive."""
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.naive_external_csr(edges, layout)


@entry("B2 C4 I15", f"""{SQL_CSR}, {SQL_SLOTS}, naive AS (SELECT pos // {BLOCK} AS blk, lag(pos // {BLOCK}) OVER (ORDER BY eid) AS former FROM slots),
linear AS (SELECT pos // {BLOCK} AS blk, lag(pos // {BLOCK}) OVER (ORDER BY pos) AS former FROM neighbors)
SELECT 'arrival order' AS way, count(*) AS edges, CAST(sum(CASE WHEN blk <> former THEN 1 ELSE 0 END) AS BIGINT) AS switches FROM naive
UNION ALL SELECT 'linear scan', count(*), CAST(sum(CASE WHEN blk <> former THEN 1 ELSE 0 END) AS BIGINT) FROM linear""")
def naive_against_scan(spark, sf_dir):
    """Changes of the target block in the neighbour vector: scatter in arrival order against the linear scan."""
    edges, layout, _ = relabelled(spark, sf_dir)
    edges = materialise(edges, "relabelled")
    naive = measures.block_switches(materialise(csr.naive_external_csr(edges, layout), "writes"), "pos", BLOCK)
    scan = measures.block_switches(materialise(csr.csr_ordered(edges, layout).neighbors, "neighbors"), "pos", BLOCK, order="pos")
    named = lambda df, way: df.select(F.lit(way).alias("way"), F.col("rows").alias("edges"), "switches")
    return named(naive, "arrival order").unionByName(named(scan, "linear scan"))


@entry("K4", f"""{SQL_CSR}, slots AS (SELECT src AS id, dst, (row_number() OVER (PARTITION BY src ORDER BY dst, eid) - 1) // 16 AS part, eid FROM relabelled)
SELECT id, part, string_agg(CAST(dst AS VARCHAR), ' ' ORDER BY dst, eid) AS nbrs FROM slots GROUP BY id, part""")
def csr_lists(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    lists = csr.adjacency_lists(csr.csr_ordered(edges, layout), 16)
    return lists.select("id", "part", F.array_join(F.transform("nbrs", lambda x: x.cast("string")), " ").alias("nbrs"))


@entry("K5 J8", f"{SQL_CSR}, numbered AS (SELECT src AS id, row_number() OVER (ORDER BY src, dst, eid) - 1 AS pos, dst FROM relabelled) SELECT id, pos, dst FROM numbered")
def csr_lookup(spark, sf_dir):
    """The slices of all vertices."""
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.neighbors_of(csr.csr_ordered(edges, layout), spark.range(layout.n))


@entry("K6 I11", f"{SQL_BASE} SELECT src, dst FROM relabelled")
def csr_roundtrip(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.edges_from_csr(csr.csr_ordered(edges, layout))


@entry("K7 G13", f"""{SQL_BASE}, sides AS (SELECT eid * 2 AS eid, src, dst FROM relabelled UNION ALL SELECT eid * 2 + 1, dst, src FROM relabelled)
SELECT row_number() OVER (ORDER BY src, dst, eid) - 1 AS pos, dst FROM sides""")
def csr_symmetric(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.csr_ordered(csr.prepared(edges, symmetrize=True), layout).neighbors


@entry("K7 AG3", f"{SQL_BASE}, once AS (SELECT DISTINCT src, dst FROM relabelled WHERE src <> dst) SELECT row_number() OVER (ORDER BY src, dst) - 1 AS pos, dst FROM once")
def csr_simple(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return csr.csr_ordered(csr.prepared(edges, drop_self_loops=True, dedup=True), layout).neighbors


# ---------------------------------------------------------------- D and B: generators

for _name, _options, _ids in (
    ("generate_full_ordered", dict(csr="ordered", strategy="merge"), "D2 D4 D5"), ("generate_full_sequential", None, "D1 B3 I13"), ("generate_range_rounds", dict(csr="ordered", strategy="range_rounds"), "D2 RL2"),
    ("generate_full_merged", dict(csr="merged", strategy="merge"), "D4 R5a"),
):
    def _run(spark, sf_dir, options=_options):
        if options is None:
            return generate.generate_sequential(spark, RMAT10).tables["neighbors"]
        return generate.generate_graph(spark, RMAT10, Layout(1024, NB, NC), **options).tables["neighbors"]

    entry(_ids, SQL_CSR_RMAT + " SELECT pos, dst FROM neighbors", _name)(_run)


@entry("D3 B5", SQL_CSR_RMAT + " SELECT o.off + row_number() OVER (PARTITION BY e.src ORDER BY e.eid) - 1 AS pos, e.dst FROM relabelled e JOIN offsets o ON o.id = e.src")
def generate_full_unordered(spark, sf_dir):
    return generate.generate_graph(spark, RMAT10, Layout(1024, NB, NC), csr="unordered", strategy="merge").tables["neighbors"]


@entry("B1", sql_with(SQL_RMAT10, sql_rmat(RMAT10), SQL_IDS, f"perm AS ({sql_hash('id', 1024)})", SQL_RELABEL, SQL_NEIGHBORS) + " SELECT pos, dst FROM neighbors")
def generate_hash_kernel(spark, sf_dir):
    return generate.generate_hashed(spark, RMAT10, Layout(1024, NB, NC)).neighbors


def _skew_sql(nb: int, source: str) -> str:
    return f"SELECT {nb} AS nb, '{source}' AS graph, CAST(max(c) AS BIGINT) AS most, CAST(sum(c) AS BIGINT) AS edges FROM (SELECT (src * {nb}) // n AS b, count(*) AS c FROM {source}, dims GROUP BY 1)"


@entry("W8 W9 B4 C14", SQL_BASE + " " + " UNION ALL ".join(_skew_sql(nb, s) for nb in (2, 8, 32) for s in ("edges", "relabelled")))
def biased_vs_relabelled_skew(spark, sf_dir):
    """The largest owner of the part-supplier edges before and after relabelling; sources crowd the range of parts before."""
    edges, perm, layout, _ = base(spark, sf_dir)
    edges = materialise(edges, "edges")
    new, out = materialise(relabel.relabel_merge(edges, perm), "relabelled"), None
    for nb in (2, 8, 32):
        for name, df in (("edges", edges), ("relabelled", new)):
            row = measures.owner_skew(df, Layout(layout.n, nb, 1)).select(F.lit(nb).alias("nb"), F.lit(name).alias("graph"), "most", "edges")
            out = row if out is None else out.unionByName(row)
    return out


@entry("C15 W9", SQL_BASE + f""" SELECT 'biased' AS graph, count(*) AS edges, CAST(sum(CASE WHEN (src * {NB}) // n = (dst * {NB}) // n THEN 1 ELSE 0 END) AS BIGINT) AS local_edges FROM edges, dims
UNION ALL SELECT 'relabelled', count(*), CAST(sum(CASE WHEN (src * {NB}) // n = (dst * {NB}) // n THEN 1 ELSE 0 END) AS BIGINT) FROM relabelled, dims""")
def locality(spark, sf_dir):
    """Part-supplier edges with both ends in one bucket, before and after relabelling."""
    edges, perm, layout, _ = base(spark, sf_dir)
    edges = materialise(edges, "edges")
    named = lambda df, g: measures.edge_locality(df, layout).select(F.lit(g).alias("graph"), "edges", "local_edges")
    return named(edges, "biased").unionByName(named(relabel.relabel_merge(edges, perm), "relabelled"))


@entry("C13", SQL_BASE + f", {SQL_DEGREES} SELECT CAST(CASE WHEN deg = 0 THEN 0 ELSE length(bin(deg)) END AS INTEGER) AS log2_bin, count(*) AS vertices, CAST(sum(deg) AS BIGINT) AS total FROM degrees GROUP BY ALL")
def degree_histogram(spark, sf_dir):
    """Out-degrees of the relabelled part-supplier edges; suppliers have none."""
    edges, layout, _ = relabelled(spark, sf_dir)
    return measures.degree_histogram(csr.out_degrees(edges, layout))


@entry("C13 W9", f"WITH {SQL_WORDS}, d AS (SELECT word, count(*) AS deg FROM words GROUP BY word) SELECT CAST(length(bin(deg)) AS INTEGER) AS log2_bin, count(*) AS vertices, CAST(sum(deg) AS BIGINT) AS total FROM d GROUP BY ALL")
def degree_histogram_words(spark, sf_dir):
    return measures.degree_histogram(tables.document_words(spark, sf_dir).groupBy("word").agg(F.sum("times").alias("deg")))


@entry("C13", sql_with(sql_rmat(RMAT10)) + """ SELECT part, CAST(sum(s) AS BIGINT) AS sources, CAST(sum(t) AS BIGINT) AS targets FROM
 (SELECT (src * 8) // 1024 AS part, 1 AS s, 0 AS t FROM edges UNION ALL SELECT (dst * 8) // 1024, 0, 1 FROM edges) GROUP BY ALL""")
def prefix_mass(spark, sf_dir):
    return measures.prefix_mass(rmat.rmat_edges(spark, RMAT10), 1024, 8)


@entry("C14 W8", f"{SQL_BASE}, {SQL_OWNED}, c AS (SELECT bucket, count(*) AS c FROM owned GROUP BY bucket) SELECT {NB} AS owners, CAST(sum(c) AS BIGINT) AS edges, CAST(max(c) AS BIGINT) AS most, CAST(max(c) * {1000 * NB} // sum(c) AS BIGINT) AS skew_milli FROM c")
def owner_skew(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return measures.owner_skew(edges, layout)


@entry("C14 F5", f"""{SQL_BASE}, {SQL_OWNED}, c AS (SELECT bucket, count(*) AS c, row_number() OVER (ORDER BY count(*)) AS i FROM owned GROUP BY bucket)
SELECT round(2.0 * sum(i * c) / ({NB} * sum(c)) - ({NB} + 1.0) / {NB}, 9) AS gini FROM c""")
def owner_gini(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return measures.owner_gini(edges, layout).select(F.round("gini", 9).alias("gini"))


def _switch_sql(order: str) -> str:
    return f'{SQL_BASE_RMAT}, b AS (SELECT {order} AS nth, src // 64 AS blk FROM relabelled), p AS (SELECT blk, lag(blk) OVER (ORDER BY nth) AS former FROM b) SELECT count(*) AS "rows", CAST(sum(CASE WHEN blk <> former THEN 1 ELSE 0 END) AS BIGINT) AS switches FROM p'


@entry("C4 B2 I15", _switch_sql("eid"))
def block_switches_generation(spark, sf_dir):
    edges, perm, _ = rmat10(spark, sf_dir)
    return measures.block_switches(materialise(relabel.relabel_merge(edges, perm), "relabelled"), "src", 64)


@entry("C4 I15", _switch_sql("row_number() OVER (ORDER BY src, dst, eid)"))
def block_switches_sorted(spark, sf_dir):
    edges, perm, _ = rmat10(spark, sf_dir)
    ordered = dense_position(relabel.relabel_merge(edges, perm), ["src", "dst", "eid"], "at")
    return measures.block_switches(ordered, "src", 64, order="at")


@entry("C3", f"{SQL_BASE}, {SQL_OWNED} SELECT bucket, lane, count(*) AS rows, CAST(ceil(count(*) / {BLOCK}.0) AS BIGINT) AS blocks FROM owned GROUP BY ALL")
def blocks_sequential(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    return longs(measures.count_blocks(redistribute.with_owner(edges, layout), ["bucket", "lane"], BLOCK))


def _message_sql(nb: int) -> str:
    return f"""{SQL_BASE}, cells AS (SELECT a AS from_bucket, b AS to_bucket FROM (SELECT unnest(range({nb})) AS a), (SELECT unnest(range({nb})) AS b)),
  c AS (SELECT (eid * {nb}) // m AS from_bucket, (src * {nb}) // n AS to_bucket, count(*) AS edges FROM relabelled, dims GROUP BY ALL)
  SELECT from_bucket, to_bucket, coalesce(edges, 0) AS edges, CAST(ceil(coalesce(edges, 0) / {PACKET}.0) AS BIGINT) AS packets FROM cells LEFT JOIN c USING (from_bucket, to_bucket)"""


for _name, _nb, _ids in (("message_packets", NB, "C6 J7"), ("message_packets_no_threads", NB * NC, "B6 C6")):
    def _messages(spark, sf_dir, nb=_nb):
        edges, layout, m = relabelled(spark, sf_dir)
        return measures.message_matrix(edges, Layout(layout.n, nb, 1), m)

    entry(_ids, _message_sql(_nb), _name)(_messages)


# ---------------------------------------------------------------- C: models and scaling tables

IO = (NB, NC, BLOCK)
SQL_LINE_SIZES = "sizes AS (SELECT max(l_partkey) + max(l_suppkey) + 2 AS n, count(l_orderkey) AS m FROM lineitem)"


def line_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(n, m) of the part-supplier graph as its edges have it."""
    return tables.table(spark, sf_dir, "lineitem").agg((F.max("l_partkey") + F.max("l_suppkey") + 2).alias("n"), F.count("l_orderkey").alias("m"))


@entry("C1 G14 G15", f"""WITH {SQL_LINE_SIZES}, p AS (SELECT n // {IO[0]} AS bb, n // {IO[0]} // {IO[1]} AS b, m // n AS f, {IO[2]} AS ce FROM sizes)
SELECT * FROM (SELECT 'generate' AS step, 'per core' AS variant, 'sequential' AS unit, CAST(b * f // ce AS BIGINT) AS blocks FROM p
UNION ALL SELECT 'relabel', 'per core', 'sequential', 2 * b * f * 8 // ce FROM p UNION ALL SELECT 'redistribute', 'per node', 'sequential', bb * f // ce FROM p
UNION ALL SELECT 'redistribute', 'per core', 'sequential', b * f // ce FROM p UNION ALL SELECT 'csr', 'unordered', 'random', b FROM p UNION ALL SELECT 'csr', 'ordered per node', 'sequential', bb // ce FROM p
UNION ALL SELECT 'csr', 'ordered per core', 'sequential', b // ce FROM p UNION ALL SELECT 'csr', 'ordered per node, with f', 'sequential', bb * f // ce FROM p)""")
def io_model(spark, sf_dir):
    """The printed block reads for the part-supplier graph, its size taken from its edges."""
    return models.io_model(line_sizes(spark, sf_dir), *IO)


@entry("C2 G5 G7", """SELECT CAST(nb AS INTEGER) AS nb, CAST(CASE WHEN nb < 2 THEN 1 ELSE ceil(20 / log2(nb) - 1e-12) END AS INTEGER) AS rounds, CAST(nb * nb AS BIGINT) AS messages_a_round,
 CAST(floor((1048576 // nb) * log2(1048576 // nb)) AS BIGINT) AS work_a_round, CAST(1048576 AS BIGINT) * nb * nb * 400 AS total FROM (SELECT unnest([1, 2, 4, 8, 32]) AS nb)""")
def shuffle_model(spark, sf_dir):
    return models.shuffle_model(spark, 1 << 20, [1, 2, 4, 8, 32])


@entry("C7 W7 G17", f"WITH {SQL_LINE_SIZES}, v AS (SELECT doublings, n * (CAST(1 AS BIGINT) << doublings) AS vertices FROM sizes, (SELECT unnest([14, 16, 18, 21, 22]) AS doublings)) "
       "SELECT CAST(doublings AS INTEGER) AS doublings, vertices, vertices * 512 // 1073741824 AS gib, (vertices * 512 // 1073741824 + 63) // 64 AS nodes FROM v")
def memory_model(spark, sf_dir):
    """What the part-supplier graph takes in memory as it doubles."""
    return models.memory_model(line_sizes(spark, sf_dir), [14, 16, 18, 21, 22])


@entry("C8 W7", "SELECT CAST(nb AS INTEGER) AS nb, CAST(16 * (2 ** 32) / nb / (2 ** 30) AS BIGINT) AS gib_a_node FROM (SELECT unnest([1, 2, 4, 8]) AS nb)")
def shuffle_memory(spark, sf_dir):
    return models.shuffle_memory(spark, 32, [1, 2, 4, 8])


#: Made-up seconds by (step, scale, nb) that check the measures; catalogue_timings has measured ones.
TIMES = [("relabel", 16, 1, 8.0), ("relabel", 16, 2, 5.0), ("relabel", 16, 4, 4.0), ("relabel", 18, 1, 32.0), ("relabel", 18, 4, 10.0), ("csr", 16, 1, 4.0), ("csr", 17, 2, 6.0), ("csr", 18, 4, 10.0)]
SQL_TIMES = "t AS (SELECT * FROM (VALUES " + ", ".join(f"('{a}', {b}, {c}, CAST({d} AS DOUBLE))" for a, b, c, d in TIMES) + ") v(step, scale, nb, seconds))"


def _times(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(TIMES, "step string, scale int, nb int, seconds double")


@entry("C9 G16", """WITH u AS (SELECT event_type AS step, user_id, CAST(length(bin(count(*))) AS INTEGER) AS scale, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS hundredths FROM events GROUP BY event_type, user_id),
t AS (SELECT step, scale, count(*) AS nb, CAST(sum(hundredths) AS BIGINT) / 100.0 AS seconds FROM u GROUP BY step, scale) SELECT *, seconds / (2.0 ** (scale - 16)) AS norm_seconds FROM t""")
def normalized_time(spark, sf_dir):
    """Time values of events normalised by size: a step is an event type, its scale the binary digits of a user's number of such events, nb the users."""
    hundredths = F.sum(F.round(F.col("value") * 100).cast("long"))
    users = tables.table(spark, sf_dir, "events").groupBy(F.col("event_type").alias("step"), "user_id").agg(F.length(F.bin(F.count(F.lit(1)))).alias("scale"), hundredths.alias("hundredths"))
    return models.normalize(users.groupBy("step", "scale").agg(F.count(F.lit(1)).alias("nb"), (F.sum("hundredths") / 100.0).alias("seconds")))


@entry("C10", f"WITH {SQL_TIMES} SELECT step, scale, nb, t0 / seconds AS speedup, t0 / seconds * nb0 / nb AS efficiency FROM (SELECT *, first_value(seconds) OVER w AS t0, first_value(nb) OVER w AS nb0 FROM t WINDOW w AS (PARTITION BY step, scale ORDER BY nb))")
def strong_scaling(spark, sf_dir):
    return models.strong_scaling(_times(spark))


@entry("C11", f"WITH {SQL_TIMES} SELECT step, scale, nb, seconds / first_value(seconds) OVER (PARTITION BY step ORDER BY scale) AS ratio FROM t WHERE step = 'csr'")
def weak_scaling(spark, sf_dir):
    return models.weak_scaling(_times(spark).where("step = 'csr'"))


WEAK = [(12, 1), (13, 2), (14, 4), (15, 8), (16, 16), (17, 32)]


def _weak_spec(scale: int) -> GenSpec:
    return GenSpec(scale=scale, edge_factor=16, seed=SEED, backend="portable")


def _weak_sql() -> str:
    parts, rows = [], []
    for s, nb in WEAK:
        n = 1 << s
        parts += [sql_rmat(_weak_spec(s), "edge", f"e{s}"), f"p{s} AS (SELECT id, row_number() OVER (ORDER BY md5(concat('{SEED}:perm:', id)), id) - 1 AS label FROM (SELECT unnest(range({n})) AS id))"]
        rows.append(f"SELECT {s} AS scale, {nb} AS nb, CAST({n} AS BIGINT) AS perm_rows_a_node, CAST(max(c) AS BIGINT) AS most_edges, CAST({16 * n} // {nb} AS BIGINT) AS mean_edges FROM (SELECT (label * {nb}) // {n} AS b, count(*) AS c FROM e{s} JOIN p{s} ON src = id GROUP BY 1)")
    return sql_with(*parts) + " " + " UNION ALL ".join(rows)


@entry("W6 G27", _weak_sql())
def weak_scaling_counts(spark, sf_dir):
    """As nodes and vertices double: every node still scans all of the permutation, and the largest owner drifts from the mean."""
    out = None
    for s, nb in WEAK:
        spec = _weak_spec(s)
        new = relabel.relabel_endpoint(rmat.rmat_edges(spark, spec), permute.by_sort(spark, spec.vertices, SEED, "portable"), "src")
        row = measures.owner_skew(new, Layout(spec.vertices, nb, 1)).select(F.lit(s).alias("scale"), F.lit(nb).alias("nb"), F.lit(spec.vertices).cast("long").alias("perm_rows_a_node"), F.col("most").alias("most_edges"), F.lit(spec.edges // nb).cast("long").alias("mean_edges"))
        out = row if out is None else out.unionByName(row)
    return out


@entry("W4 W5", f"{SQL_BASE} " + " UNION ALL ".join(f"SELECT {nb} AS nb, CAST(max(c) AS BIGINT) AS edges_of_largest, CAST(count(*) AS INTEGER) AS owners FROM (SELECT (src * {nb}) // n AS b, count(*) AS c FROM relabelled, dims GROUP BY 1)" for nb in (1, 2, 4, 8)))
def strong_scaling_counts(spark, sf_dir):
    edges, layout, _ = relabelled(spark, sf_dir)
    edges = materialise(edges, "relabelled")
    out = None
    for nb in (1, 2, 4, 8):
        counts = redistribute.with_owner(edges, Layout(layout.n, nb, 1)).groupBy("bucket").agg(F.count(F.lit(1)).alias("c"))
        row = counts.agg(F.max("c").alias("edges_of_largest"), F.count(F.lit(1)).cast("int").alias("owners")).select(F.lit(nb).alias("nb"), "edges_of_largest", "owners")
        out = row if out is None else out.unionByName(row)
    return out


@entry("C17 W10 I17")
def plan_costs(spark, sf_dir):
    """Exchanges, sorts, joins and Python nodes of each relabel and compression plan."""
    from edgemill.plans.inspect import plan_summary

    edges, perm, layout, m = base(spark, sf_dir)
    edges, perm = materialise(edges, "edges"), materialise(perm, "perm")
    plans = {
        "merge": relabel.relabel_merge(edges, perm), "hash_join": relabel.relabel_hash_join(edges, perm), "broadcast": relabel.relabel_broadcast(edges, perm, layout.n), "hashed": relabel.relabel_hashed(edges, layout.n),
        "unpivot": relabel.relabel_unpivot(edges, perm), "ship_sorted": redistribute.ship_sorted(edges, layout), "csr_ordered": csr.csr_ordered(edges, layout).neighbors, "csr_unordered": csr.csr_unordered(edges, layout).neighbors,
    }
    rows = [(name, node, times) for name, df in plans.items() for node, times in sorted(plan_summary(df).items())]
    return spark.createDataFrame(rows, "variant string, node string, times int")


#: Exchanges and sorts that the method needs: of the edges, and in joins of the permutation.
EXPECTED = {"merge": (4, 4), "hash_join": (4, 0), "broadcast": (0, 0), "hashed": (0, 0), "ship_sorted": (1, 1)}


@entry("C17 W10 I17", "SELECT * FROM (VALUES " + ", ".join(f"('{v}', '{node}', {n})" for v, both in EXPECTED.items() for node, n in zip(("exchanges", "sorts"), both)) + ") t(variant, node, times)")
def plan_exchanges(spark, sf_dir):
    """The plans whose shape their hints decide, against what the method needs."""
    return plan_costs(spark, sf_dir).where(F.col("variant").isin(*EXPECTED) & F.col("node").isin("exchanges", "sorts"))


# ---------------------------------------------------------------- W11 and graph kernels

@entry("W11 AG9", f"""WITH RECURSIVE {SQL_V6}, und AS (SELECT src, dst FROM geo UNION SELECT dst, src FROM geo),
walk AS (SELECT CAST(0 AS BIGINT) AS id, 0 AS level UNION SELECT dst, level + 1 FROM walk JOIN und ON src = id WHERE level < 6)
SELECT id, min(level) AS level FROM walk GROUP BY id""")
def bfs_levels(spark, sf_dir):
    """From region 0 through the whole tree of regions, nations, suppliers and customers, to an empty frontier."""
    tree = tables.geo_tree(spark, sf_dir)
    return graphops.bfs_levels(tree.select("src", "dst").unionByName(tree.select(F.col("dst").alias("src"), F.col("src").alias("dst"))), 0)


@entry("W11", f"""WITH RECURSIVE {SQL_V4}, links AS (SELECT DISTINCT src, dst FROM steps WHERE dst IS NOT NULL),
walk AS (SELECT CAST(0 AS BIGINT) AS id, 0 AS level UNION SELECT dst, level + 1 FROM walk JOIN links ON src = id WHERE level < 6) SELECT id, min(level) AS level FROM walk GROUP BY id""")
def bfs_user_steps(spark, sf_dir):
    return graphops.bfs_levels(tables.user_step(spark, sf_dir), 0)


@entry("W11 V12", f"""WITH RECURSIVE {SQL_BASE_RMAT.removeprefix("WITH ")}, links AS (SELECT DISTINCT src, dst FROM relabelled),
walk AS (SELECT (SELECT min(src) FROM links) AS id, 0 AS level UNION SELECT dst, level + 1 FROM walk JOIN links ON src = id WHERE level < 12) SELECT id, min(level) AS level FROM walk GROUP BY id""")
def bfs_generated(spark, sf_dir):
    """The kernel that generated graphs are for: levels over the compressed rows of a generated graph, from its least vertex with edges."""
    run = generate.generate_graph(spark, RMAT10, Layout(1024, NB, NC), strategy="merge")
    built = csr.Csr(run.tables["offsets"], run.tables["neighbors"], run.layout, RMAT10.edges)
    edges = materialise(csr.edges_from_csr(built), "from-rows")
    return graphops.bfs_levels(edges, edges.agg(F.min("src")).first()[0])


@entry("J11", f"WITH {SQL_V4}, e AS (SELECT src, dst, count(*) AS w FROM steps WHERE dst IS NOT NULL GROUP BY ALL) SELECT a.src, b.dst, CAST(sum(a.w * b.w) AS BIGINT) AS paths FROM e a JOIN e b ON a.dst = b.src GROUP BY ALL")
def two_hop(spark, sf_dir):
    return graphops.two_hop(tables.user_step(spark, sf_dir))


@entry("J11", f"WITH {SQL_V4}, s AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM steps WHERE dst IS NOT NULL AND src <> dst) SELECT count(*) AS triangles FROM s x JOIN s y ON x.b = y.a JOIN s z ON z.a = x.a AND z.b = y.b")
def triangles(spark, sf_dir):
    return graphops.triangles(tables.user_step(spark, sf_dir))


@entry("J11", f"WITH {SQL_V4}, s AS (SELECT DISTINCT src, dst FROM steps WHERE dst IS NOT NULL AND src <> dst) SELECT count(*) AS links, CAST(sum(CASE WHEN EXISTS (SELECT 1 FROM s r WHERE r.src = s.dst AND r.dst = s.src) THEN 1 ELSE 0 END) AS BIGINT) AS returned FROM s")
def reciprocity(spark, sf_dir):
    return graphops.reciprocity(tables.user_step(spark, sf_dir))


@entry("J11 K5", "WITH s AS (SELECT DISTINCT user_id AS src, CAST(json_extract_string(props, '$.k') AS BIGINT) AS dst FROM events) SELECT x.src AS a, y.src AS b, count(*) AS common FROM s x JOIN s y ON x.dst = y.dst AND x.src < y.src GROUP BY ALL HAVING count(*) >= 30")
def common_neighbors(spark, sf_dir):
    return graphops.common_neighbors(tables.event_keys(spark, sf_dir), 30)


@entry("W11 AG9", """WITH t AS (SELECT conv_id, row_number() OVER (ORDER BY conv_id, turn) - 1 AS id, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS after, lag(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS before, turn FROM conversations),
linked AS (SELECT * FROM t WHERE after = turn + 1 OR before = turn - 1) SELECT id AS node, min(id) OVER (PARTITION BY conv_id) AS root FROM linked""")
def components_iter(spark, sf_dir):
    return connected_components(tables.conversation_steps(spark, sf_dir), "src", "dst")


# ---------------------------------------------------------------- generic operators, one text for both engines

same("scan_pruned", "S1 O1 O2 X14", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_orderkey BETWEEN 100 AND 900 AND l_linestatus IN ('O', 'F') AND l_returnflag LIKE 'R%' AND l_partkey IS NOT NULL", "lineitem")
same("join_inner", "J1", "SELECT p_brand, count(*) AS lines, CAST(sum(l_linenumber) AS BIGINT) AS numbers FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand", "lineitem", "part")
same("join_left_outer", "J4", "SELECT o_orderkey, count(l_orderkey) AS lines FROM orders LEFT JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey", "orders", "lineitem")
same("join_semi", "J5", "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)", "orders", "lineitem")
same("join_anti", "J5 V2", "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)", "orders", "lineitem")
same("join_full_outer", "J6 J12", "SELECT coalesce(a.k, b.k) AS k, a.c AS parts, b.c AS suppliers FROM (SELECT l_partkey AS k, count(*) AS c FROM lineitem GROUP BY l_partkey) a FULL OUTER JOIN (SELECT l_suppkey AS k, count(*) AS c FROM lineitem GROUP BY l_suppkey) b ON a.k = b.k", "lineitem")
same("join_null_safe", "J12", "SELECT count(*) AS pairs FROM (SELECT DISTINCT CASE WHEN user_id < 5 THEN NULL ELSE user_id END AS k FROM events) a JOIN (SELECT DISTINCT CASE WHEN user_id > 140 THEN NULL ELSE user_id END AS k FROM events) b ON a.k IS NOT DISTINCT FROM b.k", "events")
same("join_theta_ranges", "J9", "SELECT r.bucket, count(*) AS edges FROM lineitem JOIN (SELECT * FROM (VALUES (0, 0, 99), (1, 100, 499), (2, 500, 999), (3, 1000, 100000000)) v(bucket, lo, hi)) r ON l_partkey BETWEEN r.lo AND r.hi GROUP BY r.bucket", "lineitem")
same("join_self", "J11", "SELECT count(*) AS pairs FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey", "nation")
same("agg_hash", "AG1", "SELECT l_returnflag, l_linestatus, count(*) AS lines, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity FROM lineitem GROUP BY l_returnflag, l_linestatus", "lineitem")
same("agg_distinct", "AG3", "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_suppkey", "lineitem")
same("agg_grouping_sets", "AG5", "SELECT l_returnflag, l_linestatus, count(*) AS lines FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())", "lineitem")
same("agg_rollup", "AG5", "SELECT n_regionkey, n_nationkey, count(*) AS suppliers FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_nationkey)", "supplier", "nation")
same("agg_cube", "AG5", "SELECT l_returnflag, l_linestatus, count(*) AS lines FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)", "lineitem")
same("agg_conditional", "AG7", "SELECT count(*) FILTER (WHERE l_partkey < 100) AS low, count(*) FILTER (WHERE l_partkey >= 100) AS high, CAST(sum(CASE WHEN l_suppkey % 2 = 0 THEN 1 ELSE 0 END) AS BIGINT) AS even FROM lineitem", "lineitem")
same("agg_max_by", "AG8", "SELECT src % 4 AS bucket, max(deg) AS deg, CAST(max_by(src, deg * 1000000 - src) AS BIGINT) AS hub FROM (SELECT l_partkey AS src, count(*) AS deg FROM lineitem GROUP BY l_partkey) GROUP BY src % 4", "lineitem")
same("agg_bit_xor", "AG8", "SELECT bit_xor(l_orderkey * 4096 + l_partkey) AS checksum, bit_or(l_linenumber) AS bits_or, bit_and(l_linenumber) AS bits_and FROM lineitem", "lineitem")
same("window_ranks", "N1", "SELECT id, CAST(rank() OVER (ORDER BY deg DESC) AS BIGINT) AS rnk, CAST(dense_rank() OVER (ORDER BY deg DESC) AS BIGINT) AS dense, CAST(ntile(4) OVER (ORDER BY deg DESC, id) AS BIGINT) AS quarter, CAST(row_number() OVER (ORDER BY deg DESC, id) AS BIGINT) AS nth FROM (SELECT l_suppkey AS id, count(*) AS deg FROM lineitem GROUP BY l_suppkey)", "lineitem")
same("window_analytic", "N2", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", "events")
same("window_frames", "N3", "SELECT event_id, CAST(sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS BIGINT) AS before, CAST(count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS near FROM events", "events")
same("sort_limit", "T1 T3", "SELECT l_suppkey AS id, count(*) AS deg FROM lineitem GROUP BY l_suppkey ORDER BY deg DESC, id LIMIT 10", "lineitem")
same("top_k_per_group", "T4", "SELECT bucket, id, deg FROM (SELECT id % 4 AS bucket, id, deg, row_number() OVER (PARTITION BY id % 4 ORDER BY deg DESC, id) AS r FROM (SELECT l_suppkey AS id, count(*) AS deg FROM lineitem GROUP BY l_suppkey)) WHERE r <= 3", "lineitem")
same("sample_by_draw", "T5", "SELECT event_id FROM events WHERE substr(md5(concat('42:sample:', CAST(event_id AS VARCHAR(20)))), 1, 2) < '40'", "events")
same("set_union", "U1", "SELECT l_partkey AS id FROM lineitem UNION SELECT l_suppkey FROM lineitem", "lineitem")
same("set_intersect_all", "U2", "SELECT l_partkey AS id FROM lineitem INTERSECT ALL SELECT l_suppkey FROM lineitem", "lineitem")
same("set_except_all", "U2", "SELECT l_suppkey AS id FROM lineitem EXCEPT ALL SELECT s_suppkey FROM supplier", "lineitem", "supplier")
same("scalar_text", "F1 string", "SELECT page_id, lower(url) AS url, CAST(length(url) AS BIGINT) AS chars, lpad(CAST(page_id AS VARCHAR(20)), 8, '0') AS padded, concat(CAST(page_id AS VARCHAR(20)), '->', md5(url)) AS edge FROM (SELECT page_id, url FROM pages)", "pages")
same("scalar_math", "scalar math", "SELECT l_orderkey, l_orderkey % 7 AS rest, CAST(floor(l_orderkey / 7) AS BIGINT) AS part, greatest(l_partkey, l_suppkey) AS most, least(l_partkey, l_suppkey) AS least, abs(l_partkey - l_suppkey) AS gap, CAST(bit_count(l_partkey) AS BIGINT) AS ones FROM lineitem", "lineitem")
same("scalar_dates", "scalar time", "SELECT event_id, CAST(extract(HOUR FROM ts) AS BIGINT) AS hour, CAST(extract(DAY FROM ts) AS BIGINT) AS day FROM events", "events")
same("scalar_nulls", "scalar null", "SELECT coalesce(nullif(l_linenumber, 1), -1) AS number, count(*) AS lines FROM lineitem GROUP BY coalesce(nullif(l_linenumber, 1), -1)", "lineitem")


@entry("F1", sql_with(SQL_N1, SQL_V1) + f" SELECT (src * {NB}) // n AS bucket, ((src * {NB * NC}) // n) % {NC} AS lane, count(*) AS edges, min((((src * {NB}) // n) * n + {NB - 1}) // {NB}) AS lo FROM edges, dims GROUP BY ALL")
def sql_functions(spark, sf_dir):
    """The range arithmetic as SQL functions, inlined by the analyzer."""
    register_sql(spark)
    n = tables.part_supplier_vertices(spark, sf_dir)
    tables.part_supplier(spark, sf_dir).createOrReplaceTempView("edges_v1")
    return spark.sql(f"""SELECT bucket, lane, count(*) AS edges, min(lo) AS lo FROM (
        SELECT *, range_lo(bucket, {n}, {NB}) AS lo FROM (SELECT owner_of(src, {n}, {NB}) AS bucket, lane_of(src, {n}, {NB}, {NC}) AS lane FROM edges_v1)) GROUP BY bucket, lane""")


@entry("F3 E1", "SELECT CAST(4096 AS BIGINT) AS edges, CAST(0 AS BIGINT) AS outside")
def table_function(spark, sf_dir):
    from edgemill.functions import tablefunctions

    tablefunctions.register(spark)
    return spark.sql("SELECT count(*) AS edges, count(CASE WHEN src NOT BETWEEN 0 AND 255 OR dst NOT BETWEEN 0 AND 255 THEN 1 END) AS outside FROM rmat(8, 16, 42)")


@entry("AG4", "SELECT CAST(1 AS BIGINT) AS close_distinct, CAST(1 AS BIGINT) AS close_median")
def agg_sketches(spark, sf_dir):
    """Approximate counts and quantiles lie within their error of the exact ones."""
    lines = tables.table(spark, sf_dir, "lineitem")
    r = lines.agg(
        F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.countDistinct("l_partkey").alias("d"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("h"),
        F.percentile_approx("l_partkey", 0.5, 10_000).alias("p"), F.percentile("l_partkey", 0.5).alias("q"),
    )
    near = lambda x, y, e: (F.abs(F.col(x) - F.col(y)) <= e * F.col(y)).cast("long")
    return r.select((near("a", "d", 0.1) * near("h", "d", 0.1)).alias("close_distinct"), near("p", "q", 0.05).alias("close_median"))


@entry("J10", "SELECT o_orderkey, e.event_id FROM orders o ASOF LEFT JOIN (SELECT ts, max(event_id) AS event_id FROM events GROUP BY ts) e ON o.o_orderdate >= e.ts")
def join_as_of(spark, sf_dir):
    """The latest event at or before each order: both sides in one order, cut by month, the last event of earlier months carried on."""
    from pyspark.sql import Window

    orders = tables.table(spark, sf_dir, "orders").select(F.col("o_orderdate").alias("ts"), "o_orderkey", F.lit(None).cast("long").alias("event_id"))
    events = tables.table(spark, sf_dir, "events").select("ts", F.lit(None).cast("long").alias("o_orderkey"), "event_id")
    rows = orders.unionByName(events).withColumn("month", F.date_trunc("month", "ts"))
    order = [F.col("ts"), F.col("event_id").asc_nulls_last()]
    inside = Window.partitionBy("month").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    latest = events.groupBy(F.date_trunc("month", "ts").alias("month")).agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("final"))
    months = rows.select("month").distinct().join(latest, "month", "left")  # a row a month
    carry = Window.partitionBy(F.lit(0)).orderBy("month").rowsBetween(Window.unboundedPreceding, -1)
    before = months.select("month", F.last("final", ignorenulls=True).over(carry).alias("carried"))
    found = rows.withColumn("own", F.last("event_id", ignorenulls=True).over(inside)).where(F.col("o_orderkey").isNotNull())
    return found.join(before, "month").select("o_orderkey", F.coalesce("own", "carried").alias("event_id"))


SQL_SUMS = "count(*) AS edges, CAST(sum(eid) AS BIGINT) AS eids, CAST(sum(src * 31 + dst * 17) AS BIGINT) AS mixed"


@entry("S4 S6 S9", "WITH e AS (SELECT o_orderkey AS eid, o_custkey AS src, (SELECT count(*) FROM customer) + o_orderkey AS dst FROM orders) "
       + " UNION ALL ".join(f"SELECT '{f}' AS format, {SQL_SUMS.replace('count(*)', '2 * count(*)').replace('sum(', '2 * sum(') if f == 'parquet' else SQL_SUMS} FROM e" for f in ("csv", "json", "orc", "text", "parquet")))
def sinks_roundtrip(spark, sf_dir):
    """Edge lists through each file format, as sums of what is read back; the Parquet list is appended to by bucket, as an append-only edge list is."""
    from edgemill.scratch import fresh_path

    edges = tables.customer_order(spark, sf_dir)
    out = None
    for fmt in ("csv", "json", "orc", "text", "parquet"):
        path = fresh_path(spark, f"edges-{fmt}")
        rows = edges.select(F.concat_ws("\t", "eid", "src", "dst").alias("value")) if fmt == "text" else edges.withColumn("bucket", F.pmod("src", F.lit(4)))
        writer = rows.write.mode("append").option("maxRecordsPerFile", 100_000)
        for _ in range(2 if fmt == "parquet" else 1):
            (writer.partitionBy("bucket") if fmt == "parquet" else writer).format(fmt).save(path)
        back = spark.read.format(fmt).schema("value string" if fmt == "text" else "eid long, src long, dst long, bucket long").load(path)
        if fmt == "text":
            back = back.select(*(F.split("value", "\t")[k].cast("long").alias(c) for k, c in enumerate(("eid", "src", "dst"))))
        sums = back.agg(F.count(F.lit(1)).alias("edges"), F.sum("eid").alias("eids"), F.sum(F.col("src") * 31 + F.col("dst") * 17).alias("mixed")).select(F.lit(fmt).alias("format"), "*")
        out = sums if out is None else out.unionByName(sums)
    return out


@entry("W1 B7", f"""WITH ids AS (SELECT row_number() OVER (ORDER BY {', '.join(tables.LINE_ORDER)}) - 1 AS id, l_orderkey AS k FROM lineitem), hashed AS ({sql_hash("k", 1 << 24)}),
placed AS (SELECT id // 16384 AS chunk, k, label, row_number() OVER (PARTITION BY id // 16384 ORDER BY k, id) AS nth FROM ids JOIN hashed USING (id))
SELECT chunk, count(*) AS numbers, CAST(sum(label) AS BIGINT) AS hashes, CAST(sum(nth * k) AS BIGINT) AS in_order FROM placed GROUP BY chunk""")
def hash_and_chunk_sort(spark, sf_dir):
    """The two kernels of the hash-against-sort comparison over one column: sums of hashes, and of place times key in sorted chunks. bench.py times them."""
    from pyspark.sql import Window

    from edgemill.functions.prng import mixed_columns

    keys = dense_position(tables.table(spark, sf_dir, "lineitem").select("l_orderkey", *tables.LINE_ORDER[1:]), tables.LINE_ORDER).select("eid", F.col("l_orderkey").alias("src"), F.col("l_orderkey").alias("hash"))
    chunks = relabel.sort_chunks(relabel.chunk_edges(mixed_columns(keys, ["hash"], 1 << 24), 16_384), "src", 8)
    placed = chunks.withColumn("nth", F.row_number().over(Window.partitionBy("chunk").orderBy("src", "eid")))
    return placed.groupBy("chunk").agg(F.count(F.lit(1)).alias("numbers"), F.sum("hash").alias("hashes"), F.sum(F.col("nth") * F.col("src")).alias("in_order"))


def _load() -> None:
    """Register the queries of the other catalogue modules."""
    from edgemill import catalogue_streams, catalogue_surface, catalogue_timings  # noqa: F401


def queries() -> dict[str, Query]:
    _load()
    return {name: e.query for name, e in ENTRIES.items()}


def oracle_sql() -> dict[str, str]:
    _load()
    return {name: e.sql for name, e in ENTRIES.items() if e.sql}


def coverage() -> dict[str, list[str]]:
    """Survey id to the queries that cover it."""
    _load()
    out: dict[str, list[str]] = {}
    for name, e in ENTRIES.items():
        for k in e.survey.split():
            out.setdefault(k, []).append(name)
    return out
