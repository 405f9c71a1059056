"""The operators' queries over the given tables, and their SQL where it can express them."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgemill.llm import bitpack, bytebpe, descriptors, jaccard, packing, pii, sharding, topk, toxicity, urlfilter
from edgemill.llm.common import documents

WORD_BPE = public_tokenizers.path("word_bpe_49k.json")
BYTE_BPE = public_tokenizers.path("byte_bpe_50k.tiktoken")


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = toxicity.fit(docs, documents(spark, sf_dir, "labels"))
    scored = toxicity.score(docs, model)
    return scored.select("doc_id", toxicity.held_out(F.col("doc_id")).alias("held_out"), "score", "predicted", "evidence", "n_segments")


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(documents(spark, sf_dir), 16)


def op3_bitpack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bitpack.read_packed(bitpack.write_packed(documents(spark, sf_dir), WORD_BPE, 2))


def op4_descriptors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return descriptors.find_copies(descriptors.media_of_embeddings(documents(spark, sf_dir, "embeddings")))


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(documents(spark, sf_dir), WORD_BPE, 0, 2048)


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.report(documents(spark, sf_dir))


def op7_urlfilter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlfilter.judge_urls(documents(spark, sf_dir, "pages"))


def op8_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.top_k(documents(spark, sf_dir, "embeddings"), 10, 100, 1024)


def op9_bytebpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bytebpe.encode_and_decode(documents(spark, sf_dir), BYTE_BPE, public_tokenizers.PATTERN)


def op10_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.similarity_join(documents(spark, sf_dir), 0.8, 5)


OP8_SQL = """
WITH cells AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT)) AS c FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0
    AND len(list_filter(embedding, lambda x: x IS NOT NULL AND isfinite(x))) = len(embedding)),
scored AS (
  SELECT q.vec_id AS query_id, r.vec_id, CAST(list_sum(list_transform(list_zip(q.c, r.c), lambda z: z[1] * z[2])) AS BIGINT) AS score
  FROM cells q JOIN cells r ON q.vec_id % 100 = 0 AND r.vec_id <> q.vec_id),
ranked AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS "rank" FROM scored)
SELECT query_id, "rank", vec_id, score FROM ranked WHERE "rank" <= 10"""


OP10_SQL = r"""
WITH RECURSIVE docs AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
texts AS (SELECT text, min(doc_id) AS text_id, count(*) AS n_copies FROM docs GROUP BY text),
words AS (SELECT text_id, regexp_extract_all(lower(text), '[\p{L}\p{N}_]+') AS w FROM texts),
grams AS (SELECT DISTINCT text_id, gram FROM (
  SELECT text_id, unnest(list_transform(range(1, greatest(len(w) - 4, 1) + 1), lambda k: array_to_string(w[k:k + 4], ' '))) AS gram FROM words WHERE len(w) > 0)),
sizes AS (SELECT text_id, count(*) AS n FROM grams GROUP BY text_id),
pairs AS (SELECT a.text_id AS x, b.text_id AS y, count(*) AS common FROM grams a JOIN grams b ON a.gram = b.gram AND a.text_id < b.text_id GROUP BY ALL),
links AS (SELECT x, y FROM pairs JOIN sizes p ON p.text_id = x JOIN sizes q ON q.text_id = y WHERE common >= 0.8 * (p.n + q.n - common) - 1e-9),
sides AS (SELECT x, y FROM links UNION ALL SELECT y, x FROM links),
reach(x, y) AS (SELECT text_id, text_id FROM texts UNION SELECT r.x, s.y FROM reach r JOIN sides s ON s.x = r.y),
classes AS (SELECT x AS text_id, min(y) AS class_id FROM reach GROUP BY x),
linked AS (SELECT x AS text_id, count(*) AS n_links FROM sides GROUP BY x)
SELECT d.doc_id, class_id, t.text_id, n_copies, coalesce(n_links, 0) AS n_links FROM docs d JOIN texts t USING (text) JOIN classes USING (text_id) LEFT JOIN linked USING (text_id)"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_toxicity, op2_sharding, op3_bitpack, op4_descriptors, op5_packing, op6_pii, op7_urlfilter, op8_topk, op9_bytebpe, op10_jaccard)}


def oracle_sql() -> dict[str, str]:
    return {"op7_urlfilter": urlfilter.oracle_sql(), "op8_topk": OP8_SQL, "op10_jaccard": OP10_SQL}
