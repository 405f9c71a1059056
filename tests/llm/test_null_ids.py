"""Rows with null, repeated and clashing columns through the operators: each has a defined result."""

import random
import zlib

import numpy as np
import public_tokenizers
from pyspark.sql import functions as F

from edgemill.llm import bitpack, packing, sharding, toxicity
from edgemill.llm.topk import top_k
from edgemill.llm.wordtokens import word_encoder

PATH = public_tokenizers.path("word_bpe_49k.json")
ROWS = [(None, "no id and some words"), (None, "no id, other words"), (None, None), (3, "three"), (3, "a third text"), (3, "three"), (-5, "minus"), (1 << 62, "")] + [(None, f"number {k} " * (k * 9)) for k in range(60)]


def frame(spark):
    extra = "start int, size string, length int, shard int, path string, text_order long, row long"
    return spark.createDataFrame([(d, t, 7, "s", 7, 7, "p", 7, 7) for d, t in ROWS], f"doc_id long, text string, {extra}").repartition(4)


def ids_of(text, end):
    return word_encoder(PATH).library.encode(text or "", add_special_tokens=False).ids + [end]


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def test_bitpack_puts_documents_without_id_first(spark):
    files = bitpack.write_packed(frame(spark), PATH, 2)
    got = sorted(bitpack.read_packed(files).collect(), key=lambda r: r.start)
    assert [r.doc_id for r in got] == [None] * 63 + [-5, 3, 3, 3, 1 << 62]
    assert sorted((r.doc_id is None, r.doc_id or 0, r.n_tokens, r.ids_crc32) for r in got) == sorted((d is None, d or 0, len(ids_of(t, 2)), crc(ids_of(t, 2))) for d, t in ROWS)
    assert [r.start for r in got] == np.cumsum([0] + [r.n_tokens for r in got])[:-1].tolist()
    again = sorted(bitpack.read_packed(bitpack.write_packed(frame(spark).repartition(2), PATH, 2, files=5)).collect(), key=lambda r: r.start)
    assert [(r.doc_id, r.ids_crc32) for r in again] == [(r.doc_id, r.ids_crc32) for r in got]


def test_a_repeated_row_spreads_over_files(spark):
    rows = [(7, "the same row again and again")] * 300 + [(k, f"row {k}") for k in range(60)]
    files = bitpack.write_packed(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), PATH, 2, files=12)
    assert files.count() > 8 and max(r.n_docs for r in files.collect()) < 120
    got = sorted(bitpack.read_packed(files).collect(), key=lambda r: r.start)
    assert [r.doc_id for r in got] == sorted(d for d, _ in rows)


def test_files_of_lost_attempts_go(spark, tmp_path):
    folder = f"file://{tmp_path}/packed"
    (tmp_path / "packed").mkdir()
    (tmp_path / "packed" / "left-over.ids").write_bytes(b"half a file")
    files = bitpack.write_packed(frame(spark), PATH, 2, folder=folder)
    assert {f.name for f in (tmp_path / "packed").glob("*.ids")} == {r.path.rsplit("/", 1)[1] for r in files.collect()}


def test_packing_keeps_rows_without_id(spark):
    got = packing.pack_documents(frame(spark), PATH, capacity=64).collect()
    want = sorted((d is None, d or 0, p // 64, crc(ids_of(t, 0)[p : p + 64])) for d, t in ROWS for p in range(0, len(ids_of(t, 0)), 64))
    assert sorted((r.doc_id is None, r.doc_id or 0, r.piece, r.ids_crc32) for r in got) == want
    total = sum(len(ids_of(t, 0)) for _, t in ROWS)
    sequences = packing.packed_sequences(frame(spark), PATH, capacity=64).collect()
    assert sum(len(r.ids) for r in sequences) == total and all(len(r.ids) <= 64 for r in sequences)


def test_exchanges_beat_best_fit():
    """Where best fit decreasing is not optimal, the operator's search empties bins."""
    histogram = {k: 40 for k in range(600, 1300, 7)}
    plain = packing.best_fit_decreasing(histogram, 2048)
    better = packing.improve(dict(plain), 2048)
    assert sum(better.values()) < sum(plain.values())


def test_sharding_keeps_rows_without_id(spark):
    got = sharding.shard_documents(frame(spark), 4).collect()
    assert sorted((r.doc_id is None, r.doc_id or 0, r.text_crc32) for r in got) == sorted((d is None, d or 0, zlib.crc32((t or "").encode())) for d, t in ROWS)
    for k in range(4):
        assert sorted(r.slot for r in got if r.shard == k) == list(range(sum(r.shard == k for r in got)))


def test_plan_in_parts_has_the_loads_of_one(spark):
    rng = random.Random(3)
    df = spark.createDataFrame([(k, "x" * rng.randrange(400)) for k in range(600)] + [(k, "x" * 9) for k in range(600, 900)], "doc_id long, text string")
    loads = lambda rows: sorted(sum(r.size for r in rows if r.shard == k) for k in range(5))
    assert loads(sharding.shard_documents(df, 5, most=7).collect()) == loads(sharding.shard_documents(df, 5).collect())


def test_vectors_without_id_take_no_part(spark):
    rows = [(None, [9.0, 9.0]), (0, [1.0, 2.0]), (1, [3.0, 1.0]), (None, None), (100, [1.0, 1.0])]
    got = top_k(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()
    assert sorted((r.query_id, r.vec_id) for r in got) == [(0, 1), (0, 100), (100, 0), (100, 1)]


def test_toxicity_of_rows_without_id(spark):
    docs = spark.createDataFrame([(k, f"word{k % 7} good text") for k in range(40)] + [(None, "no id"), (None, None)], "doc_id long, text string")
    labels = spark.createDataFrame([(k, int(k % 7 == 0)) for k in range(40)] + [(None, 1)], "doc_id long, toxic int")
    rows = toxicity.score(docs, toxicity.fit(docs, labels)).select("doc_id", toxicity.held_out(F.col("doc_id")).alias("held_out"), "score").collect()
    assert len(rows) == 42 and all(0 <= r.score <= 1 for r in rows)
    assert [r.held_out for r in rows if r.doc_id is None] == [False, False]
