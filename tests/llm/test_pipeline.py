"""The pipeline against plain Python on the smallest tables."""

import pyarrow as pa
import pyarrow.parquet as pq

import corpus_pipeline
from edgemill.llm import pii, toxicity
from edgemill.llm.wordtokens import word_encoder
from tests.llm.test_jaccard import brute

SF = "/root/testdata/sf0.001"


def test_run_equals_plain_python(spark):
    table = pq.read_table(f"{SF}/documents.parquet").to_pylist()
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    model = toxicity.fit(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    clean = [r for r in table if toxicity.scan(model, pa.array([r["text"]]))[0][0] == 0 or model.probability(toxicity.scan(model, pa.array([r["text"]]))[0])[0] < 0.3]
    _, classes = brute([(r["doc_id"], r["text"]) for r in clean])
    kept = {min(c) for c in classes}
    texts = {}
    for r in clean:
        if r["doc_id"] in kept:
            text = r["text"] or ""
            (_, _, every), = pii.findings(pa.array([text]))
            texts[r["doc_id"]] = pii.masked(text, every)
    got = corpus_pipeline.run(spark, SF).collect()
    library = word_encoder(corpus_pipeline.WORD_BPE).library
    lengths = {d: len(library.encode(t, add_special_tokens=False).ids) + 1 for d, t in texts.items()}
    assert {r.doc_id for r in got} == set(lengths)
    for d, n in lengths.items():
        assert sum(r.length for r in got if r.doc_id == d) == n
    total = sum(lengths.values())
    assert len({r.sequence_id for r in got}) <= -(-total // 2048) + 1


def test_stages_keep_the_columns_and_take_odd_tables(spark):
    rows = [(1, None, "en", "s", 0, 7), (2, "", None, "s", None, 7), (3, "mail a@b.cc now please you all", "en", None, 5, None), (3, "mail a@b.cc now please you all", "en", None, 5, None), (4, "x " * 60_000, "de", "s", 9, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, node int")
    for frame in (docs, docs.limit(0)):
        for name, stage in corpus_pipeline.STAGES[:-1]:
            frame = stage(spark, frame, SF)
            assert frame.columns == docs.columns, name
        assert corpus_pipeline.STAGES[-1][1](spark, frame, SF).count() in (0, 32)
    assert [name for name, _ in corpus_pipeline.STAGES] == ["toxicity", "ngram_jaccard", "pii", "packing"]
