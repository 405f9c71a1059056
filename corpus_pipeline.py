"""A training corpus from raw documents: toxic documents go, one document of each group of copies stays, personal data are masked, sequences are packed.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return
the columns of documents. run() writes each stage's result as Parquet into the shared
folder and gives it to the next, so a lost executor costs tasks, not stages.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgemill.llm import jaccard, packing, pii, toxicity
from edgemill.llm.common import documents, materialise
from edgemill.llm.queries import WORD_BPE


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score stays below the threshold; rows with null doc_id are judged by their text like any other."""
    model = toxicity.fit(docs, documents(spark, sf_dir, "labels"))
    return toxicity.keep_clean(docs, model)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of equal or similar texts."""
    return jaccard.keep_one(docs)


def mask_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with personal data masked in their texts and n_chars set anew."""
    return pii.mask(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents with their place in sequences of at most 2048 tokens."""
    return packing.pack_documents(docs, WORD_BPE, 0, 2048)


STAGES = [("toxicity", drop_toxic), ("ngram_jaccard", drop_copies), ("pii", mask_personal_data), ("packing", pack_sequences)]

#: Hash functions, segment scans and tokenizers are beyond SQL; tests/llm/test_pipeline.py holds run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
