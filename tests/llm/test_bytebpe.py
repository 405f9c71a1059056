import codecs
import hashlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st

from edgemill.llm.bytebpe import Utf8Machine, codec, decode_ids, encode_and_decode, load_ranks

RANKS, PATTERN = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN
ODD = ["", " ", "  x", "a  b \n c\t\n", "don't 'tis we'LL", "漢字かな交じり 😀👍🏽", "\x00a\x00", "a\x1cb", "x" * 3000, "ab" * 2000, "ñandú ÀÉÎ ½ ª", "a b", "    def f():\n        return 1\n"]


@pytest.fixture(scope="module")
def library():
    return tiktoken.Encoding("own", pat_str=PATTERN, mergeable_ranks=load_ranks(RANKS), special_tokens={})


def by_document(texts):
    out = []
    for ids, counts in codec(RANKS, PATTERN).encode(pa.array(texts, pa.string())):
        out += [x.tolist() for x in np.split(ids, np.cumsum(counts)[:-1])]
    return out


def test_equals_the_library(library):
    texts = pq.read_table("/root/testdata/sf0.001/documents.parquet")["text"].to_pylist() + ODD
    assert by_document(texts) == [library.encode_ordinary(t) for t in texts]


@settings(max_examples=200, deadline=None)
@given(st.lists(st.one_of(st.text(max_size=30), st.text(alphabet="abes thn'r.\n 19", max_size=40)), max_size=4))
def test_equals_the_library_on_anything(library, texts):
    assert by_document(texts) == [library.encode_ordinary(t) for t in texts]


@settings(max_examples=100, deadline=None)
@given(st.binary(min_size=1, max_size=40))
def test_transducer_on_bytes(library, data):
    ids = np.frombuffer(codec(RANKS, PATTERN).machine.encode(data), "<u4").tolist()
    assert ids == library._encode_single_piece(data)


@settings(max_examples=200, deadline=None)
@given(st.one_of(st.binary(max_size=30), st.text(max_size=12).map(str.encode)), st.lists(st.integers(0, 30)))
def test_utf8_machine(data, cuts):
    machine, at, got = Utf8Machine(), 0, ""
    for c in sorted(cuts):
        got += machine.feed(data[at : max(at, c)])
        at = max(at, c)
    got += machine.feed(data[at:]) + machine.feed(b"", final=True)
    assert got == codecs.decode(data, "utf-8", "replace")


def test_small_memo_is_dropped_and_rebuilt(library):
    from edgemill.llm.bytebpe import MergeTransducer

    small = MergeTransducer(load_ranks(RANKS), limit=50)
    for word in ("internationalization", "zxqvbnkwtrp", "thththereandthere") * 3:
        assert np.frombuffer(small.encode(word.encode()), "<u4").tolist() == library._encode_single_piece(word.encode())


def test_operator(spark, library):
    texts = [None, "", "Ein Straßenfest, don't!", "Ein Straßenfest, don't!", "漢字 x" * 500]
    df = spark.createDataFrame([(7, i, t) for i, t in enumerate(texts)], "n_tokens int, doc_id long, text string")
    rows = {r.doc_id: r for r in encode_and_decode(df, RANKS, PATTERN).collect()}
    assert len(rows) == len(texts)
    for i, t in enumerate(texts):
        ids = library.encode_ordinary(t or "")
        assert rows[i].n_tokens == len(ids)
        assert rows[i].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert rows[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    assert encode_and_decode(df.limit(0), RANKS, PATTERN).count() == 0
    back = decode_ids(spark.createDataFrame([(1, library.encode_ordinary(texts[2]))], "doc_id long, ids array<int>"), RANKS, PATTERN)
    assert back.collect()[0].text == texts[2]
