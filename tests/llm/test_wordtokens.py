import numpy as np
import public_tokenizers
import pyarrow as pa
import pyarrow.parquet as pq
from hypothesis import given, settings
from hypothesis import strategies as st

from edgemill.llm.wordtokens import end_every, word_encoder

PATH = public_tokenizers.path("word_bpe_49k.json")
ODD = ["Ünï ǅ ﬁ x\x1cy a b  \t c İstanbul ΣΑΣ ́e é <|endoftext|> don't I'LL 12½ª ß漢字 emoji😀", " \n", "", "'tis o'll'd rock'n'roll's", "\x0bv\xa0n\x85", None, "straße ÀÉ ²³ ¼", "a" * 5000]


def by_document(texts):
    got = []
    for ids, counts in word_encoder(PATH).encode(pa.array(texts, pa.string())):
        assert counts.sum() == len(ids)
        got += [x.tolist() for x in np.split(ids, np.cumsum(counts)[:-1])]
    return got


def expected(texts):
    return [word_encoder(PATH).library.encode(t or "", add_special_tokens=False).ids for t in texts]


def test_equals_the_library_on_documents():
    texts = pq.read_table("/root/testdata/sf0.001/documents.parquet")["text"].to_pylist() + ODD
    assert by_document(texts) == expected(texts)


@settings(max_examples=150, deadline=None)
@given(st.lists(st.text(alphabet=st.one_of(st.characters(max_codepoint=0x250), st.sampled_from("'stmdlre 12 \n")), max_size=40), max_size=6))
def test_equals_the_library_on_latin(texts):
    assert by_document(texts) == expected(texts)


@settings(max_examples=80, deadline=None)
@given(st.lists(st.text(max_size=30), max_size=4))
def test_equals_the_library_on_anything(texts):
    assert by_document(texts) == expected(texts)


def test_end_every():
    ids, counts = end_every(np.array([5, 6, 7], "<u4"), np.array([2, 0, 1]), 9)
    assert ids.tolist() == [5, 6, 9, 9, 7, 9] and counts.tolist() == [3, 1, 2]
