import zlib
from collections import Counter

import numpy as np
import public_tokenizers
from hypothesis import given, settings
from hypothesis import strategies as st

from edgemill.llm.packing import _best_exchange, best_fit_decreasing, improve, pack_documents, packed_sequences
from edgemill.llm.wordtokens import word_encoder

PATH = public_tokenizers.path("word_bpe_49k.json")


def plain_best_fit(lengths, capacity):
    room = []
    for x in sorted(lengths, reverse=True):
        fits = [r for r in room if r >= x]
        if fits:
            room.remove(min(fits))
            room.append(min(fits) - x)
        else:
            room.append(capacity - x)
    return sorted(room)


def spelled(bins):
    return Counter(x for kind, n in bins.items() for x in kind for _ in range(n))


@settings(max_examples=300, deadline=None)
@given(st.lists(st.integers(1, 30), max_size=60))
def test_histogram_packing_is_best_fit_decreasing(lengths):
    bins = best_fit_decreasing(Counter(lengths), 30)
    assert spelled(bins) == Counter(lengths)
    assert sorted(30 - sum(k) for k, n in bins.items() for _ in range(n)) == plain_best_fit(lengths, 30)


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(1, 100), max_size=60))
def test_search_keeps_pieces_and_never_adds_bins(lengths):
    bins = best_fit_decreasing(Counter(lengths), 100)
    better = improve(bins, 100)
    assert spelled(better) == Counter(lengths)
    assert all(sum(k) <= 100 for k in better)
    assert sum(better.values()) <= sum(bins.values())


def test_search_empties_a_bin():
    bins = {(6, 3): 1, (5, 4): 1, (2,): 1}  # room 1, 1, 8 of 10; 20 tokens fit two bins
    assert sum(improve(bins, 10).values()) == 2


def test_search_empties_as_many_bins_as_there_are():
    for many in (1000, 10**9):
        bins = {(6, 3): many, (5, 4): many, (2,): many}
        better = improve(bins, 10)
        assert sum(better.values()) == 2 * many
        assert sum(n * k.count(2) for k, n in better.items()) == many


def nothing_moves(bins, capacity):
    under = sorted((k for k in bins if sum(k) < capacity), key=sum)
    return not any(
        _best_exchange(a, b, capacity - sum(b))[0] for i, a in enumerate(under) for b in under[i:] if a != b or bins[a] > 1
    )


@settings(max_examples=200, deadline=None)
@given(st.dictionaries(st.integers(20, 100), st.integers(1, 2000), max_size=30))
def test_search_runs_to_its_end(histogram):
    better = improve(best_fit_decreasing(histogram, 100), 100)
    tokens = sum(k * n for k, n in histogram.items())
    assert sum(k.count(x) * n for k, n in better.items() for x in set(k)) == sum(histogram.values())
    assert sum(better.values()) == -(-tokens // 100) or nothing_moves(better, 100)


def check(spark, rows):
    df = spark.createDataFrame([(d, t, -1) for d, t in rows], "doc_id long, text string, length int")
    got = pack_documents(df, PATH).collect()
    enc = word_encoder(PATH).library
    ids = {d: enc.encode(t or "", add_special_tokens=False).ids + [0] for d, t in rows}
    bins = {}
    for r in got:
        part = ids[r.doc_id][r.start : r.start + r.length]
        assert len(part) == r.length and r.start == 2048 * r.piece
        assert r.ids_crc32 == zlib.crc32(np.array(part, "<u4").tobytes())
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert Counter((r.doc_id, r.piece) for r in got) == Counter((d, p) for d, t in rows for p in range(-(-len(ids[d]) // 2048)))
    for b in bins.values():
        at = 0
        for offset, length in sorted(b):
            assert offset == at
            at += length
        assert at <= 2048
    return bins


def test_operator(spark):
    rows = [(i, "word " * (37 * i % 700)) for i in range(120)] + [(200, None), (201, ""), (202, "long text " * 5000), (203, "same " * 9), (203, "same " * 9)]
    bins = check(spark, rows)
    total = sum(length for b in bins.values() for _, length in b)
    assert len(bins) == -(-total // 2048)
    assert pack_documents(spark.createDataFrame([], "doc_id long, text string"), PATH).count() == 0


def test_sequences(spark):
    df = spark.createDataFrame([(i, f"text number {i} " * i) for i in range(30)], "doc_id long, text string")
    total = sum(len(r.ids) for r in packed_sequences(df, PATH, capacity=256).collect())
    assert total == sum(r.length for r in pack_documents(df, PATH, capacity=256).collect())
