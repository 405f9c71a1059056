"""The second pass by pairs of blocks against all matches of all pairs of images."""

import numpy as np
import pytest

from edgemill.llm import descriptors
from edgemill.llm.common import materialise
from edgemill.llm.descriptors import BITS, LEAST_AGREE, MARK, MOST_BITS, _halves, _rest, agreeing, describe, edited, may_agree, picture, table_keys


def marks_of(image: np.ndarray) -> bytes:
    place, code = describe(image)
    return np.concatenate([code, np.ascontiguousarray(place[:, :2], "<f4").view(np.uint8).reshape(len(code), 8)], axis=1).tobytes()


def opened(marks: bytes):
    m = np.frombuffer(marks, np.uint8).reshape(-1, MARK)
    return *_halves(m), np.ascontiguousarray(m[:, BITS // 8 :]).view("<f4").astype(float)


@pytest.mark.parametrize("block_marks", [1 << 17, 150])
def test_pairs_of_blocks_equal_all_pairs(spark, block_marks):
    rng = np.random.default_rng(11)
    shown = [picture(rng.normal(0, 0.1, 64).tolist()) for _ in range(12)]
    images = [im for k, im in enumerate(shown) for im in (im, edited(im, k), edited(im, 50 + k))]
    rows = [(k * 7 - 100, marks_of(im)) for k, im in enumerate(images)]
    df = spark.createDataFrame(rows, "node long, marks binary")
    first = spark.createDataFrame([(rows[0][0], rows[1][0], 9)], "a long, b long, agree long")
    got = {(r.a, r.b, r.agree) for r in _rest(df, first, MOST_BITS, LEAST_AGREE, block_marks).collect()}
    want = set()
    for x, (a, marks_a) in enumerate(rows):
        for y, (b, marks_b) in enumerate(rows[:x]):
            if {x, y} == {0, 1}:
                continue
            (ha, la, pa), (hb, lb, pb) = opened(marks_a), opened(marks_b)
            bits = np.bitwise_count(ha[:, None] ^ hb) + np.bitwise_count(la[:, None] ^ lb)
            met = (table_keys(ha, la)[:, None] == table_keys(hb, lb)[None]).any(axis=2)
            i, j = np.nonzero(met & (bits <= MOST_BITS))
            if len(i) >= LEAST_AGREE and (good := agreeing(pb[j], pa[i])) >= LEAST_AGREE:
                want.add((b, a, good))
    assert got == want and len(want) > 20


def test_no_agreeing_run_is_left_out():
    rng = np.random.default_rng(4)
    a = rng.integers(0, 30, (3000, 7, 2)).astype(float)
    b = a @ np.array([[0.8, 0.3], [-0.3, 0.8]]) + rng.normal(0, 3, a.shape)
    za, zb = (x.reshape(-1, 2) @ np.array([1, 1j]) for x in (a, b))
    likely = may_agree(za, zb, np.arange(3000) * 7, np.full(3000, 7), 6)
    good = np.array([agreeing(x, y) >= 6 for x, y in zip(a, b)])
    assert not (good & ~likely).any() and good.sum() > 20 and (~likely).sum() > 20


def test_tables_grow_with_corners_not_with_matches(spark, monkeypatch):
    """60 images with the same 8 codes at places of their own have 14,160 matches; the table of single matches took more disk than there was."""
    rng = np.random.default_rng(8)
    codes = rng.integers(0, 256, (8, BITS // 8), np.uint8)
    spots = rng.uniform(0, 300, (60, 8, 2)).astype("<f4")
    rows = [(k, np.concatenate([codes, s.view(np.uint8).reshape(8, 8)], axis=1).tobytes()) for k, s in enumerate(spots)]
    sizes = []

    def counted(df, name, *args):
        stored = materialise(df, name, *args)
        sizes.append(stored.count())
        return stored

    monkeypatch.setattr(descriptors, "materialise", counted)
    none = spark.createDataFrame([], "a long, b long, agree long")
    assert _rest(spark.createDataFrame(rows, "node long, marks binary"), none, MOST_BITS, LEAST_AGREE).count() == 0
    assert sizes and max(sizes) <= 3 * 8 * 60
