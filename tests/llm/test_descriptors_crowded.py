"""Copies whose corners have nearer strangers in every table entry than each other."""

import numpy as np
import pyarrow as pa
import pytest

from edgemill.llm import descriptors
from edgemill.llm.descriptors import _match_rest, find_copies


def code_bytes(bits: np.ndarray) -> bytes:
    return np.packbits(bits.astype(np.uint8)).tobytes()


def place_bytes(x: float, y: float) -> bytes:
    return np.array([x, y], "<f4").tobytes()


def crowded(corners: int = 8, strangers: int = 4) -> list[tuple[int, bytes, bytes]]:
    """Media 1 and 2 share all corners, 10 bits apart; each corner of each is met exactly by so many media that have this one only."""
    rng = np.random.default_rng(3)
    one, two, others = b"", b"", []
    for c in range(corners):
        bits = rng.integers(0, 2, 128)
        near = bits.copy()
        near[[50, 51, 52, 53, 54, 90, 91, 92, 93, 94]] ^= 1  # the first 42 bits stay, the other two keys change
        x, y = 20.0 * c, 7.0 * c * c
        one += code_bytes(bits) + place_bytes(x, y)
        two += code_bytes(near) + place_bytes(x + 5, y + 9)
        for k in range(strangers):
            others += [code_bytes(bits) + place_bytes(k, c), code_bytes(near) + place_bytes(c, k)]
    marks = [one, two, *others]
    return [(k + 1, f"image {k}".encode(), m) for k, m in enumerate(marks)]


@pytest.mark.parametrize("block", [4096, 3])
def test_copies_among_nearer_strangers(spark, monkeypatch, block):
    rows = crowded()
    described = spark.createDataFrame(rows, "media_id long, image_key binary, marks binary")
    monkeypatch.setattr(descriptors, "_described", lambda media, reach: described)
    media = spark.createDataFrame([(k, None) for k, _, _ in rows], "media_id long, media binary")
    found = {r.media_id: r for r in find_copies(media, block=block).collect()}
    assert len(found) == len(rows)
    assert (found[1].class_id, found[2].class_id, found[1].n_agree, found[2].n_agree) == (1, 1, 8, 8)
    assert all(r.class_id == k and r.n_agree == 0 for k, r in found.items() if k > 2)


def test_rest_has_every_match_of_different_classes():
    """Against all pairs, in one block and in a pair of blocks."""
    rng = np.random.default_rng(5)
    n = 60
    codes = np.zeros((n, 128), np.uint8)
    for k in range(n):
        codes[k, rng.choice(128, 9, replace=False)] = 1
    node, root, own = np.arange(n) * 3 % 45, np.arange(n) * 3 % 45 // 9, np.arange(n) % 2
    marks = [code_bytes(codes[k]) + place_bytes(k, 0) for k in range(n)]
    for first, second in ((0, 0), (0, 1)):
        rows = [k for k in range(n) if own[k] in (first, second)]
        batch = pa.RecordBatch.from_pydict({
            "key": np.zeros(len(rows), np.int64), "first": np.full(len(rows), first, np.int32), "second": np.full(len(rows), second, np.int32), "own": own[rows].astype(np.int32),
            "node": node[rows].astype(np.int64), "root": root[rows].astype(np.int64), "mark": pa.array([marks[k] for k in rows], pa.binary()),
        })
        got = sorted(tuple(r.values()) for out in _match_rest(16)([batch.slice(0, 11), batch.slice(11)]) for r in out.to_pylist())
        place = [int(np.frombuffer(m[16:], "<i8")[0]) for m in marks]
        want = []
        for i in rows:
            for j in rows:
                if i < j and root[i] != root[j] and (codes[i] != codes[j]).sum() <= 16 and (first == second or own[i] != own[j]):
                    a, b = (i, j) if node[i] < node[j] else (j, i)
                    want.append((int(node[a]), int(node[b]), place[a], place[b]))
        assert got == sorted(want) and len(want) > 50
