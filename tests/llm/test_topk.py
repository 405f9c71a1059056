import math
import random

import numpy as np

from edgemill.llm.topk import top_k


def brute(rows, k, every, scale):
    ok = [(i, [math.floor(scale * float(x)) for x in v]) for i, v in rows if v and all(x is not None and math.isfinite(x) for x in v)]
    out = {}
    for q in sorted({i for i, _ in ok if i % every == 0}):
        qv = min(v for i, v in ok if i == q)
        scored = sorted((-sum(a * b for a, b in zip(qv, v)), i) for i, v in ok if i != q and len(v) == len(qv))
        out[q] = [(r + 1, i, -s) for r, (s, i) in enumerate(scored[:k])]
    return out


def run(spark, rows, **kw):
    df = spark.createDataFrame([(i, v, "x") for i, v in rows], "vec_id long, embedding array<float>, score string").repartition(3)
    got = {}
    for r in top_k(df, **kw).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    return {q: sorted(v) for q, v in got.items()}


def test_equals_brute_force(spark):
    rng = random.Random(5)
    rows = [(i, [float(np.float32(rng.gauss(0, 0.2))) for _ in range(16)]) for i in range(300)]
    rows += [(1000 + i, rows[10][1]) for i in range(40)]  # ties
    rows += [(500, None), (501, [1.0, None] + [0.0] * 14), (600, [float("nan")] * 16), (700, [float("inf")] + [0.0] * 15), (800, [])]
    rows += [(900, [0.5, 0.25]), (901, [1.0, 1.0]), (17, rows[17][1]), (20, rows[20][1])]
    for block in (4096, 7):
        assert run(spark, rows, k=10, every=10, chunk=64, block=block) == {q: v for q, v in brute(rows, 10, 10, 1024).items() if v}


def test_fewer_rows_than_k_and_empty(spark):
    rows = [(0, [1.0, 2.0]), (1, [3.0, -1.0]), (2, [-3.0, -1.0])]
    assert run(spark, rows, k=10, every=2) == brute(rows, 10, 2, 1024)
    assert run(spark, [], k=10) == {}


def test_large_components_stay_exact(spark):
    rows = [(0, [3.0e5, 7.0e5]), (1, [5.0e5 + 1, 11.0e5]), (2, [-5.0e5, 3.0])]
    assert run(spark, rows, k=2, every=1) == brute(rows, 2, 1, 1024)
