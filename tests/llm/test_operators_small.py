"""Sharding, bit packing, URL rules and toxicity against brute force."""

import math
import random
import zlib

import duckdb
import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from edgemill.llm import bitpack, sharding, toxicity, urlfilter
from edgemill.llm.wordtokens import word_encoder

PATH = public_tokenizers.path("word_bpe_49k.json")


# sharding

def one_by_one(sizes, shards):
    loads = [0] * shards
    for size, n in sorted(sizes, reverse=True):
        for _ in range(n):
            k = loads.index(min(loads))
            loads[k] += size
    return loads


@settings(max_examples=200, deadline=None)
@given(st.dictionaries(st.integers(1, 50), st.integers(1, 90), max_size=8), st.integers(1, 6))
def test_schedule_has_the_loads_of_one_by_one(sizes, shards):
    plan, loads = sharding.schedule(list(sizes.items()), shards)
    assert sorted(loads) == sorted(one_by_one(sizes.items(), shards))
    assert {s: sum(t) for s, t in plan} == sizes


def test_sharding(spark):
    rng = random.Random(1)
    rows = [(i, "x" * rng.randrange(300)) for i in range(400)] + [(i, "same") for i in range(400, 600)] + [(600, None), (601, ""), (602, "é" * 9000), (0, "x")]
    df = spark.createDataFrame([(d, t, 1) for d, t in rows], "doc_id long, text string, size int").repartition(3)
    got = sharding.shard_documents(df, 16).collect()
    assert len(got) == len(rows)
    text = {}
    for d, t in rows:
        text.setdefault(d, []).append(t or "")
    groups, loads = {}, [0] * 16
    for r in got:
        t = next(t for t in text[r.doc_id] if zlib.crc32(t.encode()) == r.text_crc32)
        assert r.size == len(t.encode()) + 1 and r.law == "bytes" and r.grown_shard is None
        assert groups.setdefault(t, r.shard) == r.shard
        loads[r.shard] += r.size
    sizes = {}
    for t in groups:
        total = sum((u or "") == t for _, u in rows) * (len(t.encode()) + 1)
        sizes[total] = sizes.get(total, 0) + 1
    assert sorted(loads) == sorted(one_by_one(sizes.items(), 16))
    for k in range(16):
        slots = sorted(r.slot for r in got if r.shard == k)
        assert slots == list(range(len(slots)))
    assert sharding.shard_documents(df.limit(0), 16).count() == 0


# bit packing

@settings(max_examples=200, deadline=None)
@given(st.integers(1, 32), st.data())
def test_pack_round_trip(bits, data):
    ids = np.array(data.draw(st.lists(st.integers(0, (1 << bits) - 1), max_size=150)), "<u4")
    packed = bitpack.pack(ids, bits)
    assert len(packed) == -(-len(ids) // 32) * bits * 4
    assert bitpack.unpack(packed, bits, len(ids)).tolist() == ids.tolist()


def test_random_access(tmp_path):
    docs = [np.arange(k, dtype="<u4") * 7 % 50_000 for k in (3, 0, 500, 64, 1)]
    with open(tmp_path / "f", "wb") as f:
        w = bitpack.PackedWriter(f, 16, block=64)
        for k, ids in enumerate(docs):
            w.add(np.array([k]), ids, np.array([len(ids)]))
        w.close()
    with pa.OSFile(str(tmp_path / "f")) as source:
        packed = bitpack.PackedFile(source)
        for k in (4, 2, 0, 1, 3):
            assert packed.document(k).tolist() == docs[k].tolist()
        assert packed.ids_between(100, 300).tolist() == np.concatenate(docs)[100:300].tolist()


def test_bitpack_operator(spark):
    rows = [(i * 3, f"Document number {i}, with words " * (i % 7)) for i in range(50)] + [(1, None), (2, "long " * 90_000), (1000, "twice"), (1000, "twice")]
    df = spark.createDataFrame([(d, t, 0) for d, t in rows], "doc_id long, text string, start int").repartition(3)
    got = sorted(bitpack.read_packed(bitpack.write_packed(df, PATH, 2)).collect(), key=lambda r: r.start)
    enc, at = word_encoder(PATH).library, 0
    by = {}
    for d, t in rows:
        by[d] = enc.encode(t or "", add_special_tokens=False).ids + [2]
    assert [r.doc_id for r in got] == sorted(d for d, _ in rows)
    for r in got:
        assert (r.start, r.n_tokens) == (at, len(by[r.doc_id]))
        assert r.ids_crc32 == zlib.crc32(np.array(by[r.doc_id], "<u4").tobytes())
        at += r.n_tokens
    assert bitpack.read_packed(bitpack.write_packed(df.limit(0), PATH, 2)).count() == 0


# URL rules

URLS = [None, "", "no scheme", "http://", "http://NET/", "http://a.net/x", "http://net", "http://xnet/y", "https://example.net/en/1?x=/fr/", "https://www.Example.NET/en/#a", "http://example.net/en",
        "http://a.example.com/de/page", "http://example.com/dex", "http://q.org/fr/", "http://q.org?x", "http://host:80/net/x", "http://x.y/a.net/", "http://spam.example.org/z", "ftp://b.edu/spam", "http://b.xxx/", "x://ü.net/é", "http://c.com/" + "a" * 3000 + "/ads/"]


def test_url_rules_equal_sql_and_brute_force(spark):
    rows = [(i, u, "h") for i, u in enumerate(URLS * 2)]
    df = spark.createDataFrame(rows, "page_id long, url string, host string").repartition(2)
    got = {r.page_id: tuple(r) for r in urlfilter.judge_urls(df, slice_bytes=100).collect()}
    pages = df.toPandas()  # noqa: F841  read by DuckDB
    con = duckdb.connect()
    con.register("pages", pages)
    expected = {r[0]: r for r in con.sql(urlfilter.oracle_sql()).fetchall()}
    assert got == expected
    assert urlfilter.judge_urls(df.limit(0)).count() == 0


@settings(max_examples=200, deadline=None)
@given(st.lists(st.text(alphabet="ab/.", min_size=1, max_size=4), min_size=1, max_size=5), st.lists(st.text(alphabet="ab/.", max_size=12), max_size=8))
def test_automaton_equals_matching_one_by_one(parts, texts):
    from fnmatch import fnmatchcase

    globs = [f"*{p}*" for p in parts] + [f"*{'*'.join(parts)}"] * 2 + ["*" + "ab" * 40 + "*"]
    hit = urlfilter.ShiftAnd([urlfilter.Glob.of_glob(g) for g in globs]).run([t.encode() for t in texts])
    assert hit.tolist() == [[fnmatchcase(t, g) for g in globs] for t in texts]


# toxicity

def all_segments(scores):
    """Maximal segments by their definition: the best one (shortest, leftmost), then left and right of it."""
    best = None
    for i in range(len(scores)):
        for j in range(i, len(scores)):
            v = sum(scores[i : j + 1])
            if v > 0 and (best is None or v > best[0] + 1e-9 or abs(v - best[0]) <= 1e-9 and j - i < best[2] - best[1]):
                best = (v, i, j)
    if best is None:
        return []
    v, i, j = best
    return all_segments(scores[:i]) + [(v, i, j)] + [(a, b + j + 1, c + j + 1) for a, b, c in all_segments(scores[j + 1 :])]


@settings(max_examples=300, deadline=None)
@given(st.lists(st.sampled_from([-3.5, -1.25, -0.5, 0.75, 2.0, 4.25]), max_size=14))
def test_maximal_segments(scores):
    got = toxicity.maximal_segments([(s, k, k) for k, s in enumerate(scores)])
    assert math.isclose(sum(v for v, _, _ in got), sum(v for v, _, _ in all_segments(scores)))
    assert max((v for v, _, _ in got), default=0) == max((v for v, _, _ in all_segments(scores)), default=0)
    assert all(math.isclose(sum(scores[a : b + 1]), v) for v, a, b in got)
    assert all(x[2] < y[1] for x, y in zip(got, got[1:]))


def test_lambda_and_isotonic():
    lam = toxicity.solve_lambda(np.array([0.1, 0.9]), np.array([1.0, -1.0]))
    assert math.isclose(0.1 * math.exp(lam) + 0.9 * math.exp(-lam), 1.0, rel_tol=1e-6)
    levels = toxicity.isotonic(np.arange(4), np.array([0, 5, 1, 9]), np.array([10, 10, 10, 10]))
    assert list(levels) == sorted(levels) and levels[1] == levels[2]


@pytest.fixture(scope="module")
def prose(spark):
    rng = random.Random(4)
    rows, marks = [], []
    for i in range(600):
        words = [f"w{rng.randrange(500)}" for _ in range(rng.randrange(20, 120))]
        bad = rng.random() < 0.2
        if bad:
            for _ in range(rng.randrange(2, 5)):
                words.insert(rng.randrange(len(words)), rng.choice(["scum", "uglyness", "uglyling"]))
        rows.append((i, " ".join(words), "en"))
        marks.append((i, int(bad)))
    return spark.createDataFrame(rows, "doc_id long, text string, score string"), spark.createDataFrame(marks, "doc_id long, toxic int"), dict(marks)


def test_toxicity_on_held_out_rows(spark, prose):
    docs, labels, truth = prose
    model = toxicity.fit(docs, labels)
    held = {r.doc_id for r in docs.where(toxicity.held_out(docs.doc_id)).select("doc_id").collect()}
    assert held == {i for i in truth if zlib.crc32(str(i).encode()) % 4 == 2}
    rows = toxicity.score(docs, model).collect()
    right = sum(r.predicted == truth[r.doc_id] for r in rows if r.doc_id in held)
    assert right >= 0.97 * len(held)
    spans = toxicity.toxic_segments(docs, model).collect()
    text = {r.doc_id: r.text for r in docs.collect()}
    assert spans and all(text[r.doc_id][r.start : r.end] == r.passage and ("scum" in r.passage or "ugly" in r.passage) for r in spans)
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "scum " * 40_000), (3, "scum " * 40_000), (4, "漢字 scum uglyness scum")], "doc_id long, text string")
    got = {r.doc_id: r for r in toxicity.score(odd, model).collect()}
    assert got[1].predicted == got[2].predicted == 0 and got[3].predicted == got[4].predicted == 1
    assert toxicity.keep_clean(odd, model).count() == 2


def test_toxicity_without_labels(spark, prose):
    docs, labels, _ = prose
    assert {r.score for r in toxicity.score(docs, toxicity.fit(docs, labels.limit(0))).collect()} == {0.0}
    assert toxicity.score(docs.limit(0), toxicity.fit(docs.limit(0), labels)).count() == 0
