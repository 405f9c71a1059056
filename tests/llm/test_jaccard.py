import random
import re

import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from edgemill.llm.jaccard import BLOCK, keep_one, least_matches, similarity_join


def grams(text, n=5):
    words = re.findall(r"\w+", (text or "").lower())
    return {tuple(words[i : i + n]) for i in range(max(1, len(words) - n + 1))} if words else set()


def brute(rows):
    """(links between different texts, classes of linked and equal texts) of (doc_id, text) rows."""
    texts = sorted({t or "" for _, t in rows})
    sets = [grams(t) for t in texts]
    links = {t: 0 for t in texts}
    parent = {t: t for t in texts}

    def top(t):
        while parent[t] != t:
            t = parent[t]
        return t

    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if a and b and len(a) * 0.8 <= len(b) <= len(a) / 0.8 and len(a & b) >= 0.8 * len(a | b) - 1e-9:
                links[texts[i]] += 1
                links[texts[j]] += 1
                parent[top(texts[i])] = top(texts[j])
    classes = {}
    for d, t in rows:
        classes.setdefault(top(t or ""), set()).add(d)
    return links, {frozenset(c) for c in classes.values()}


def check(spark, rows, **options):
    df = spark.createDataFrame([(d, t, "x") for d, t in rows], "doc_id long, text string, node string").repartition(3)
    got = similarity_join(df, **options).collect()
    links, classes = brute(rows)
    assert len(got) == len(rows)
    text = dict(rows)
    for r in got:
        assert r.n_links == links[text[r.doc_id] or ""]
        assert r.n_copies == sum((t or "") == (text[r.doc_id] or "") for _, t in rows)
        assert r.text_id == min(d for d, t in rows if (t or "") == (text[r.doc_id] or ""))
    by = {}
    for r in got:
        by.setdefault(r.class_id, set()).add(r.doc_id)
    assert {frozenset(c) for c in by.values()} == classes
    assert all(k == min(c) for k, c in by.items())


def corpus(seed=3):
    rng = random.Random(seed)
    words = [f"w{k}" for k in range(400)]
    rows, n = [], 0
    for _ in range(12):
        base = [rng.choice(words) for _ in range(rng.choice([4, 30, 120]))]
        for _ in range(rng.choice([1, 2, 30])):
            t = list(base)
            for _ in range(rng.choice([0, 0, 1, 2, 3])):
                t[rng.randrange(len(t))] = rng.choice(words)
            rows.append((n, " ".join(t)))
            n += 1
    return rows + [(n, None), (n + 1, ""), (n + 2, "... !!"), (n + 3, "one"), (n + 4, "ONE"), (n + 5, "Two words"), (n + 6, " ".join(words * 60)), (n + 7, " ".join(words * 60))]


@pytest.mark.parametrize("block", [BLOCK, 8])
def test_equals_brute_force(spark, block):
    check(spark, corpus(), block=block)


def test_given_documents(spark):
    table = pq.read_table("/root/testdata/sf0.001/documents.parquet")
    check(spark, list(zip(table["doc_id"].to_pylist(), table["text"].to_pylist())))


def test_large_group_takes_the_matrix_way(spark):
    rng = random.Random(9)
    base = [f"w{rng.randrange(3000)}" for _ in range(120)]
    rows = []
    for k in range(140):
        t = list(base)
        for _ in range(rng.randrange(4)):
            t[rng.randrange(120)] = f"x{k}"
        rows.append((k, " ".join(t)))
    check(spark, rows, block=64)


def test_empty_and_repeated(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert similarity_join(empty).count() == 0 and keep_one(empty).count() == 0
    df = spark.createDataFrame([(1, "a b c d e f", 3), (1, "a b c d e f", 3), (2, "a b c d e f", 4), (3, None, 5), (4, "", 6)], "doc_id long, text string, root int")
    assert sorted((r.doc_id, r.root) for r in keep_one(df).collect()) == [(1, 3), (3, 5)]
    assert [r.n_copies for r in similarity_join(df).where("doc_id < 3").collect()] == [3, 3, 3]


def test_null_ids_are_documents(spark):
    words = [f"w{k}" for k in range(60)]
    text = lambda *changed: " ".join([*words[: 60 - len(changed)], *changed])
    other = lambda *changed: " ".join([*words[::-1][: 60 - len(changed)], *changed])
    rows = [
        (None, "stands alone here and nowhere else at all"),
        (None, "a text of several"), (None, "a text of several"),
        (None, text("n")), (7, text("x")), (5, text("y", "z")),
        (None, other("p")), (None, other("q")),
        (9, "has an id too"), (None, "has an id too"), (None, None),
    ]
    df = spark.createDataFrame([(d, t, k) for k, (d, t) in enumerate(rows)], "doc_id long, text string, row int").repartition(3)
    got = similarity_join(df).collect()
    links, _ = brute(rows)
    assert sorted(r.n_links for r in got) == sorted(links[t or ""] for _, t in rows)
    assert {(r.doc_id, r.class_id) for r in got if r.doc_id is not None} == {(7, 5), (5, 5), (9, 9)}
    assert sorted(r.class_id for r in got if r.doc_id is None and r.class_id is not None) == [5, 9]
    kept = keep_one(df).collect()
    assert sorted(r.doc_id for r in kept if r.doc_id is not None) == [5, 9]
    unnamed = [r.text for r in kept if r.doc_id is None]
    assert len(unnamed) == 4 and {rows[0][1], rows[1][1], None} < set(unnamed) and len({other("p"), other("q")} & set(unnamed)) == 1


def test_tolerance_table():
    assert 0 < least_matches(16, 0.8, 1e-6) < least_matches(80, 0.8, 1e-6) < 64
