import numpy as np

from edgemill.llm.descriptors import KEY_BITS, LEAST_AGREE, MOST_BITS, _halves, agreeing, describe, edited, find_copies, media_of_embeddings, partners, picture, read_pgm, resize, table_keys, write_pgm


def textures(n, seed=0):
    rng = np.random.default_rng(seed)
    return [picture(rng.normal(0, 0.1, 64).tolist()) for _ in range(n)]


def classes(rows):
    by = {}
    for r in rows:
        by.setdefault(r.class_id, set()).add(r.media_id)
    assert all(k == min(v) for k, v in by.items())
    return {frozenset(v) for v in by.values()}


def test_pgm_round_trip_and_broken_bytes():
    image = textures(1)[0]
    assert np.array_equal(read_pgm(write_pgm(image)), np.rint(image))
    for data in (None, b"", b"P5", b"P5 4 4 255\nxx", b"P6 1 1 255\nx", b"P5 a b c\n", b"P5 1 1 65535\nxx"):
        assert read_pgm(data) is None


def test_consensus_finds_the_transform():
    rng = np.random.default_rng(1)
    a = rng.uniform(0, 80, (30, 2))
    turn = 0.8 * np.exp(0.5j)
    z = (a[:, 0] + 1j * a[:, 1]) * turn + (3 - 7j)
    b = np.stack([z.real, z.imag], axis=1)
    b[20:] = rng.uniform(0, 80, (10, 2))
    assert agreeing(a, b) >= 20
    assert agreeing(a, rng.uniform(0, 80, (30, 2))) < 10


def test_crops_edits_turns_and_strangers(spark):
    images = textures(24)
    rows = [(i, write_pgm(im)) for i, im in enumerate(images)]
    rows += [(100 + i, write_pgm(edited(im, i))) for i, im in enumerate(images[:20])]
    rows += [(200 + i, write_pgm(np.rot90(im))) for i, im in enumerate(images[:6])]
    rows += [(300, write_pgm(images[23])), (301, write_pgm(images[23])), (302, None), (303, None), (304, b"broken"), (305, b"broken"), (306, write_pgm(np.full((60, 60), 9.0))), (307, write_pgm(np.zeros((2, 2))))]
    df = spark.createDataFrame([(i, d, "x") for i, d in rows], "media_id long, media binary, node string").repartition(3)
    expected = {frozenset({i, 100 + i} | ({200 + i} if i < 6 else set())) for i in range(20)} | {frozenset({i}) for i in (20, 21, 22, 302, 303, 306, 307)} | {frozenset({23, 300, 301}), frozenset({304, 305})}
    assert classes(find_copies(df).collect()) == expected
    assert classes(find_copies(df, block=5).collect()) == expected
    assert find_copies(df.limit(0)).count() == 0


def test_given_vectors(spark):
    rows = [(i, np.random.default_rng(i).normal(0, 0.1, 64).astype(np.float32).tolist()) for i in range(20)] + [(50, None), (51, [])]
    got = find_copies(media_of_embeddings(spark.createDataFrame(rows, "vec_id long, embedding array<float>"))).collect()
    assert classes(got) == {frozenset({2 * i, 2 * i + 1}) for i in range(20)} | {frozenset({100, 101, 102, 103})}


def test_small_images_have_no_corners():
    assert len(describe(np.zeros((5, 5), np.float32))[0]) == 0
    assert resize(np.ones((1, 1), np.float32), 4, 4).shape == (4, 4)


def brute_classes(media):
    """Every pair of images: all pairs of corners that share a table key and differ in few bits must agree."""
    seen = [(i, *describe(read_pgm(d))) for i, d in media]
    root = {i: i for i, _ in media}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for k, (i, place_i, code_i) in enumerate(seen):
        for j, place_j, code_j in seen[:k]:
            if not len(code_i) or not len(code_j):
                continue
            (hi, li), (hj, lj) = _halves(code_i), _halves(code_j)
            bits = np.bitwise_count(hi[:, None] ^ hj) + np.bitwise_count(li[:, None] ^ lj)
            met = (table_keys(hi, li)[:, None] == table_keys(hj, lj)[None]).any(axis=2)
            x, y = np.nonzero(met & (bits <= MOST_BITS))
            if len(x) >= LEAST_AGREE and agreeing(place_i[x, :2], place_j[y, :2]) >= LEAST_AGREE:
                a, b = sorted((find(i), find(j)))
                root[b] = a
    by = {}
    for i, _ in media:
        by.setdefault(find(i), set()).add(i)
    return {frozenset(v) for v in by.values()}


def test_equals_brute_force_over_all_pairs(spark):
    images = textures(40, seed=3)
    media = [(i, write_pgm(im)) for i, im in enumerate(images)] + [(100 + i, write_pgm(edited(im, i))) for i, im in enumerate(images[:30])] + [(200 + i, write_pgm(edited(images[0], 900 + i))) for i in range(25)]
    df = spark.createDataFrame(media, "media_id long, media binary").repartition(3)
    assert classes(find_copies(df).collect()) == brute_classes(media)


def test_recall_among_many_strangers(spark):
    """2,000 media, a picture and its edited crop each: nine of ten pairs at least, and no two pictures in one class."""
    rows = [(i, np.random.default_rng(i).normal(0, 0.1, 64).astype(np.float32).tolist()) for i in range(1000)]
    got = find_copies(media_of_embeddings(spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(8))).collect()
    found = classes(got)
    assert all(len({m // 2 for m in c}) == 1 for c in found)
    assert sum(len(c) == 2 for c in found) >= 900


def test_a_large_class_of_edits_stays_whole(spark):
    images = textures(60, seed=9)
    rows = [(1000 + i, write_pgm(edited(images[0], i))) for i in range(400)] + [(i, write_pgm(im)) for i, im in enumerate(images[1:])]
    found = classes(find_copies(spark.createDataFrame(rows, "media_id long, media binary").repartition(4), block=300).collect())
    assert max(map(len, found)) >= 392 and all(len(c) == 1 for c in found if min(c) < 1000)


def test_small_crop_of_a_large_image(spark):
    rng = np.random.default_rng(5)
    large = [np.clip(resize(rng.uniform(-1, 1, (90, 90)).astype(np.float32), 300, 300) * 80 + 128, 0, 255) for _ in range(6)]
    rows = [(i, write_pgm(im)) for i, im in enumerate(large)] + [(10 + i, write_pgm(im[150:230, 60:140])) for i, im in enumerate(large)]
    wide = resize(rng.uniform(-1, 1, (12, 6000)).astype(np.float32), 40, 20_000) * 80 + 128
    rows += [(50, write_pgm(wide)), (51, write_pgm(wide[:, 19_400:]))]
    found = classes(find_copies(spark.createDataFrame(rows, "media_id long, media binary")).collect())
    assert found == {frozenset({i, 10 + i}) for i in range(6)} | {frozenset({50, 51})}


def test_ids_null_negative_and_repeated(spark):
    images = textures(4, seed=2)
    rows = [(None, write_pgm(images[0]), 1), (None, write_pgm(edited(images[0], 1)), 1), (-7, write_pgm(images[1]), 1), (-3, write_pgm(edited(images[1], 2)), 1), (None, write_pgm(images[1]), 1)]
    rows += [(None, None, 1), (None, None, 1), (8, None, 1), (8, None, 1), (9, None, 1), (5, write_pgm(images[2]), 1), (5, write_pgm(images[2]), 1)]
    df = spark.createDataFrame(rows, "media_id long, media binary, class_id int")
    got = sorted((r.media_id is None, r.media_id or 0, r.class_id is None, r.class_id or 0, r.n_equal) for r in find_copies(df).collect())
    assert got == sorted([(True, 0, True, 0, 1)] * 2 + [(False, -7, False, -7, 2), (False, -3, False, -7, 1), (True, 0, False, -7, 2)] + [(True, 0, True, 0, 2)] * 2 + [(False, 8, False, 8, 2)] * 2 + [(False, 9, False, 9, 1)] + [(False, 5, False, 5, 2)] * 2)
    odd = spark.createDataFrame([(None, [0.5] * 64), (-4, [0.25] * 64), (3, None)], "vec_id long, embedding array<float>")
    assert sorted(r.media_id is None or r.media_id for r in media_of_embeddings(odd).collect()) == sorted([True, True, -8, -7, 6, 7])


def test_partners_are_nearest_and_least():
    rng = np.random.default_rng(0)
    node = np.sort(rng.integers(0, 40, 200))
    high, low = rng.integers(0, 16, 200).astype(np.uint64), rng.integers(0, 16, 200).astype(np.uint64)
    got = set(zip(*(x.tolist() for x in partners(node, high, low, 4, 2))))
    bits = lambda i, j: int(high[i] ^ high[j]).bit_count() + int(low[i] ^ low[j]).bit_count()
    for i in range(200):
        strangers = [j for j in range(200) if node[j] != node[i]]
        nearest = min(strangers, key=lambda j: (bits(i, j), j))
        assert bits(i, nearest) > 4 or (i, nearest) in got
        close = [j for j in strangers if bits(i, j) <= 2]
        assert not close or (i, close[0]) in got
    assert table_keys(np.array([2**64 - 1], np.uint64), np.array([0], np.uint64)).tolist() == [[((1 << KEY_BITS) - 1) << 2, (((1 << 22) - 1) << 20) << 2 | 1, 2]]
