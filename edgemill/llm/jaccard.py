"""Near-duplicate texts: a self-join on the Jaccard similarity of word n-grams.

Equal texts collapse to one node. MinHash bands propose candidates; hash values
of a proposed pair are compared step by step, and the pair is dropped as
soon as the posterior probability (uniform prior) that its similarity
reaches the threshold falls below a tolerance. Pairs that survive link candidate
components; inside a component every pair is compared in the same way and
the survivors are verified exactly on their n-gram sets.

No pair of a group is a row: buckets and components are cut into blocks (n-gram sets into
blocks of so many n-grams, whatever the length of the texts), a task
compares two blocks with arrays and returns one row per node (its number of
links and the least node it is connected to). Nothing is capped. What can be
lost is bounded by the bands (a pair at the threshold shares none with
probability (1 - t^rows)^bands, 2e-5 at 0.8) and the tolerance.

N-grams are hashed to 64 bits, words are lower-cased runs of letters, digits and
underscores. A text of fewer words than n has one n-gram, all its words; a text
without words (null and empty ones among them) has none and is similar
only to texts equal to it (null counts as empty). Repeated rows are copies. Rows with null doc_id are
documents like any other; class_id and text_id are null only where no document of the class or text has an id. An empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgemill.llm.common import id_and_text, materialise, ship_package
from edgemill.llm.words import word_lists
from edgemill.operators.components import connected_components

THRESHOLD, N = 0.8, 5
BANDS, ROWS = 20, 4
STEP = 16  # hash values compared between two looks at the posterior
TOLERANCE = 1e-6
BLOCK = 1024  # nodes in a block
BLOCK_GRAMS = 1 << 20  # n-grams in a block of n-gram sets
JOIN_SCHEMA = "doc_id long, class_id long, text_id long, n_copies long, n_links long"


@cache
def least_matches(hashes: int, threshold: float, tolerance: float) -> int:
    """The fewest equal values among `hashes` that leave the pair alive.

    With a uniform prior the posterior of the similarity is Beta(m + 1, n - m + 1), and the
    chance that it is at least t equals that of at most m successes in n + 1 trials of t.
    """
    total = 0.0
    for m in range(hashes + 1):
        total += comb(hashes + 1, m) * threshold**m * (1 - threshold) ** (hashes + 1 - m)
        if total >= tolerance:
            return m
    return hashes


@cache
def multipliers(count: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20)
    return rng.integers(0, 1 << 31, count, dtype=np.uint32) * np.uint32(2) + np.uint32(1), rng.integers(0, 1 << 32, count, dtype=np.uint32)


def _mixed(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    return x ^ (x >> np.uint64(32))


def gram_hashes(texts: pa.Array, n: int = N) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(64-bit hashes of the n-grams of the texts end to end, how many each text has), slice by slice; not made distinct."""
    odd = np.random.default_rng(5).integers(0, 1 << 63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    for codes, words, sizes in word_lists(texts):
        of = np.fromiter((xxhash.xxh64_intdigest(w.encode()) for w in words), np.uint64, len(words))
        token = of[codes] if len(codes) else np.zeros(0, np.uint64)
        starts = np.cumsum(sizes) - sizes
        grams = np.maximum(sizes - n + 1, np.minimum(sizes, 1))
        place = np.repeat(starts - (np.cumsum(grams) - grams), grams) + np.arange(int(grams.sum()))
        padded = np.concatenate([token, np.zeros(n, np.uint64)])
        short = np.repeat((sizes < n) & (sizes > 0), grams)
        room = np.repeat(sizes, grams)
        total = np.zeros(len(place), np.uint64)
        for k in range(n):
            part = padded[place + k] * odd[k]
            if short.any():
                part = np.where(short & (room <= k), np.uint64(k), part)
            total = total + part
        yield _mixed(total), grams


def signatures(grams: np.ndarray, counts: np.ndarray, hashes: int) -> np.ndarray:
    """MinHash values, texts x hashes; all ones for texts without n-grams."""
    out = np.full((len(counts), hashes), np.uint32(0xFFFFFFFF))
    some = np.flatnonzero(counts)
    if len(some):
        starts = (np.cumsum(counts) - counts)[some]
        high = (grams >> np.uint64(32)).astype(np.uint32)
        for h, (a, b) in enumerate(zip(*multipliers(hashes))):
            out[some, h] = np.minimum.reduceat(high * a + b, starts)
    return out


def band_keys(signature: np.ndarray, bands: int, rows: int) -> np.ndarray:
    keys = np.empty((len(signature), bands), np.uint64)
    for band in range(bands):
        key = np.full(len(signature), np.uint64(band + 1))
        for v in signature[:, band * rows : (band + 1) * rows].T:
            key = _mixed(key * np.uint64(0x9E3779B97F4A7C15) + v)
        keys[:, band] = key
    return keys.view(np.int64)


def _fingerprints(docs: DataFrame, n: int, bands: int, rows: int) -> DataFrame:
    """doc_id, text_key, number of n-grams and, for texts with some, signature (16 bits a value) and band keys; one narrow pass over the texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = 0
            for grams, counts in gram_hashes(batch.column(2), n):
                sig = signatures(grams, counts, bands * rows)
                keys = band_keys(sig, bands, rows)
                low = sig.astype("<u2").view(np.uint8).reshape(len(counts), -1)
                some = counts > 0
                width = low.shape[1]
                packed = pa.FixedSizeBinaryArray.from_buffers(pa.binary(width), len(low), [None, pa.py_buffer(np.ascontiguousarray(low))]).cast(pa.binary())
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(some * bands)]).astype(np.int32)), pa.array(keys[some].reshape(-1)))
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(at, len(counts)), batch.column(1).slice(at, len(counts)), pa.array(counts.astype(np.int64)), packed, lists], ["doc_id", "text_key", "n_grams", "signature", "bands"]
                )
                at += len(counts)

    text = F.coalesce("text", F.lit(""))
    keyed = id_and_text(docs).select("doc_id", F.unhex(F.md5(text.cast("binary"))).alias("text_key"), text.alias("text"))
    return keyed.mapInArrow(run, "doc_id long, text_key binary, n_grams long, signature binary, bands array<long>")


def _alive(a: np.ndarray, b: np.ndarray, threshold: float, tolerance: float) -> np.ndarray:
    """Matrix a x b of the pairs that the posterior never drops; a and b are signatures."""
    same = np.zeros((len(a), len(b)), np.int16)
    alive = np.ones(same.shape, bool)
    for lo in range(0, a.shape[1], STEP):
        hi = min(lo + STEP, a.shape[1])
        for h in range(lo, hi):
            same += a[:, h][:, None] == b[:, h][None, :]
        alive &= same >= least_matches(hi, threshold, tolerance)
        if not alive.any():
            break
    return alive


def _grouped(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[list[pa.RecordBatch]]:
    """Runs of rows with equal first `keys` columns, of rows sorted by them, as lists of batch slices."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [batch.column(k).to_numpy() for k in range(keys)]
        change = np.zeros(batch.num_rows, bool)
        for c in columns:
            change[1:] |= c[1:] != c[:-1]
        first = tuple(c[0] for c in columns)
        change[0] = last is not None and first != last
        last = tuple(c[-1] for c in columns)
        at = 0
        for k in np.flatnonzero(change).tolist():
            if k > at:
                held.append(batch.slice(at, k - at))
            if held:
                yield held
            held, at = [], k
        held.append(batch.slice(at))
    if held:
        yield held


def _signature_rows(column: pa.Array) -> np.ndarray:
    flat = np.frombuffer(b"".join(column.to_pylist()), "<u2")
    return flat.reshape(len(column), -1)


def _spanning(nodes: np.ndarray, near) -> tuple[np.ndarray, np.ndarray]:
    """(node, least node of its component) by breadth-first search over near(i, unvisited) -> those adjacent to i."""
    left = np.arange(len(nodes))
    roots = nodes.copy()
    while len(left):
        queue, left = [int(left[0])], left[1:]
        member = list(queue)
        while queue and len(left):
            hit = near(queue.pop(), left)
            if hit.any():
                found = left[hit]
                left = left[~hit]
                queue += found.tolist()
                member += found.tolist()
        roots[member] = nodes[member].min()
    return nodes, roots


def _link_candidates(threshold: float, tolerance: float):
    """Rows (key, first block, second block, node, signature) sorted by group to (a, b) links of surviving candidates."""

    def bucket(rows: list[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray]:
        nodes = np.concatenate([b.column(3).to_numpy() for b in rows])
        sig = np.concatenate([_signature_rows(b.column(4)) for b in rows])
        nodes, roots = _spanning(nodes, lambda i, left: _alive(sig[i : i + 1], sig[left], threshold, tolerance)[0])
        return nodes[nodes != roots], roots[nodes != roots]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pairs: list[tuple] = []
        larger: list[tuple[np.ndarray, np.ndarray]] = []

        def flush():
            nodes = np.array([(p[0], p[2]) for p in pairs], np.int64).reshape(-1, 2)
            a, b = (np.frombuffer(b"".join(p[k] for p in pairs), "<u2").reshape(len(pairs), -1) for k in (1, 3))
            alive = np.ones(len(pairs), bool)
            for hi in range(STEP, a.shape[1] + STEP, STEP):
                hi = min(hi, a.shape[1])
                alive &= (a[:, :hi] == b[:, :hi]).sum(axis=1) >= least_matches(hi, threshold, tolerance)
            pairs.clear()
            out = [(nodes[alive].max(axis=1), nodes[alive].min(axis=1)), *larger]
            larger.clear()
            both = np.unique(np.stack([np.concatenate([x for x, _ in out]), np.concatenate([y for _, y in out])], axis=1), axis=0)
            return pa.RecordBatch.from_pydict({"a": both[:, 0], "b": both[:, 1]})

        for rows in _grouped(batches, 3):
            size = sum(b.num_rows for b in rows)
            if size == 2:
                two = [(b.column(3)[k].as_py(), b.column(4)[k].as_py()) for b in rows for k in range(b.num_rows)]
                pairs.append((*two[0], *two[1]))
            elif size > 2:
                larger.append(bucket(rows))
            if len(pairs) >= 20_000 or len(larger) >= 2_000:
                yield flush() if pairs else _links(larger)
        if pairs:
            yield flush()
        elif larger:
            yield _links(larger)

    return run


def _links(larger: list) -> pa.RecordBatch:
    both = np.unique(np.stack([np.concatenate([x for x, _ in larger]), np.concatenate([y for _, y in larger])], axis=1), axis=0)
    larger.clear()
    return pa.RecordBatch.from_pydict({"a": both[:, 0], "b": both[:, 1]})


def _in_blocks(rows: DataFrame, keys: list[str], size: str, block: int) -> DataFrame:
    """Cut groups of more than `block` nodes into hash blocks; every row goes to each pair of blocks that its own is in."""
    many = F.ceil(F.col(size) / block).cast("int")
    own = F.pmod(F.xxhash64("node"), many).cast("int")
    other = F.explode(F.sequence(F.lit(0), many - 1))
    cut = rows.withColumn("_own", own).withColumn("_other", other)
    return cut.withColumn("first_block", F.least("_own", "_other")).withColumn("second_block", F.greatest("_own", "_other")).drop("_other")


def overlaps(a: list[np.ndarray], b: list[np.ndarray]) -> np.ndarray:
    """Sizes of the intersections of all sets of a with all of b.

    N-grams that many sets hold are multiplied as dense columns, the others are
    added where they meet; one held by a single set adds nothing.
    """
    out = np.zeros((len(a), len(b)), np.float32)
    owner = np.repeat(np.arange(len(a) + len(b)), [len(x) for x in (*a, *b)])
    if not len(owner):
        return out
    grams = np.concatenate([*a, *b])
    order = np.argsort(grams, kind="stable")
    grams, owner = grams[order], owner[order]
    starts = np.flatnonzero(np.concatenate([[True], grams[1:] != grams[:-1]]))
    sizes = np.diff(np.append(starts, len(grams)))
    in_a = np.add.reduceat((owner < len(a)).astype(np.int64), starts)
    work = in_a * (sizes - in_a)
    dense = np.flatnonzero(work > max(64, len(a) * len(b) // 64))
    for at in range(0, len(dense), 512):
        part = dense[at : at + 512]
        cells = np.repeat(np.arange(len(part)), sizes[part])
        rows = owner[np.repeat(starts[part] - (np.cumsum(sizes[part]) - sizes[part]), sizes[part]) + np.arange(int(sizes[part].sum()))]
        matrix = np.zeros((len(a) + len(b), len(part)), np.float32)
        matrix[rows, cells] = 1
        out += matrix[: len(a)] @ matrix[len(a) :].T
    # owners are sorted inside an n-gram, those of a first
    sparse = np.flatnonzero((work > 0) & (work <= max(64, len(a) * len(b) // 64)))
    for at in range(0, len(sparse), 4096):
        part = sparse[at : at + 4096]
        n_a, n_b, lo = in_a[part], (sizes - in_a)[part], starts[part]
        pairs = n_a * n_b
        which = np.repeat(np.arange(len(part)), pairs)
        nth = np.arange(int(pairs.sum())) - np.repeat(np.cumsum(pairs) - pairs, pairs)
        left = owner[lo[which] + nth // n_b[which]]
        right = owner[lo[which] + n_a[which] + nth % n_b[which]] - len(a)
        cell, n = np.unique(left * len(b) + right, return_counts=True)
        out.reshape(-1)[cell] += n
    return out


def _verify(threshold: float, tolerance: float, bands: int, rows: int):
    """Rows (component, first block, second block, own block, node, n-grams) sorted by group to (node, links, root) per node and group."""

    def group(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
        nodes = np.concatenate([p.column(4).to_numpy() for p in parts])
        own = np.concatenate([p.column(3).to_numpy() for p in parts])
        raw = [x for p in parts for x in p.column(5).to_pylist()]
        nodes, first = np.unique(nodes, return_index=True)
        own, sets = own[first], [np.frombuffer(raw[k], np.uint64) for k in first.tolist()]
        sig = signatures(np.concatenate(sets), np.array([len(s) for s in sets]), bands * rows).astype("<u2")
        one_block = own.min() == own.max()
        split = own == own.min()
        a = np.flatnonzero(split)
        b = a if one_block else np.flatnonzero(~split)
        linked = np.zeros((len(a), len(b)), bool)
        for at in range(0, len(a), 256):
            alive = _alive(sig[a[at : at + 256]], sig[b], threshold, tolerance)
            if one_block:
                alive &= a[at : at + 256, None] < b[None, :]
            linked[at : at + 256] = alive
        if (pairs := np.argwhere(linked)).shape[0] <= 2048:
            for i, j in pairs.tolist():
                x, y = sets[a[i]], sets[b[j]]
                common = len(x) + len(y) - len(np.union1d(x, y))
                linked[i, j] = common >= threshold * (len(x) + len(y) - common) - 1e-9
        else:
            length = np.array([len(s) for s in sets], np.float32)
            for at in range(0, len(a), 1024):
                rows_a = a[at : at + 1024]
                common = overlaps([sets[k] for k in rows_a.tolist()], [sets[k] for k in b.tolist()])
                linked[at : at + 1024] &= common >= threshold * (length[rows_a][:, None] + length[b][None, :] - common) - 1e-3
        if one_block:
            linked |= linked.T
            count = linked.sum(axis=1)
            nodes, roots = _spanning(nodes, lambda i, left: linked[i, left])
        else:
            count = np.zeros(len(nodes), np.int64)
            count[a], count[b] = linked.sum(axis=1), linked.sum(axis=0)
            at_a, at_b = np.full(len(nodes), -1), np.full(len(nodes), -1)
            at_a[a], at_b[b] = np.arange(len(a)), np.arange(len(b))

            def near(i: int, left: np.ndarray) -> np.ndarray:
                if at_a[i] >= 0:
                    return (at_b[left] >= 0) & linked[at_a[i], at_b[left]]
                return (at_a[left] >= 0) & linked[at_a[left], at_b[i]]

            nodes, roots = _spanning(nodes, near)
        return pa.RecordBatch.from_pydict({"node": nodes, "links": count.astype(np.int64), "root": roots})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for parts in _grouped(batches, 3):
            if sum(p.num_rows for p in parts) > 1:
                held.append(group(parts))
                n += held[-1].num_rows
            if n >= 8192:
                yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
                held, n = [], 0
        if held:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]

    return run


def similarity_join(docs: DataFrame, threshold: float = THRESHOLD, n: int = N, bands: int = BANDS, rows: int = ROWS, tolerance: float = TOLERANCE, block: int = BLOCK) -> DataFrame:
    """One row per document: class_id (least doc_id of its class of linked and equal texts), text_id (least doc_id with the same text),
    n_copies (documents with the same text) and n_links (different texts at or above the threshold).
    """
    prints, known = _joined(docs, threshold, n, bands, rows, tolerance, block)
    return prints.select("doc_id", "text_key").join(known, "text_key").select("doc_id", "class_id", "text_id", "n_copies", "n_links")


def _one_of_each(docs: DataFrame) -> DataFrame:
    """text_id, text_key and text of all rows; of those with null id one a text."""
    source = id_and_text(docs).select(F.col("doc_id").alias("text_id"), F.unhex(F.md5(F.coalesce("text", F.lit("")).cast("binary"))).alias("text_key"), "text")
    unnamed = source.where("text_id IS NULL").groupBy("text_key").agg(F.first("text").alias("text"))
    return source.where("text_id IS NOT NULL").unionByName(unnamed.withColumn("text_id", F.lit(None).cast("long")))


def _joined(docs: DataFrame, threshold: float = THRESHOLD, n: int = N, bands: int = BANDS, rows: int = ROWS, tolerance: float = TOLERANCE, block: int = BLOCK) -> tuple[DataFrame, DataFrame]:
    """(fingerprints of the documents, one row per text with text_id, n_copies, class_id, n_links and the text_key that stands for its class)."""
    spark = docs.sparkSession
    ship_package(spark)
    prints = materialise(_fingerprints(docs, n, bands, rows), "fingerprints")
    texts = materialise(
        prints.groupBy("text_key")
        .agg(F.min("doc_id").alias("text_id"), F.count(F.lit(1)).alias("n_copies"), F.first("n_grams").alias("n_grams"), F.first("signature").alias("signature"), F.first("bands").alias("bands"))
        .withColumn("node", F.monotonically_increasing_id()),  # fixed from here on: this is a table
        "texts",
    )
    banded = texts.select("node", F.explode("bands").alias("key"))
    shared = materialise(banded.groupBy("key").agg(F.count(F.lit(1)).alias("size")).where("size > 1"), "buckets")
    members = banded.join(shared, "key").join(texts.select("node", "signature"), "node")
    blocks = _in_blocks(members, ["key"], "size", block).select("key", "first_block", "second_block", "node", "signature")
    width = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = blocks.repartition(width, "key", "first_block", "second_block").sortWithinPartitions("key", "first_block", "second_block")
    candidates = dealt.mapInArrow(_link_candidates(threshold, tolerance), "a long, b long")
    components = materialise(connected_components(candidates), "components")

    listed = components.join(texts.select("node", "text_id", "text_key", "n_grams"), "node")
    nodes = F.count(F.lit(1))
    pieces = F.least(nodes, F.greatest(F.ceil(nodes / block), F.ceil(F.sum("n_grams") / BLOCK_GRAMS)))
    sized = materialise(listed.groupBy("root").agg(pieces.cast("long").alias("pieces")), "component-sizes")
    placed = listed.join(sized, "root")
    source = _one_of_each(docs)
    same = placed["text_id"].eqNullSafe(source["text_id"]) & (placed["text_key"] == source["text_key"])
    found = placed.join(source, same).select("root", "pieces", "node", "text")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = 0
            for grams, counts in gram_hashes(batch.column(3), n):
                cuts = np.cumsum(counts)
                parts = [np.unique(grams[a:b]).tobytes() for a, b in zip((cuts - counts).tolist(), cuts.tolist())]
                yield pa.RecordBatch.from_arrays([batch.column(k).slice(at, len(counts)) for k in range(3)] + [pa.array(parts, pa.binary())], ["root", "pieces", "node", "grams"])
                at += len(counts)

    # the text join's output is materialised as n-gram sets of the documents in components, not of all
    grams = found.mapInArrow(sets, "root long, pieces long, node long, grams binary")
    cut = _in_blocks(grams, ["root"], "pieces", 1).select("root", "first_block", "second_block", F.col("_own").alias("own"), "node", "grams")
    dealt = cut.repartition(width, "root", "first_block", "second_block").sortWithinPartitions("root", "first_block", "second_block")
    verified = materialise(dealt.mapInArrow(_verify(threshold, tolerance, bands, rows), "node long, links long, root long"), "verified")
    links = verified.groupBy("node").agg(F.sum("links").alias("n_links"))
    classes = materialise(connected_components(verified.where("node <> root").select(F.col("node").alias("a"), F.col("root").alias("b"))), "classes")
    first = F.min(F.struct(F.col("text_id").isNull().alias("unnamed"), "text_id", "text_key")).alias("first")  # least id, none last
    named = materialise(
        classes.join(texts.select("node", "text_id", "text_key"), "node").groupBy("root").agg(first)
        .select("root", F.col("first.text_id").alias("class_id"), F.col("first.text_key").alias("class_key")),
        "class-names",
    )
    by_node = classes.join(named, "root").select("node", "class_id", "class_key")
    known = materialise(
        texts.select("text_key", "node", "text_id", "n_copies").join(by_node, "node", "left").join(links, "node", "left")
        .select(
            "text_key", "text_id", "n_copies", F.coalesce("class_id", "text_id").alias("class_id"),
            F.coalesce("class_key", "text_key").alias("class_key"), F.coalesce("n_links", F.lit(0)).alias("n_links"),
        ),
        "texts-joined",
    )
    return prints, known


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """The document with the least doc_id of each class (one with null doc_id only where none has an id), with all its columns; of repeated rows one stays."""
    _, known = _joined(docs, **options)
    kept = known.where("text_key = class_key").select(F.col("text_id").alias("_id"), F.col("text_key").alias("_key"))
    key = F.unhex(F.md5(F.coalesce("text", F.lit("")).cast("binary")))
    marked = docs.withColumn("_key", key)
    joined = marked.join(kept, marked["doc_id"].eqNullSafe(kept["_id"]) & (marked["_key"] == kept["_key"]), "left_semi")
    return joined.dropDuplicates(["doc_id", "_key"]).select(*docs.columns)
