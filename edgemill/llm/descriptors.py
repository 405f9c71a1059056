"""Edited and cropped copies of images by local descriptors.

A media column holds images as binary PGM (P5) bytes. Each distinct image gets corners at
several scales: every place whose corner response is the highest of the window around it
and above a threshold, so their number grows with the image and a crop keeps those of
its part. A corner has an orientation (intensity centroid) and 128 binary intensity tests
turned by it. Three runs of 42 bits of a descriptor are keys of hash tables. In a table
entry each row is matched with its nearest rows of two other images and with the two least
images within a few bits, so a row has four matches at most whatever the entry's
size, the pair of an image and its copy is found among strangers, and a group of any
number of copies meets at its least ones. Entries are cut into pairs of blocks; in
a large block rows with equal codes are compared once. What those four leave out is made
good: once the pairs found form classes, the corners of entries with images of several classes
are compared again, block by block of images, and all matches between images of different
classes count, whatever their number; they stay in the task that makes them. The classes are those that all matches of all pairs would give; n_agree is the most
of the pairs compared. The matches of two images must
agree on one similarity transform (rotation, scale, shift): each pair of matches
proposes one, and enough others must fit. Verified pairs form classes.

Null media match nothing but rows with the same id; broken bytes and images without corners
match only media with equal bytes. Repeated rows fall into one class. Rows with null
id are media like any other; class_id is null only where no medium of the class has an id.
Ids may be negative, images of any size. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import cache, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgemill.llm.common import discard, materialise, ship_package
from edgemill.llm.jaccard import _grouped, _in_blocks
from edgemill.operators.components import connected_components

RADIUS = 9
BITS = 128
BINS = 36  # orientations that the tests are turned to
SCALES = (1.0, 0.75, 0.5625)
REACH = 4  # a corner is the highest within so many pixels
TABLES, KEY_BITS = 3, 42
MOST_BITS = 16  # differing bits of a match
NEAR_BITS = 8  # differing bits of a match with a least image
LEAST_AGREE = 6
BLOCK = 4096
BLOCK_MARKS = 1 << 17  # corners in a block of the second pass
FIRST_BLOCKS = 2  # blocks that the second pass compares with the others at a time
PLACE = 8  # bytes
MARK = BITS // 8 + PLACE


def write_pgm(image: np.ndarray) -> bytes:
    h, w = image.shape
    return f"P5 {w} {h} 255\n".encode() + np.clip(np.rint(image), 0, 255).astype(np.uint8).tobytes()


def read_pgm(data: bytes | None) -> np.ndarray | None:
    """Grey values, or None for what is no 8-bit binary PGM."""
    try:
        head = data[:64].split(maxsplit=4)
        w, h, top = int(head[1]), int(head[2]), int(head[3])
        at = data.index(head[3], data.index(head[2], data.index(head[1], 2) + len(head[1])) + len(head[2])) + len(head[3]) + 1
        if head[0] != b"P5" or top > 255 or w < 1 or h < 1 or len(data) - at < w * h:
            return None
        return np.frombuffer(data, np.uint8, w * h, at).reshape(h, w).astype(np.float32)
    except (AttributeError, IndexError, TypeError, ValueError):
        return None


def resize(image: np.ndarray, h: int, w: int) -> np.ndarray:
    y, x = np.linspace(0, image.shape[0] - 1, h), np.linspace(0, image.shape[1] - 1, w)
    y0, x0 = np.minimum(y.astype(int), max(image.shape[0] - 2, 0)), np.minimum(x.astype(int), max(image.shape[1] - 2, 0))
    y1, x1 = np.minimum(y0 + 1, image.shape[0] - 1), np.minimum(x0 + 1, image.shape[1] - 1)
    fy, fx = (y - y0)[:, None].astype(np.float32), (x - x0)[None, :].astype(np.float32)
    rows = image[y0] * (1 - fy) + image[y1] * fy
    return rows[:, x0] * (1 - fx) + rows[:, x1] * fx


def _box(a: np.ndarray, r: int) -> np.ndarray:
    """Means over (2 r + 1) squares, edges padded."""
    k = 2 * r + 1
    c = np.cumsum(np.cumsum(np.pad(a, ((r + 1, r), (r + 1, r)), mode="edge"), axis=0, dtype=np.float64), axis=1)
    return ((c[k:, k:] - c[:-k, k:] - c[k:, :-k] + c[:-k, :-k]) / (k * k)).astype(np.float32)


@cache
def _tests() -> tuple[np.ndarray, np.ndarray]:
    """Rounded (y, x) of both points of each test, for each orientation bin."""
    rng = np.random.default_rng(128)
    points = np.clip(rng.normal(0, RADIUS / 2.2, (BITS, 2, 2)), -RADIUS * 0.7, RADIUS * 0.7)
    angle = np.arange(BINS) * 2 * np.pi / BINS
    y, x = points[None, :, :, 0], points[None, :, :, 1]
    c, s = np.cos(angle)[:, None, None], np.sin(angle)[:, None, None]
    return np.rint(y * c + x * s).astype(int), np.rint(x * c - y * s).astype(int)


@cache
def _disc() -> tuple[np.ndarray, np.ndarray]:
    y, x = np.mgrid[-RADIUS : RADIUS + 1, -RADIUS : RADIUS + 1]
    inside = y * y + x * x <= RADIUS * RADIUS
    return y[inside], x[inside]


def _highest(a: np.ndarray, reach: int) -> np.ndarray:
    """Maxima over (2 reach + 1) squares, one axis after the other."""
    for axis in (0, 1):
        pad = [(reach, reach) if k == axis else (0, 0) for k in (0, 1)]
        a = np.lib.stride_tricks.sliding_window_view(np.pad(a, pad, constant_values=-np.inf), 2 * reach + 1, axis=axis).max(axis=-1)
    return a


def describe(image: np.ndarray, reach: int = REACH) -> tuple[np.ndarray, np.ndarray]:
    """(corners x [x, y, scale, angle], corners x 16 descriptor bytes); places are in pixels of the image."""
    places, codes = [], []
    for scale in SCALES:
        h, w = int(round(image.shape[0] * scale)), int(round(image.shape[1] * scale))
        if min(h, w) < 2 * RADIUS + 3:
            break
        level = image if scale == 1.0 else resize(image, h, w)
        smooth = _box(level, 1)
        gy, gx = np.gradient(smooth)
        a, b, c = _box(gx * gx, 2), _box(gy * gy, 2), _box(gx * gy, 2)
        response = a * b - c * c - 0.05 * (a + b) ** 2
        margin = RADIUS + 1
        inner = response[margin:-margin, margin:-margin]
        peaks = np.argwhere((inner >= _highest(response, reach)[margin:-margin, margin:-margin]) & (inner > 1e-3)) + margin
        means, (dy, dx), (ty, tx) = _box(level, 2), _disc(), _tests()
        for at in range(0, len(peaks), 8192):
            y, x = peaks[at : at + 8192].T
            patch = smooth[y[:, None] + dy, x[:, None] + dx]
            angle = np.arctan2((patch * dy).sum(axis=1), (patch * dx).sum(axis=1))
            turn = np.rint(angle * BINS / (2 * np.pi)).astype(int) % BINS
            value = means[np.clip(y[:, None, None] + ty[turn], 0, h - 1), np.clip(x[:, None, None] + tx[turn], 0, w - 1)]
            codes.append(np.packbits(value[:, :, 0] < value[:, :, 1], axis=1))
            places.append(np.stack([x / scale, y / scale, np.full(len(x), scale), angle], axis=1))
    if not places:
        return np.zeros((0, 4)), np.zeros((0, BITS // 8), np.uint8)
    return np.concatenate(places), np.concatenate(codes)


def _described(media: DataFrame, reach: int) -> DataFrame:
    """(media_id, image_key, marks): the marks of each media end to end; one narrow pass, which remembers its last images.

    A mark is what later steps keep of a corner: 16 code bytes and its place as two 32-bit floats.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[bytes, bytes] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                keys, marks = [], []
                for media_id, data in zip(part.column(0).to_pylist(), part.column(1)):
                    data = data.as_py()
                    key = f"null {media_id}".encode() if data is None else hashlib.md5(data).digest()
                    if key not in seen:
                        image = read_pgm(data)
                        place, code = describe(image, reach) if image is not None else (np.zeros((0, 4)), np.zeros((0, BITS // 8), np.uint8))
                        if len(seen) >= 256:
                            seen.pop(next(iter(seen)))
                        spots = np.ascontiguousarray(place[:, :2], "<f4").view(np.uint8).reshape(len(code), PLACE)
                        seen[key] = np.concatenate([code, spots], axis=1).tobytes()
                    keys.append(key)
                    marks.append(seen[key])
                yield pa.RecordBatch.from_pydict({"media_id": part.column(0), "image_key": pa.array(keys, pa.binary()), "marks": pa.array(marks, pa.binary())})

    return media.mapInArrow(run, "media_id long, image_key binary, marks binary")


def _halves(marks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both 64-bit halves of the codes."""
    halves = np.ascontiguousarray(marks[:, : BITS // 8]).view(">u8").astype(np.uint64)
    return halves[:, 0], halves[:, 1]


def table_keys(high: np.ndarray, low: np.ndarray) -> np.ndarray:
    """Keys of each code in each table, the table's number in the lowest bits."""
    rest = BITS // 2 - KEY_BITS
    runs = high >> np.uint64(rest), (high & np.uint64((1 << rest) - 1)) << np.uint64(KEY_BITS - rest) | low >> np.uint64(BITS // 2 - KEY_BITS + rest), low >> np.uint64(2) & np.uint64((1 << KEY_BITS) - 1)
    return np.stack([r << np.uint64(2) | np.uint64(t) for t, r in enumerate(runs)], axis=1).astype(np.int64)


def _table_rows(images: DataFrame) -> DataFrame:
    """(key, node, corner): a row for each corner and hash table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 2048):
                part = batch.slice(at, 2048)
                raw = part.column(1).to_pylist()
                counts = np.array([len(m) // MARK for m in raw], np.int64)
                marks = np.frombuffer(b"".join(raw), np.uint8).reshape(-1, MARK)
                corner = np.arange(len(marks)) - np.repeat(np.cumsum(counts) - counts, counts)
                columns = table_keys(*_halves(marks)).reshape(-1), np.repeat(part.column(0).to_numpy(), counts * TABLES), np.repeat(corner, TABLES).astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["key", "node", "corner"])

    return images.mapInArrow(run, "key long, node long, corner int")


def _bits_between(high: np.ndarray, low: np.ndarray, rows: slice) -> np.ndarray:
    return np.bitwise_count(high[rows, None] ^ high) + np.bitwise_count(low[rows, None] ^ low)


def partners(node: np.ndarray, high: np.ndarray, low: np.ndarray, most_bits: int, near_bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, partner row) for rows in order of node: the nearest rows of two other images and the two least other images within near_bits; ties to the least image."""
    ones, others = [], []
    step = max(1, (1 << 20) // len(node))
    for at in range(0, len(node), step):
        mine = slice(at, at + step)
        bits = _bits_between(high, low, mine)
        bits[node[mine, None] == node] = 255
        index = np.arange(at, at + len(bits))
        near = np.where(bits <= near_bits, bits, 255)
        for table, limit, first in ((bits, most_bits, True), (near, near_bits, False)):
            for _ in range(2):
                best = table.argmin(axis=1) if first else (table < 255).argmax(axis=1)
                found = table[index - at, best] <= limit
                if not found.any():
                    break
                ones.append(index[found])
                others.append(best[found])
                table = np.where(node[best][:, None] == node, 255, table)
    if not ones:
        return np.zeros(0, int), np.zeros(0, int)
    return np.concatenate(ones), np.concatenate(others)


def _entry_matches(node: np.ndarray, high: np.ndarray, low: np.ndarray, most_bits: int, near_bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of matching rows of an entry, in order of node. Rows of a large one with equal codes are compared through the first of them."""
    if len(node) <= 256:
        return partners(node, high, low, most_bits, near_bits)
    order = np.lexsort((low, high))  # stable: rows with equal codes stay in order of node
    change = np.concatenate([[True], (high[order][1:] != high[order][:-1]) | (low[order][1:] != low[order][:-1])])
    code = np.empty(len(node), int)
    code[order] = np.cumsum(change) - 1
    firsts = order[change]
    by_node = np.argsort(firsts)
    firsts = firsts[by_node]
    rank = np.empty(len(firsts), int)
    rank[by_node] = np.arange(len(firsts))
    code = rank[code]
    one, other = partners(node[firsts], high[firsts], low[firsts], most_bits, near_bits)
    # every row takes the partners of its code, the first row with the code, and the one before it
    sort = np.argsort(one, kind="stable")
    one, other = one[sort], other[sort]
    times = np.searchsorted(one, code, "right") - (lo := np.searchsorted(one, code, "left"))
    row = np.repeat(np.arange(len(node)), times)
    nth = np.arange(len(row)) - np.repeat(np.cumsum(times) - times, times)
    before = np.arange(len(node))
    before[order[1:]] = np.where(change[1:], order[1:], order[:-1])
    rows = np.concatenate([row, np.arange(len(node)), np.arange(len(node))])
    found = np.concatenate([firsts[other[lo[row] + nth]], firsts[code], before])
    keep = node[rows] != node[found]
    return rows[keep], found[keep]


def _whole_groups(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.RecordBatch]:
    """The rows again, in batches that end where a group (equal first `keys` columns, sorted) ends."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [batch.column(k).to_numpy() for k in range(keys)]
        new = np.flatnonzero(np.any([c[1:] != c[:-1] for c in columns], axis=0)) + 1
        first = tuple(c[0] for c in columns)
        starts = [0, *new.tolist()] if last is not None and first != last else new.tolist()
        last = tuple(c[-1] for c in columns)
        if starts:
            if held or starts[-1]:
                yield pa.Table.from_batches([*held, batch.slice(0, starts[-1])]).combine_chunks().to_batches()[0]
            held = []
            batch = batch.slice(starts[-1])
        held.append(batch)
    if held:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def _match(most_bits: int, near_bits: int):
    """Rows (key, first block, second block, node, mark) sorted by group and node to (a, b, place_a, place_b)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _whole_groups(batches, 3):
            keys = [batch.column(k).to_numpy() for k in range(3)]
            node = batch.column(3).to_numpy()
            marks = np.frombuffer(b"".join(batch.column(4).to_pylist()), np.uint8).reshape(-1, MARK)
            high, low = _halves(marks)
            starts = np.flatnonzero(np.concatenate([[True], np.any([k[1:] != k[:-1] for k in keys], axis=0)]))
            sizes = np.diff(np.append(starts, len(node)))
            two = starts[sizes == 2]
            bits = np.bitwise_count(high[two] ^ high[two + 1]) + np.bitwise_count(low[two] ^ low[two + 1])
            two = two[(bits <= most_bits) & (node[two] != node[two + 1])]
            ones, others = [two], [two + 1]
            for lo, n in zip(starts[sizes > 2].tolist(), sizes[sizes > 2].tolist()):
                part = slice(lo, lo + n)
                a, b = _entry_matches(node[part], high[part], low[part], most_bits, near_bits)
                ones.append(a + lo)
                others.append(b + lo)
            one, other = np.concatenate(ones), np.concatenate(others)
            swap = node[one] > node[other]
            one, other = np.where(swap, other, one), np.where(swap, one, other)
            pair = np.unique(one * len(node) + other)
            one, other = pair // len(node), pair % len(node)
            place = np.ascontiguousarray(marks[:, BITS // 8 :]).view("<i8").reshape(-1)
            if len(one):
                yield pa.RecordBatch.from_pydict({"a": node[one], "b": node[other], "place_a": place[one], "place_b": place[other]})

    return run


def _match_rest(most_bits: int):
    """Rows (key, first block, second block, own block, node, class, mark) sorted by group to (a, b, place_a, place_b): every match between images of different classes.

    The plain form of the second pass, a row a match; the query goes by _pairs_between, which keeps the matches in the task.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _whole_groups(batches, 3):
            key, first, second, own, node, root = (batch.column(k).to_numpy() for k in range(6))
            marks = np.frombuffer(b"".join(batch.column(6).to_pylist()), np.uint8).reshape(-1, MARK)
            high, low = _halves(marks)
            place = np.ascontiguousarray(marks[:, BITS // 8 :]).view("<i8").reshape(-1)

            def found(one: np.ndarray, other: np.ndarray) -> pa.RecordBatch:
                swap = node[one] > node[other]
                one, other = np.where(swap, other, one), np.where(swap, one, other)
                return pa.RecordBatch.from_pydict({"a": node[one], "b": node[other], "place_a": place[one], "place_b": place[other]})

            starts = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (first[1:] != first[:-1]) | (second[1:] != second[:-1])]))
            sizes = np.diff(np.append(starts, len(node)))
            two = starts[sizes == 2]
            bits = np.bitwise_count(high[two] ^ high[two + 1]) + np.bitwise_count(low[two] ^ low[two + 1])
            # pairs inside a block of a cut entry are those of the group of this block with itself
            apart = (first[two] == second[two]) | (own[two] != own[two + 1])
            two = two[(bits <= most_bits) & (root[two] != root[two + 1]) & apart]
            ones, others, n = [two], [two + 1], len(two)
            for lo, size in zip(starts[sizes > 2].tolist(), sizes[sizes > 2].tolist()):
                rows = np.arange(lo, lo + size)
                whole = first[lo] == second[lo]
                a = rows if whole else rows[own[rows] == first[lo]]
                b = rows if whole else rows[own[rows] == second[lo]]
                if not len(a) or not len(b):
                    continue
                step = max(1, (1 << 20) // len(b))
                for at in range(0, len(a), step):
                    mine = a[at : at + step]
                    hit = (np.bitwise_count(high[mine, None] ^ high[b]) + np.bitwise_count(low[mine, None] ^ low[b]) <= most_bits) & (root[mine, None] != root[b])
                    if whole:
                        hit &= mine[:, None] < b
                    i, j = np.nonzero(hit)
                    ones.append(mine[i])
                    others.append(b[j])
                    n += len(i)
                    if n >= 1 << 18:
                        yield found(np.concatenate(ones), np.concatenate(others))
                        ones, others, n = [], [], 0
            if n:
                yield found(np.concatenate(ones), np.concatenate(others))

    return run


def agreeing(a: np.ndarray, b: np.ndarray, within: float = 3.0) -> int:
    """The most corners that one similarity transform takes from places a to places b; every pair of matches proposes one.

    Matches of one corner (at several scales) count once: places of a within a cell of `within` pixels.
    """
    i, j = np.triu_indices(len(a), 1)
    za, zb = a[:, 0] + 1j * a[:, 1], b[:, 0] + 1j * b[:, 1]
    span = za[j] - za[i]
    fine = np.abs(span) > 4
    if not fine.any():
        return 0
    turn = (zb[j] - zb[i])[fine] / span[fine]
    sized = (np.abs(turn) > 0.4) & (np.abs(turn) < 2.5)
    if not sized.any():
        return 0
    turn, shift = turn[sized], (zb[i][fine] - turn * za[i][fine])[sized]
    _, cell = np.unique(np.floor(a / (within + 1)), axis=0, return_inverse=True)
    corner = (cell.reshape(-1)[:, None] == np.arange(cell.max() + 1)).astype(np.float32)
    fits = (np.abs(turn[:, None] * za + shift[:, None] - zb) <= within).astype(np.float32)
    return int((fits @ corner > 0).sum(axis=1).max())


def _consensus(least: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = []
            for matches in batch.column(2).to_pylist():
                places = np.array([(m["place_a"], m["place_b"]) for m in matches], "<i8").view("<f4").astype(float)
                good.append(agreeing(places[:, :2], places[:, 2:]))
            good = np.array(good, np.int64)
            keep = pa.array(good >= least)
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(keep), batch.column(1).filter(keep), pa.array(good[good >= least])], ["a", "b", "agree"])

    return run


def _numbered(images: DataFrame) -> DataFrame:
    """images with a number `node` of their own: a hash of the key, taken with another salt until no two images share one."""
    for salt in range(16):
        marked = materialise(images.withColumn("node", F.xxhash64("image_key", F.lit(salt))), "images")
        if marked.groupBy("node").agg(F.count(F.lit(1)).alias("n")).where("n > 1").isEmpty():
            return marked
    raise RuntimeError("no salt gives every image its own number")


def _only_corners(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (node, class, marks, corners) to (node, class, marks of these corners)."""
    for batch in batches:
        kept = [np.frombuffer(m, np.uint8).reshape(-1, MARK)[np.sort(c)].tobytes() for m, c in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist())]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(kept, pa.binary())], ["node", "root", "marks"])


def may_agree(a: np.ndarray, b: np.ndarray, starts: np.ndarray, sizes: np.ndarray, least: int, within: float = 3.0) -> np.ndarray:
    """Which runs of matches (complex places a and b) have a proposed transform that `least` of them fit; the others cannot agree."""
    out = np.ones(len(starts), bool)
    for k in np.unique(sizes[sizes <= 32]).tolist():
        i, j = np.triu_indices(k, 1)
        runs = np.flatnonzero(sizes == k)
        step = max(1, (1 << 20) // (len(i) * k))
        for at in range(0, len(runs), step):
            rows = starts[runs[at : at + step], None] + np.arange(k)
            za, zb = a[rows], b[rows]
            with np.errstate(divide="ignore", invalid="ignore"):
                turn = (zb[:, j] - zb[:, i]) / (za[:, j] - za[:, i])
                off = np.abs(turn[:, :, None] * za[:, None, :] + (zb[:, i] - turn * za[:, i])[:, :, None] - zb[:, None, :])
            out[runs[at : at + step]] = ((off <= within + 1e-6).sum(axis=2) >= least).any(axis=1)
    return out


def _pairs_between(most_bits: int, least: int):
    """Rows (first block, second block, own block, node, class, marks) sorted by blocks and node to (a, b, agree): the verified pairs of images of different classes.

    All matches of some images of the first block with the second are made at a time; none leaves the task.
    """

    def pairs(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        first, second = batch.column(0)[0].as_py(), batch.column(1)[0].as_py()
        own, node, root = (batch.column(k).to_numpy() for k in (2, 3, 4))
        raw = batch.column(5).to_pylist()
        image = np.repeat(np.arange(len(raw)), [len(m) // MARK for m in raw])
        marks = np.frombuffer(b"".join(raw), np.uint8).reshape(-1, MARK)
        high, low = _halves(marks)
        keys = table_keys(high, low)
        spots = np.ascontiguousarray(marks[:, BITS // 8 :]).view("<f4").astype(float)
        place = spots[:, 0] + 1j * spots[:, 1]
        rows, others = (np.flatnonzero(own[image] == block) for block in (first, second))
        if not len(rows) or not len(others):
            return
        order = [others[np.argsort(keys[others, t], kind="stable")] for t in range(TABLES)]
        lo = np.stack([np.searchsorted(keys[order[t], t], keys[rows, t]) for t in range(TABLES)])
        many = np.stack([np.searchsorted(keys[order[t], t], keys[rows, t], "right") for t in range(TABLES)]) - lo
        heads = np.flatnonzero(np.concatenate([[True], image[rows][1:] != image[rows][:-1]]))
        met = np.cumsum(many.sum(axis=0))
        at = 0
        while at < len(rows):
            # whole images, as many as meet so many rows; one at least
            end = np.searchsorted(met, (met[at - 1] if at else 0) + (1 << 20), "right")
            later = heads[heads > at]
            inside = later[later <= end]
            end = len(rows) if end >= len(rows) else int(inside[-1]) if len(inside) else int(later[0]) if len(later) else len(rows)
            found = []
            for t in range(TABLES):
                for lower in range(at, end, step := 4096):
                    part = slice(lower, min(lower + step, end))
                    times = many[t, part]
                    one = np.repeat(rows[part], times)
                    other = order[t][np.repeat(lo[t, part] - (np.cumsum(times) - times), times) + np.arange(len(one))]
                    hit = (np.bitwise_count(high[one] ^ high[other]) + np.bitwise_count(low[one] ^ low[other]) <= most_bits) & (root[image[one]] != root[image[other]])
                    for before in range(t):  # corners that meet in several tables count once
                        hit &= keys[one, before] != keys[other, before]
                    if first == second:
                        hit &= image[one] < image[other]
                    found.append((one[hit], other[hit]))
            at = end
            one, other = (np.concatenate(x) for x in zip(*found))
            swap = image[one] > image[other]  # images are in order of node
            one, other = np.where(swap, other, one), np.where(swap, one, other)
            pair = image[one] * len(raw) + image[other]
            sort = np.argsort(pair, kind="stable")
            one, other, pair = one[sort], other[sort], pair[sort]
            starts = np.flatnonzero(np.concatenate([[True], pair[1:] != pair[:-1]])) if len(pair) else np.zeros(0, int)
            sizes = np.diff(np.append(starts, len(pair)))
            starts, sizes = starts[sizes >= least], sizes[sizes >= least]
            likely = may_agree(place[one], place[other], starts, sizes, least)
            out = []
            for start, n in zip(starts[likely].tolist(), sizes[likely].tolist()):
                good = agreeing(spots[one[start : start + n]], spots[other[start : start + n]])
                if good >= least:
                    out.append((node[image[one[start]]], node[image[other[start]]], good))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.array(x, np.int64)) for x in zip(*out)], ["a", "b", "agree"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for parts in _grouped(batches, 2):
            yield from pairs(pa.Table.from_batches(parts).combine_chunks().to_batches()[0])

    return run


def _rest(images: DataFrame, verified: DataFrame, most_bits: int, least: int, block_marks: int = BLOCK_MARKS) -> DataFrame:
    """(a, b, agree): the verified pairs among images that `verified` leaves in different classes, by all their matches in all tables.

    Corners that meet none of another class stay out. The images are cut into hash blocks of so
    many corners, a task compares two blocks with arrays, a few first blocks are on their way at a time.
    """
    classes = connected_components(verified.select("a", "b"))
    marked = images.where(F.length("marks") > 0).select("node", "marks").join(classes, "node", "left")
    marked = materialise(marked.select("node", F.coalesce("root", "node").alias("root"), "marks"), "classed-images")
    spread = _table_rows(marked.select(F.col("root").alias("node"), "marks")).groupBy("key").agg(F.min("node").alias("lo"), F.max("node").alias("hi"))
    mixed = materialise(spread.where("lo <> hi").select("key"), "mixed-keys")
    corners = _table_rows(marked.select("node", "marks")).join(mixed, "key").groupBy("node").agg(F.collect_set("corner").alias("corners"))
    crowded = materialise(marked.join(corners, "node").select("node", "root", "marks", "corners").mapInArrow(_only_corners, "node long, root long, marks binary"), "mixed-marks")
    discard(mixed, marked)
    size = crowded.agg(F.sum(F.length("marks").cast("long"))).first()[0] or 0
    pieces = max(1, -(-size // (MARK * block_marks)))
    owned = crowded.withColumn("own", F.pmod(F.xxhash64("node"), F.lit(pieces)).cast("int"))
    found = []
    for at in range(0, pieces, FIRST_BLOCKS):
        last = min(at + FIRST_BLOCKS, pieces) - 1
        other = F.explode(F.expr(f"filter(sequence(0, {pieces - 1}), o -> least(o, own) between {at} and {last})"))
        cut = owned.withColumn("_other", other).select(F.least("own", "_other").alias("first_block"), F.greatest("own", "_other").alias("second_block"), "own", "node", "root", "marks")
        place = ((F.col("first_block") - at) * pieces + F.col("second_block")).cast("int")
        dealt = cut.repartitionById((last - at + 1) * pieces, place).sortWithinPartitions("first_block", "second_block", "node")
        found.append(materialise(dealt.mapInArrow(_pairs_between(most_bits, least), "a long, b long, agree long"), "rest-pairs"))
    discard(crowded)
    return reduce(DataFrame.unionByName, found)


def find_copies(
    media: DataFrame, id_col: str = "media_id", media_col: str = "media", reach: int = REACH, most_bits: int = MOST_BITS, near_bits: int = NEAR_BITS, least: int = LEAST_AGREE, block: int = BLOCK
) -> DataFrame:
    """media_id, class_id (least id of the class), n_equal (media with equal bytes), n_agree (most agreeing matches with another image)."""
    spark = media.sparkSession
    ship_package(spark)
    rows = media.select(F.col(id_col).cast("long").alias("media_id"), F.col(media_col).alias("media"))
    described = materialise(_described(rows, reach), "descriptors")
    listed = materialise(described.select("media_id", "image_key"), "media-keys")
    # equal bytes have equal marks, so any of them serves
    grouped = described.groupBy("image_key").agg(F.min("media_id").alias("least_id"), F.count(F.lit(1)).alias("n_equal"), F.first("marks").alias("marks"))
    images = _numbered(grouped)
    discard(described)
    entries = _table_rows(images.where(F.length("marks") > 0).select("node", "marks"))
    # most keys have a single row: they go before any descriptor is shuffled
    shared = materialise(entries.groupBy("key").agg(F.count(F.lit(1)).alias("size")).where("size > 1"), "shared-keys")
    kept = materialise(entries.join(shared, "key"), "shared-rows")
    mark = F.expr(f"substring(marks, corner * {MARK} + 1, {MARK})")
    placed = kept.join(images.select("node", "marks"), "node").select("key", "size", "node", mark.alias("mark"))
    cut = _in_blocks(placed, ["key"], "size", block).select("key", "first_block", "second_block", "node", "mark")
    width = int(spark.conf.get("spark.sql.shuffle.partitions"))
    tables = []
    # one table after another: the rows of one only are on their way at a time
    for table in range(TABLES):
        own = cut.where(F.col("key").bitwiseAND(3) == table)
        dealt = own.repartition(width, "key", "first_block", "second_block").sortWithinPartitions("key", "first_block", "second_block", "node")
        tables.append(materialise(dealt.mapInArrow(_match(most_bits, near_bits), "a long, b long, place_a long, place_b long"), "matches"))
    discard(shared, kept)
    matches = reduce(DataFrame.unionByName, tables)
    # corners that meet in several tables count once
    pairs = matches.groupBy("a", "b").agg(F.collect_set(F.struct("place_a", "place_b")).alias("matches")).where(F.size("matches") >= least)
    verified = materialise(pairs.mapInArrow(_consensus(least), "a long, b long, agree long"), "verified-pairs")
    discard(*tables)
    verified = verified.unionByName(_rest(images, verified, most_bits, least))
    ends = verified.select(F.col("a").alias("node"), "agree").unionByName(verified.select(F.col("b").alias("node"), "agree"))
    best = ends.groupBy("node").agg(F.max("agree").alias("n_agree"))
    rooted = connected_components(verified.select("a", "b")).join(images.select("node", "least_id"), "node")
    rooted = materialise(rooted, "rooted")
    named = rooted.groupBy("root").agg(F.min("least_id").alias("class_id"))
    classes = rooted.join(named, "root").select("node", "class_id")
    known = materialise(
        images.drop("marks").join(classes, "node", "left").join(best, "node", "left")
        .select("image_key", "n_equal", F.coalesce("class_id", "least_id").alias("class_id"), F.coalesce("n_agree", F.lit(0)).alias("n_agree")),
        "images-joined",
    )
    return listed.join(known, "image_key").select("media_id", "class_id", "n_equal", "n_agree")


def picture(vector: list[float] | None, size: int = 80) -> np.ndarray:
    """A texture that a vector decides: its components on an 8 x 8 grid with finer detail drawn from their hash."""
    import zlib

    values = np.array([x if x is not None and np.isfinite(x) else 0.0 for x in vector or []], np.float32)
    rng = np.random.default_rng(zlib.crc32(values.tobytes()))
    coarse = np.resize(values, (8, 8)) if len(values) else np.zeros((8, 8), np.float32)
    image = resize((coarse / (np.abs(coarse).max() + 1e-6)).astype(np.float32), size, size) * 40
    for cells, weight in ((12, 60), (24, 45)):
        image = image + resize(rng.uniform(-1, 1, (cells, cells)).astype(np.float32), size, size) * weight
    return np.clip(image + 128, 0, 255)


def edited(image: np.ndarray, seed: int) -> np.ndarray:
    """A crop of up to an eighth on each side, with other contrast and brightness and some noise."""
    rng = np.random.default_rng(seed)
    h, w = image.shape
    top, left, bottom, right = (int(rng.integers(0, n // 8 + 1)) for n in (h, w, h, w))
    part = image[top : h - bottom, left : w - right]
    return np.clip((part - 128) * rng.uniform(0.8, 1.15) + 128 + rng.uniform(-15, 15) + rng.normal(0, 2.0, part.shape), 0, 255)


def media_of_embeddings(embeddings: DataFrame) -> DataFrame:
    """Two media a row, as no given table has images: 2 * vec_id shows the vector, 2 * vec_id + 1 an edited crop of that. A null vec_id gives two null ids."""
    ship_package(embeddings.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                ids, data = [], []
                for i, v in zip(batch.column(0).slice(at, 512).to_pylist(), batch.column(1).slice(at, 512).to_pylist()):
                    shown = picture(v)
                    ids += [None, None] if i is None else [2 * i, 2 * i + 1]
                    data += [write_pgm(shown), write_pgm(edited(shown, (i or 0) % (1 << 64)))]
                yield pa.RecordBatch.from_pydict({"media_id": pa.array(ids, pa.int64()), "media": pa.array(data, pa.binary())})

    return embeddings.select("vec_id", "embedding").mapInArrow(run, "media_id long, media binary")
