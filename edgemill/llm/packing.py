"""Best-fit packing of token sequences with swap-based local search.

A document is its ids and an end id. Longer ones are cut at the capacity; full
pieces are sequences of their own. How the rest is packed depends only on how many
pieces each length has, at most `capacity` numbers whatever the corpus, so the
driver packs this histogram: best-fit decreasing over groups of equal bins, then
local search over underfull bins. A step moves one piece, exchanges one for one, two for
one or one for two, from the emptier to the fuller bin, and so increases the sum of
squared fills, until bins are empty or nothing moves. Pieces of a length
then take their places by rank.

Null and empty texts are a piece of one token (the end id). Repeated rows and ids
are packed as they come, rows with null doc_id too (first in the order of equal lengths). An empty table
gives no rows; other columns are ignored.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgemill.functions.ranking import rank_within
from edgemill.llm.common import id_and_text, materialise, ship_package
from edgemill.llm.wordtokens import end_every, word_encoder

PIECE_SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long"
PLACED_SCHEMA = PIECE_SCHEMA + ", sequence_id long, offset long"

Bins = dict[tuple[int, ...], int]  # lengths in a bin, falling -> number of such bins


def best_fit_decreasing(histogram: dict[int, int], capacity: int) -> Bins:
    """Best-fit decreasing with all pieces of a length at once.

    A bin that takes a piece is the tightest fit for the next equal one as long
    as it has room, so bins of one kind are filled one after another: whole
    multiples together, the last one in part.
    """
    room: list[int] = []  # rooms left in some bin, rising
    kinds: dict[int, Counter] = defaultdict(Counter)
    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        touched: list[tuple[int, tuple[int, ...], int]] = []
        at = bisect_left(room, length)
        while left and at < len(room):
            space = room[at]
            each = space // length
            for kind in list(kinds[space]):
                if not left:
                    break
                n = min(kinds[space][kind], left // each)
                rest = left - n * each if n < kinds[space][kind] else 0
                if n:
                    touched.append((space - each * length, kind + (length,) * each, n))
                if 0 < rest < each:
                    touched.append((space - rest * length, kind + (length,) * rest, 1))
                    n, left = n + 1, left - rest
                    left -= (n - 1) * each
                else:
                    left -= n * each
                kinds[space][kind] -= n
                if not kinds[space][kind]:
                    del kinds[space][kind]
            if not kinds[space]:
                del kinds[space]
                room.pop(at)
            else:
                at += 1
        if left:
            each = capacity // length
            full, rest = divmod(left, each)
            if full:
                touched.append((capacity - each * length, (length,) * each, full))
            if rest:
                touched.append((capacity - rest * length, (length,) * rest, 1))
        for space, kind, n in touched:
            if space not in kinds:
                insort(room, space)
            kinds[space][kind] += n
    out: Counter = Counter()
    for group in kinds.values():
        out.update(group)
    return dict(out)


def _best_exchange(low: tuple[int, ...], high: tuple[int, ...], space: int) -> tuple[int, tuple[int, ...], tuple[int, ...]]:
    """The exchange that moves most tokens, `space` at most, from bin `low` to bin `high`: (tokens, out of low, out of high)."""
    best = (0, (), ())
    a, b = sorted(set(low)), sorted(set(high))
    many_a, many_b = Counter(low), Counter(high)
    pairs_a = [(x + y, (x, y)) for i, x in enumerate(a) for y in a[i:] if x != y or many_a[x] > 1]
    pairs_b = [(x + y, (x, y)) for i, x in enumerate(b) for y in b[i:] if x != y or many_b[x] > 1]
    for x in a:
        if best[0] < x <= space:
            best = (x, (x,), ())
    sums_b = sorted([(x, (x,)) for x in b] + pairs_b)
    values = [v for v, _ in sums_b]
    for total, out in [(x, (x,)) for x in a]:
        k = bisect_left(values, total - space)
        if k < len(values) and best[0] < total - values[k] <= space:
            best = (total - values[k], out, sums_b[k][1])
    for total, out in pairs_a:
        k = bisect_left(b, total - space)
        if k < len(b) and best[0] < total - b[k] <= space:
            best = (total - b[k], out, (b[k],))
        if best[0] < total <= space:
            best = (total, out, ())
    return best


def _without(kind: tuple[int, ...], out: tuple[int, ...], put: tuple[int, ...]) -> tuple[int, ...]:
    left = Counter(kind)
    left.subtract(out)
    left.update(put)
    return tuple(sorted(left.elements(), reverse=True))


def improve(bins: Bins, capacity: int) -> Bins:
    """Empty the emptiest bins into the room of the others.

    Every exchange goes from an emptier to a fuller bin (the emptiest first) and is
    made in as many bins as both kinds have, so the sum of squared fills rises with
    each and the search ends: when the bins are as few as all tokens need, or
    nothing moves. A pair of kinds that has no exchange is not looked at again.
    """
    bins = Counter({k: n for k, n in bins.items() if n})
    tokens = sum(sum(k) * n for k, n in bins.items())
    least, total = -(-tokens // capacity), sum(bins.values())
    settled: set[tuple[int, ...]] = set()  # kinds without an exchange among each other
    moved = True
    while moved and total > least:
        moved, gone = False, set()
        under = sorted((k for k in bins if sum(k) < capacity), key=lambda k: (sum(k), k))
        fresh = [(i, k) for i, k in enumerate(under) if k not in settled]
        for i, low in enumerate(under):
            if low in settled:
                partners = [k for j, k in reversed(fresh) if j > i] + [low]
            else:
                partners = under[: i - 1 if i else None : -1]
            for high in partners:
                if not bins[low] or total <= least:
                    break
                n = bins[low] // 2 if high == low else min(bins[low], bins[high])
                if not n:
                    continue
                got, out, back = _best_exchange(low, high, capacity - sum(high))
                if not got:
                    continue
                bins.subtract({low: 2 * n} if high == low else {low: n, high: n})
                bins[_without(high, back, out)] += n
                if rest := _without(low, out, back):
                    bins[rest] += n
                else:
                    total -= n
                for kind in {low, high}:
                    if not bins[kind]:
                        del bins[kind]
                        gone.add(kind)
                moved = True
        settled = set(under) - gone
    return dict(bins)


def cut_pieces(docs: DataFrame, tokenizer: str, end_id: int = 0, capacity: int = 2048, with_ids: bool = False) -> DataFrame:
    """Pieces of every document; with_ids adds the ids themselves."""
    ship_package(docs.sparkSession)
    schema = PIECE_SCHEMA + (", ids array<int>" if with_ids else "")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = word_encoder(tokenizer)
        for batch in batches:
            at = 0
            for ids, counts in encoder.encode(batch.column(1)):
                ids, counts = end_every(ids, counts, end_id)
                doc_ids = batch.column(0).slice(at, len(counts))
                at += len(counts)
                pieces = -(-counts // capacity)
                owner = np.repeat(np.arange(len(counts)), pieces)
                number = np.arange(len(owner)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
                start = number * capacity
                length = np.minimum(counts[owner] - start, capacity)
                lo = (np.cumsum(counts) - counts)[owner] + start
                raw = memoryview(ids.tobytes())
                crc = np.fromiter((zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(lo.tolist(), (lo + length).tolist())), np.int64, len(lo))
                out = {"doc_id": doc_ids.take(pa.array(owner)), "piece": number.astype(np.int32), "start": start, "length": length, "ids_crc32": crc}
                if with_ids:
                    out["ids"] = pa.ListArray.from_arrays(pa.array(np.append(lo, len(ids)).astype(np.int32)), pa.array(ids.astype(np.int32)))
                yield pa.RecordBatch.from_pydict(out)

    return id_and_text(docs).mapInArrow(cut, schema)


def places(bins: Bins, capacity: int) -> tuple[np.ndarray, ...]:
    """Where the pieces of each length go, by rank: sorted keys (length << 40 | first rank), first sequence, offset, equal pieces a bin."""
    rows, ranks, sequence = [], Counter(), 0
    for kind, n in sorted(bins.items(), reverse=True):
        offset = 0
        for length, times in sorted(Counter(kind).items(), reverse=True):
            rows.append(((length << 40) | ranks[length], sequence, offset, times))
            ranks[length] += n * times
            offset += length * times
        sequence += n
    table = np.array(sorted(rows), np.int64).reshape(-1, 4)
    return tuple(table.T.copy())


def pack_pieces(pieces: DataFrame, capacity: int = 2048) -> DataFrame:
    """Add sequence_id and offset to pieces (columns doc_id, piece, start, length, ids_crc32)."""
    spark = pieces.sparkSession
    ship_package(spark)
    kept = materialise(pieces.select("doc_id", "piece", "start", "length", "ids_crc32"), "pieces")
    histogram = {r.length: r.n for r in kept.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    full = histogram.pop(capacity, 0)
    bins = improve(best_fit_decreasing(histogram, capacity), capacity)
    if full:
        bins[(capacity,)] = full
    shared = spark.sparkContext.broadcast(places(bins, capacity))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, sequence, offset, times = shared.value
        for batch in batches:
            length, rank = batch.column(3).to_numpy(), batch.column(5).to_numpy()
            key = (length << 40) | rank
            row = np.searchsorted(keys, key, "right") - 1
            nth = key - keys[row]
            columns = batch.columns[:5] + [pa.array(sequence[row] + nth // times[row]), pa.array(offset[row] + nth % times[row] * length)]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    ranked = rank_within(kept, ["length"], ["doc_id", "piece", "ids_crc32"])
    return ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "rank").mapInArrow(place, PLACED_SCHEMA)


def pack_documents(docs: DataFrame, tokenizer: str, end_id: int = 0, capacity: int = 2048) -> DataFrame:
    """Pieces of all documents with their sequence and place in it."""
    return pack_pieces(cut_pieces(docs, tokenizer, end_id, capacity), capacity)


def packed_sequences(docs: DataFrame, tokenizer: str, end_id: int = 0, capacity: int = 2048) -> DataFrame:
    """The packed sequences themselves: sequence_id and its ids, end to end."""
    pieces = materialise(cut_pieces(docs, tokenizer, end_id, capacity, with_ids=True), "pieces-with-ids")
    # pieces with the same id, number, length and checksum stand for each other
    same = [F.col("doc_id").isNull().alias("unnamed"), F.coalesce("doc_id", F.lit(0)).alias("id"), "piece", "length", "ids_crc32"]
    ids = pieces.select(*same, "ids").dropDuplicates(["unnamed", "id", "piece", "length", "ids_crc32"])
    joined = pack_pieces(pieces, capacity).select(*same, "sequence_id", "offset").join(ids, ["unnamed", "id", "piece", "length", "ids_crc32"])
    return joined.groupBy("sequence_id").agg(F.flatten(F.transform(F.sort_array(F.collect_list(F.struct("offset", "ids"))), lambda x: x["ids"])).alias("ids"))
