"""Token ids in files of fixed-width bit packing.

One file holds a range of documents in ascending id order. Ids take as many
bits as the vocabulary needs. They are packed in blocks; the directory at the
end of a file has each block's byte offset and each document's first id, so a
reader seeks to the blocks of any document and unpacks them with numpy.

File layout (little-endian): magic, payload of blocks, directory
(document ids, document starts, block offsets as int64), footer (number of
documents, ids, blocks, block size, bits, directory offset, leading documents without
an id as int64, magic).

Nulls and empty texts give a document that has the end id alone. Documents with null doc_id come
before all others; documents with equal ids stand in order of a hash of their texts, and repeated
rows stay separate documents. An empty table gives no file and no rows; other
columns are ignored. Files get a new name at each attempt of a task and only
those a finished task reports are read, so a lost executor leaves no wrong file
in use; files of lost attempts are deleted at the end.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgemill.llm.common import fresh_path, id_and_text, materialise, ship_package
from edgemill.llm.wordtokens import end_every, word_encoder

MAGIC = b"IDPACK02"
BLOCK = 1 << 16  # ids
FOOTER = np.dtype("<i8").itemsize * 7 + len(MAGIC)
FILE_SCHEMA = "part int, path string, first_doc long, n_docs long, n_tokens long"
DOC_SCHEMA = "doc_id long, start long, n_tokens long, ids_crc32 long"


def bits_for(vocabulary: int) -> int:
    """Bits that the largest id of a vocabulary needs."""
    return max(1, int(vocabulary - 1).bit_length())


def pack(ids: np.ndarray, bits: int) -> bytes:
    """32 ids fill `bits` 32-bit words; the last group is padded with zeros."""
    groups = -(-len(ids) // 32)
    lanes = np.zeros((groups, 32), "<u4")
    lanes.reshape(-1)[: len(ids)] = ids
    words = np.zeros((groups, bits), "<u4")
    for lane in range(32):
        word, shift = divmod(lane * bits, 32)
        words[:, word] |= lanes[:, lane] << np.uint32(shift)
        if shift + bits > 32:
            words[:, word + 1] |= lanes[:, lane] >> np.uint32(32 - shift)
    return words.tobytes()


def unpack(data: bytes, bits: int, count: int) -> np.ndarray:
    words = np.frombuffer(data, "<u4").reshape(-1, bits)
    lanes = np.empty((len(words), 32), "<u4")
    keep = np.uint32((1 << bits) - 1)
    for lane in range(32):
        word, shift = divmod(lane * bits, 32)
        value = words[:, word] >> np.uint32(shift)
        if shift + bits > 32:
            value = value | (words[:, word + 1] << np.uint32(32 - shift))
        lanes[:, lane] = value & keep
    return lanes.reshape(-1)[:count]


class PackedWriter:
    """Streams documents into one file; holds one block of ids and the directory."""

    def __init__(self, sink, bits: int, block: int = BLOCK):
        self.sink, self.bits, self.block = sink, bits, block
        self.sink.write(MAGIC)
        self.at, self.total, self.unnamed = len(MAGIC), 0, 0
        self.held: list[np.ndarray] = []
        self.n_held = 0
        self.docs: list[np.ndarray] = []
        self.counts: list[np.ndarray] = []
        self.offsets: list[int] = []

    def _put(self, ids: np.ndarray) -> None:
        data = pack(ids, self.bits)
        self.sink.write(data)
        self.offsets.append(self.at)
        self.at += len(data)

    def add(self, doc_ids: np.ndarray, ids: np.ndarray, counts: np.ndarray, unnamed: int = 0) -> None:
        """Documents in order; the first `unnamed` of them have no id (any number stands for it)."""
        self.unnamed += unnamed
        self.docs.append(doc_ids)
        self.counts.append(counts)
        self.total += len(ids)
        self.held.append(ids)
        self.n_held += len(ids)
        if self.n_held >= self.block:
            joined = np.concatenate(self.held)
            full = len(joined) // self.block * self.block
            for k in range(0, full, self.block):
                self._put(joined[k : k + self.block])
            self.held, self.n_held = [joined[full:]], len(joined) - full

    def close(self) -> None:
        if self.n_held:
            self._put(np.concatenate(self.held))
        docs = np.concatenate([np.zeros(0, "<i8"), *self.docs]).astype("<i8")
        counts = np.concatenate([np.zeros(0, "<i8"), *self.counts]).astype("<i8")
        starts = np.cumsum(counts) - counts
        directory = docs.tobytes() + starts.astype("<i8").tobytes() + np.array(self.offsets, "<i8").tobytes()
        self.sink.write(directory)
        self.sink.write(np.array([len(docs), self.total, len(self.offsets), self.block, self.bits, self.at, self.unnamed], "<i8").tobytes() + MAGIC)


class PackedFile:
    """Random access to one file through any seekable source."""

    def __init__(self, source):
        self.source = source
        size = source.size()
        source.seek(size - FOOTER)
        footer = source.read(FOOTER)
        if footer[-len(MAGIC) :] != MAGIC:
            raise ValueError("not a packed id file")
        self.n_docs, self.n_tokens, n_blocks, self.block, self.bits, at, self.unnamed = np.frombuffer(footer[: -len(MAGIC)], "<i8").tolist()
        source.seek(at)
        directory = np.frombuffer(source.read(size - FOOTER - at), "<i8")
        self.doc_ids = directory[: self.n_docs]
        self.starts = directory[self.n_docs : 2 * self.n_docs]
        self.offsets = directory[2 * self.n_docs : 2 * self.n_docs + n_blocks]
        self.ends = np.append(self.starts[1:], self.n_tokens)

    def ids_between(self, lo: int, hi: int) -> np.ndarray:
        """Ids lo to hi of the file; reads only the blocks that hold them."""
        if lo >= hi:
            return np.zeros(0, "<u4")
        first, last = lo // self.block, (hi - 1) // self.block
        parts = []
        for k in range(first, last + 1):
            count = min(self.block, self.n_tokens - k * self.block)
            self.source.seek(int(self.offsets[k]))
            parts.append(unpack(self.source.read(-(-count // 32) * self.bits * 4), self.bits, count))
        joined = np.concatenate(parts) if len(parts) > 1 else parts[0]
        return joined[lo - first * self.block : hi - first * self.block]

    def document(self, k: int) -> np.ndarray:
        """Ids of the file's k-th document."""
        return self.ids_between(int(self.starts[k]), int(self.ends[k]))


def _open(path: str):
    return pafs.FileSystem.from_uri(path)


def _keys(doc_ids: pa.Array, text_order: pa.Array) -> np.ndarray:
    """Bytes that compare like (has an id, id, text_order)."""
    out = np.empty((len(doc_ids), 17), np.uint8)
    out[:, 0] = 1 - doc_ids.is_null().to_numpy(zero_copy_only=False)
    for lo, column in ((1, pc.fill_null(doc_ids, 0)), (9, text_order)):
        out[:, lo : lo + 8] = (column.to_numpy().astype(np.int64).view(np.uint64) ^ np.uint64(1 << 63)).astype(">u8").view(np.uint8).reshape(-1, 8)
    return out.view("S17").reshape(-1)


def _bounds(keyed: DataFrame, files: int, most: int = 1_000_000) -> np.ndarray:
    """`files` - 1 keys that cut the documents into even ranges, from a sample of ids and text hashes (at most about `most` rows, no texts); they decide where files end, nothing else."""
    share = min(1.0, min(100 * files, most) / max(1, keyed.count()))
    sample = keyed.sample(share, 1).toArrow().combine_chunks() if share < 1 else keyed.toArrow().combine_chunks()
    if not sample.num_rows:
        return np.zeros(0, "S17")
    keys = np.sort(_keys(*(sample.column(k).combine_chunks() for k in (0, 1))))
    return keys[np.arange(1, files) * len(keys) // files]


def _parts(keys: np.ndarray, bounds: np.ndarray, spread: np.ndarray) -> np.ndarray:
    """The range of each key. Equal keys that several bounds share are dealt over all ranges that may hold them."""
    first, last = np.searchsorted(bounds, keys, "left"), np.searchsorted(bounds, keys, "right")
    return (first + spread % (last - first + 1)).astype(np.int32)


def _encoded(keyed: DataFrame, tokenizer: str, end_id: int, bounds: np.ndarray) -> DataFrame:
    """(part, doc_id, text_order, ids): ids of each whole text and the end id, as 16-bit numbers where the vocabulary allows that, else 32."""

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, seen = word_encoder(tokenizer), 0
        width = _width(bits_for(encoder.vocabulary))
        for batch in batches:
            parts = pa.array(_parts(_keys(batch.column(0), batch.column(1)), bounds, seen + np.arange(batch.num_rows)))
            seen += batch.num_rows
            at = 0
            for ids, counts in encoder.encode(batch.column(2)):
                ids, counts = end_every(ids, counts, end_id)
                data, ends = pa.py_buffer(ids.astype(f"<u{width}").tobytes()), np.cumsum(counts) * width
                packed = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(counts), [None, pa.py_buffer(np.append(0, ends).astype("<i8").tobytes()), data])
                columns = [x.slice(at, len(counts)) for x in (parts, batch.column(0), batch.column(1))]
                yield pa.RecordBatch.from_arrays([*columns, packed.cast(pa.binary())], ["part", "doc_id", "text_order", "ids"])
                at += len(counts)

    return keyed.mapInArrow(encode, "part int, doc_id long, text_order long, ids binary")


def _width(bits: int) -> int:
    return 2 if bits <= 16 else 4


def write_packed(docs: DataFrame, tokenizer: str, end_id: int, folder: str | None = None, files: int | None = None) -> DataFrame:
    """Encode every whole text, end each with `end_id`, and write files of ascending id ranges; returns the list of files.

    Columns of the result: part (ascending with the ids), path, first_doc, n_docs, n_tokens. Texts are encoded once, where they
    are read, and never shuffled; their ids (two bytes each for a vocabulary of up to 65,536) are, by ranges of doc_id, then
    text, and equal rows are dealt over all files of their range; a task streams its range.
    """
    spark = docs.sparkSession
    ship_package(spark)
    folder = folder or fresh_path(spark, "packed-ids")
    files = files or max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    bits = bits_for(word_encoder(tokenizer).vocabulary)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sink = store = None
        width = _width(bits)
        for batch in batches:
            if not batch.num_rows:
                continue
            if sink is None:
                store, at = _open(folder)
                store.create_dir(at, recursive=True)
                name = f"{uuid.uuid4().hex}.ids"
                raw = store.open_output_stream(f"{at}/{name}")
                sink, first = PackedWriter(raw, bits), batch.column(0)[0].as_py()
            for lo in range(0, batch.num_rows, 1024):
                part = batch.slice(lo, 1024)
                data = part.column(1).to_pylist()
                named = part.column(0)
                counts = np.fromiter(map(len, data), np.int64, len(data)) // width
                sink.add(pc.fill_null(named, 0).to_numpy(), np.frombuffer(b"".join(data), f"<u{width}").astype("<u4"), counts, named.null_count)
        if sink is not None:
            sink.close()
            raw.close()
            yield pa.RecordBatch.from_pydict({"part": pa.array([TaskContext.get().partitionId()], pa.int32()), "path": [f"{folder}/{name}"], "first_doc": pa.array([first], pa.int64()), "n_docs": [sum(map(len, sink.docs))], "n_tokens": [sink.total]})

    keyed = id_and_text(docs).select("doc_id", F.xxhash64("text").alias("text_order"), "text")
    encoded = _encoded(keyed, tokenizer, end_id, _bounds(keyed.select("doc_id", "text_order"), files))
    dealt = encoded.repartitionById(files, F.col("part")).sortWithinPartitions("doc_id", "text_order")
    stored = materialise(dealt.select("doc_id", "ids").mapInArrow(write, FILE_SCHEMA), "packed-files")
    _delete_others(stored, folder)
    return stored


def _delete_others(stored: DataFrame, folder: str) -> None:
    """Remove what attempts that did not finish have left; one name a file passes through the driver."""
    names = {r.path.rsplit("/", 1)[1] for r in stored.select("path").collect()}
    spark = stored.sparkSession
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    store = path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())
    for entry in store.listStatus(path) if names else ():
        if entry.getPath().getName() not in names and entry.getPath().getName().endswith(".ids"):
            store.delete(entry.getPath(), False)


def read_packed(files: DataFrame) -> DataFrame:
    """Read the files of `write_packed` back: one row per document with its place among all ids, count and crc32 of its ids.

    The list of files (one row a file) passes through the driver to number the ids across files; a task reads one file.
    """
    spark = files.sparkSession
    ship_package(spark)
    rows, total = [], 0
    for k, r in enumerate(sorted(files.collect(), key=lambda r: r.part)):
        rows.append((k, r.path, total))
        total += r.n_tokens
    listed = spark.createDataFrame(rows, "k int, path string, base long")
    places = listed.repartitionById(max(1, len(rows)), F.col("k")).select("path", "base")

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                store, at = _open(path)
                with store.open_input_file(at) as source:
                    packed = PackedFile(source)
                    step = max(1, BLOCK * 64)
                    k = 0
                    while k < packed.n_docs:
                        to = max(k + 1, int(np.searchsorted(packed.ends, packed.starts[k] + step, "right")))
                        lo = int(packed.starts[k])
                        ids = packed.ids_between(lo, int(packed.ends[to - 1]))
                        raw = memoryview(ids.astype("<u4").tobytes())
                        cuts = ((packed.starts[k:to] - lo) * 4).tolist(), ((packed.ends[k:to] - lo) * 4).tolist()
                        yield pa.RecordBatch.from_pydict({
                            "doc_id": pa.array(packed.doc_ids[k:to], mask=np.arange(k, to) < packed.unnamed), "start": packed.starts[k:to] + base, "n_tokens": packed.ends[k:to] - packed.starts[k:to],
                            "ids_crc32": np.array([zlib.crc32(raw[a:b]) for a, b in zip(*cuts)], np.int64),
                        })
                        k = to

    return places.mapInArrow(read, DOC_SCHEMA)
