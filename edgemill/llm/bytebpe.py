"""Byte-level BPE as a lazily determinised transducer, and a streaming decoder.

Encoding. Merge ranks decide, for any two tokens, whether they stay apart when
their bytes stand together; a token sequence is the encoding of its bytes just
where all neighbours do. So a left-to-right automaton suffices: for each prefix
it keeps the encodings that a longer prefix can still continue, which are
those ending where some vocabulary entry may still be under way, within
the length of the longest entry. A state is that set; what all its encodings
share is emitted at once. States and transitions are made when first met and kept
(the whole memo is dropped when it grows past a limit).

Decoding. Token bytes run through a UTF-8 state machine that keeps the bytes of an
unfinished character between calls.

Null and empty texts have no ids. Any text round-trips. Very long pieces take
time in proportion to their length.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame

from edgemill.llm.common import id_and_text, ship_package
from edgemill.llm.wordtokens import TwoAges, slices, spread

DOC_SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
#: A boundary follows each match of these, wherever it stands: the alternatives of the public pattern that are not white space.
SOLID = r"('s|'t|'re|'ve|'m|'ll|'d| ?[a-zA-Z\x{c0}-\x{d6}\x{d8}-\x{f6}\x{f8}-\x{24f}]+| ?[0-9]+| ?[!-/:-@\[-`{-~]+)"
USUAL_ONLY = r"[^\t\n\r\x20-\x7e\x{c0}-\x{d6}\x{d8}-\x{f6}\x{f8}-\x{24f}]"
MARK = "\x00"
#: Texts with white space after white space, or with a comma or full stop after white space or a symbol, are cut by SOLID; in all others these literal cuts are boundaries of the pattern.
CROWDED = r"[\t\n\r ][\t\n\r ]|[\t\n\r !-/:-@\[-`{-~][,.]"
CUTS = ((" ", MARK + " "), ("\n", MARK + "\n" + MARK), (",", MARK + ","), (".", MARK + "."))


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(word): int(rank) for word, rank in map(bytes.split, f)}


class MergeTransducer:
    """Byte-by-byte encoder of one piece; `limit` bounds the states that are kept."""

    def __init__(self, ranks: dict[bytes, int], limit: int = 200_000):
        self.ranks, self.limit = ranks, limit
        self.words = {i: w for w, i in ranks.items()}
        #: Every beginning of an entry: (the entry it is, or None; whether a longer one begins with it).
        self.begun: dict[bytes, tuple[int | None, bool]] = {w: (i, False) for w, i in ranks.items()}
        for w in ranks:
            for k in range(1, len(w)):
                self.begun[w[:k]] = (ranks.get(w[:k]), True)
        self.apart_memo: dict[tuple[int, int], bool] = {}
        self.whole_memo: dict[bytes, bool] = {}
        self.halves_memo: dict[int, tuple[int, int] | None] = {}
        self._reset()

    def _reset(self) -> None:
        self.states: dict[tuple, int] = {}
        self.keys: list[tuple] = []
        self.moves: list[dict[int, tuple[int, bytes]]] = []
        self.ends: list[bytes | None] = []
        self.begin = self._state((b"", ((0, (-1,)),)))

    def _state(self, key: tuple) -> int:
        k = self.states.get(key)
        if k is None:
            k = self.states[key] = len(self.keys)
            self.keys.append(key)
            self.moves.append({})
            self.ends.append(None)
        return k

    def merged(self, data: bytes, down_to: int = 1) -> list[int]:
        """Plain merging by rank, for short strings: the lowest rank first, the leftmost of equal ones."""
        parts = [data[i : i + 1] for i in range(len(data))]
        while len(parts) > down_to:
            ranked = [(self.ranks.get(a + b, 1 << 40), i) for i, (a, b) in enumerate(zip(parts, parts[1:]))]
            rank, i = min(ranked)
            if rank == 1 << 40:
                break
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return [self.ranks[p] for p in parts]

    def _reachable(self, word: bytes) -> bool:
        known = self.whole_memo.get(word)
        if known is None:
            known = self.whole_memo[word] = self.merged(word) == [self.ranks[word]]
        return known

    def _halves(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose merge makes this one; None for single bytes."""
        if token not in self.halves_memo:
            word = self.words[token]
            parts = self.merged(word, 2) if len(word) > 1 else []
            self.halves_memo[token] = (parts[0], parts[1]) if len(parts) == 2 else None
        return self.halves_memo[token]

    def _apart(self, a: int, b: int) -> bool:
        """Whether tokens a and b stay as they are side by side.

        Merges are undone at the border, the later one first. A token of both inner
        parts that comes before the merge just undone would have been made
        instead, so the border would not stand.
        """
        if a < 0:
            return True
        known = self.apart_memo.get((a, b))
        if known is not None:
            return known
        if len(self.apart_memo) > 2_000_000:
            self.apart_memo.clear()
        left, right, before, known = a, b, 1 << 40, True
        while True:
            across = self.ranks.get(self.words[left] + self.words[right])
            if across is not None and across < before:
                known = False
                break
            in_left, in_right = self._halves(left), self._halves(right)
            if in_left is not None and (left > right or in_right is None):
                before, left = left, in_left[1]
            elif in_right is not None:
                before, right = right + 1, in_right[0]
            else:
                break
        self.apart_memo[a, b] = known
        return known

    def _move(self, state: int, byte: int) -> tuple[int, bytes]:
        tail, live = self.keys[state]
        tail += bytes([byte])
        size, ending, kept = len(tail), None, []
        begun = self.begun.get
        for back, path in live:
            known = begun(tail[size - back - 1 :])
            if known is None:
                continue
            token, longer = known
            if ending is None and token is not None and self._apart(path[-1], token) and self._reachable(self.words[token]):
                ending = (*path, token)
            if longer:
                kept.append((back + 1, path))
        if ending is None:
            raise ValueError("the rank file lacks a single byte")
        kept.append((0, ending))
        # what the least and the greatest path share, all of them do
        paths = [p for _, p in kept]
        least, most = min(paths), max(paths)
        shared, shortest = 0, min(len(least), len(most))
        while shared < shortest and least[shared] == most[shared]:
            shared += 1
        shared = max(shared, 1)
        emitted = array("I", paths[0][1:shared]).tobytes()
        kept = tuple((back, p[shared - 1 :]) for back, p in kept)
        to = self._state((tail[size - kept[0][0] :] if kept[0][0] else b"", kept))
        self.moves[state][byte] = result = (to, emitted)
        return result

    def _end(self, state: int) -> bytes:
        self.ends[state] = out = array("I", self.keys[state][1][-1][1][1:]).tobytes()
        return out

    def encode(self, piece: bytes) -> bytes:
        """Ids of one piece as little-endian unsigned 32-bit integers; a piece that is a vocabulary entry is that entry."""
        direct = self.ranks.get(piece)
        if direct is not None:
            return array("I", [direct]).tobytes()
        if len(self.keys) > self.limit:
            self._reset()
        moves, state, out = self.moves, self.begin, []
        for byte in piece:
            step = moves[state].get(byte)
            if step is None:
                step = self._move(state, byte)
            state, emitted = step
            if emitted:
                out.append(emitted)
        last = self.ends[state]
        out.append(self._end(state) if last is None else last)
        return b"".join(out)


class Utf8Machine:
    """Incremental UTF-8: feed bytes in any cuts; complete characters come out, an unfinished one stays for the next call.

    States are the number of bytes still due and the range the next one may have;
    a byte that cannot continue gives U+FFFD.
    """

    def __init__(self) -> None:
        self.kept, self.due, self.lo, self.hi = bytearray(), 0, 0x80, 0xBF

    @staticmethod
    def _lead(b: int) -> tuple[int, int, int] | None:
        if 0xC2 <= b <= 0xDF:
            return 1, 0x80, 0xBF
        if 0xE0 <= b <= 0xEF:
            return 2, 0xA0 if b == 0xE0 else 0x80, 0x9F if b == 0xED else 0xBF
        if 0xF0 <= b <= 0xF4:
            return 3, 0x90 if b == 0xF0 else 0x80, 0x8F if b == 0xF4 else 0xBF
        return None

    def feed(self, data: bytes, final: bool = False) -> str:
        if not self.kept:
            # whole characters at once; the machine itself runs from the first doubtful byte
            try:
                return data.decode()
            except UnicodeDecodeError as e:
                out, data = [data[: e.start].decode()], data[e.start :]
        else:
            out = []
        for b in data:
            if self.due and not self.lo <= b <= self.hi:
                out.append("�")
                self.kept.clear()
                self.due = 0
            if self.due:
                self.kept.append(b)
                self.due, self.lo, self.hi = self.due - 1, 0x80, 0xBF
                if not self.due:
                    out.append(self.kept.decode())
                    self.kept.clear()
            elif b < 0x80:
                out.append(chr(b))
            elif lead := self._lead(b):
                self.due, self.lo, self.hi = lead
                self.kept.append(b)
            else:
                out.append("�")
        if final and self.kept:
            out.append("�")
            self.kept.clear()
            self.due = 0
        return "".join(out)


class ByteBpe:
    """Ranks, pattern, memo of distinct pieces and decoder tables of one vocabulary."""

    def __init__(self, path: str, pattern: str, memo: int = 400_000):
        self.machine = MergeTransducer(load_ranks(path))
        self.find = regex.compile(pattern).findall
        self.pieces = TwoAges(self._piece, memo)
        size = max(self.machine.words) + 1
        self.table = pa.array([self.machine.words.get(i) for i in range(size)], pa.binary())

    def _piece(self, text: str) -> bytes:
        return b"".join(self.machine.encode(p.encode()) for p in self.find(text))

    def encode_text(self, text: str) -> bytes:
        return b"".join(self.machine.encode(p.encode()) for p in self.find(text))

    def encode(self, texts: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(ids end to end, ids of each text), slice by slice.

        Usual texts (ASCII and Latin letters) are cut with Arrow, before spaces, commas
        and full stops and around line feeds where those stand alone, or else after each
        solid match; what lies between cuts is matched by the pattern itself, once per distinct
        string. Others are matched whole.
        """
        for part in slices(pc.fill_null(texts, "")):
            kind = pc.match_substring_regex(part, CROWDED).to_numpy(zero_copy_only=False).astype(np.int8)
            kind[pc.match_substring_regex(part, USUAL_ONLY).to_numpy(zero_copy_only=False)] = 2
            bounds = np.flatnonzero(np.diff(kind)) + 1
            for lo, hi in zip([0, *bounds.tolist()], [*bounds.tolist(), len(kind)]):
                run = part.slice(lo, hi - lo)
                if kind[lo] == 2:
                    for text in run.to_pylist():
                        ids = np.frombuffer(self.encode_text(text), "<u4")
                        yield ids, np.array([len(ids)])
                    continue
                if kind[lo] == 1:
                    run = pc.replace_substring_regex(run, SOLID, "\\1" + MARK)
                else:
                    for old, new in CUTS:
                        run = pc.replace_substring(run, old, new)
                yield spread(pc.split_pattern(run, MARK), self.pieces.__getitem__)

    def token_bytes(self, ids: np.ndarray) -> tuple[memoryview, np.ndarray]:
        """Bytes of tokens end to end, and where each token's begin."""
        taken = self.table.take(pa.array(ids))
        if not len(taken):
            return memoryview(b""), np.zeros(1, np.int64)
        ends = np.frombuffer(taken.buffers()[1], np.int32)[taken.offset : taken.offset + len(taken) + 1]
        return memoryview(taken.buffers()[2])[ends[0] : ends[-1]], (ends - ends[0]).astype(np.int64)

    def decode_stream(self, batches: Iterable[np.ndarray]) -> Iterator[str]:
        """Characters of a stream of ids as soon as they are complete."""
        machine = Utf8Machine()
        for ids in batches:
            yield machine.feed(bytes(self.token_bytes(ids)[0]))
        yield machine.feed(b"", final=True)


_CODECS: dict[tuple[str, str], ByteBpe] = {}


def codec(path: str, pattern: str) -> ByteBpe:
    if (path, pattern) not in _CODECS:
        _CODECS[path, pattern] = ByteBpe(path, pattern)
    return _CODECS[path, pattern]


def encode_and_decode(docs: DataFrame, ranks: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens and digests of the ids and of the decoded text of every document; one narrow pass."""
    ship_package(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = codec(ranks, pattern)
        for batch in batches:
            rows: dict[str, list] = {"doc_id": batch.column(0).to_pylist(), "n_tokens": [], "ids_sha256": [], "decoded_sha256": []}
            for ids, counts in bpe.encode(batch.column(1)):
                raw, ends = memoryview(ids.astype("<u4").tobytes()), np.cumsum(counts)
                text, starts = bpe.token_bytes(ids)
                cuts = starts[np.append(0, ends)].tolist()
                lows = np.append(0, ends[:-1]).tolist()
                for k, (lo, hi) in enumerate(zip(lows, ends.tolist())):
                    machine = Utf8Machine()
                    decoded = machine.feed(bytes(text[cuts[k] : cuts[k + 1]])) + machine.feed(b"", final=True)
                    rows["n_tokens"].append(hi - lo)
                    rows["ids_sha256"].append(hashlib.sha256(raw[4 * lo : 4 * hi]).hexdigest())
                    rows["decoded_sha256"].append(hashlib.sha256(decoded.encode()).hexdigest())
            yield pa.RecordBatch.from_pydict(rows)

    return id_and_text(docs).mapInArrow(run, DOC_SCHEMA)


def decode_ids(frame: DataFrame, ranks: str, pattern: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """Texts of rows that hold arrays of ids."""
    ship_package(frame.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = codec(ranks, pattern)
        for batch in batches:
            texts = ["".join(bpe.decode_stream([np.array(x or [], "<u4")])) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column(0), "text": texts})

    return frame.select(frame[id_col].alias("doc_id"), frame[ids_col].alias("ids")).mapInArrow(run, "doc_id long, text string")
