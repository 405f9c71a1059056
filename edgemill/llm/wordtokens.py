"""Whole-text encoding with the tokenizers library, once per distinct piece of text.

A batch of texts is lower-cased and cut into the vocabulary file's own pieces
with Arrow kernels, the pieces are dictionary-encoded, and each distinct piece
goes through the library's BPE model once per worker (kept in a bounded
two-generation memo). That holds for texts of ASCII and Latin letters, for
which the file's normaliser only lower-cases; a text with anything else
(other scripts, combining marks, control characters, special token strings)
goes through the library's complete `encode`. tests/llm/test_wordtokens.py
holds both ways against `encode` of whole texts.
"""

from __future__ import annotations

import os
from array import array
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: What the vocabulary file's splitter sets apart from letters, for ASCII and Latin text: contractions, runs of symbols, single numerals (fixed value).
SYMBOLS = r"!-/:-@\[-`{-~\x{a1}-\x{a9}\x{ab}-\x{b1}\x{b4}\x{b6}-\x{b8}\x{bb}\x{bf}\x{d7}\x{f7}"
PIECE = rf"('s|'t|'re|'ve|'m|'ll|'d|[{SYMBOLS}]+|[0-9\x{{b2}}\x{{b3}}\x{{b9}}\x{{bc}}-\x{{be}}])"
#: Texts that need more than lower-casing, or have other white space than these.
UNUSUAL = r"[^\t\n\r\x20-\x7e\x{a1}-\x{24f}]|<\||\x{130}"
#: Texts are encoded in slices of about so many bytes.
SLICE_BYTES = 8 << 20
#: The same for encoding by this vocabulary, whose arrays take some ten times a slice.
ENCODE_BYTES = 4 << 20


def byte_letters() -> dict[int, str]:
    """Printable stand-ins of bytes in byte-level vocabularies: printable Latin-1 bytes stand for themselves, the others follow from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    table = {b: chr(b) for b in plain}
    for b in range(256):
        if b not in table:
            table[b] = chr(256 + len(table) - len(plain))
    return table


class TwoAges(dict):
    """A memo of at most 2 * limit entries: when the young half is full it becomes the old one."""

    def __init__(self, compute: Callable[[str], bytes], limit: int, longest: int = 64):
        super().__init__()
        self.compute, self.limit, self.longest, self.old = compute, limit, longest, {}

    def __missing__(self, key: str) -> bytes:
        value = self.old.get(key)
        if value is None:
            value = self.compute(key)
        if len(key) <= self.longest:
            if len(self) >= self.limit:
                self.old = dict(self)
                self.clear()
            self[key] = value
        return value


def spread(pieces: pa.ListArray, of: Callable[[str], bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Ids of lists of pieces, end to end, and how many each list has; `of` is asked once per distinct piece."""
    coded = pieces.flatten().dictionary_encode()
    taken = pa.array(list(map(of, coded.dictionary.to_numpy(zero_copy_only=False))), pa.binary()).take(coded.indices)
    if not len(taken):
        return np.zeros(0, "<u4"), np.zeros(len(pieces), np.int64)
    ends = np.frombuffer(taken.buffers()[1], np.int32)[taken.offset : taken.offset + len(taken) + 1]
    ids = np.frombuffer(taken.buffers()[2], "<u4", (ends[-1] - ends[0]) >> 2, ends[0])
    bounds = pieces.offsets.to_numpy() - pieces.offsets[0].as_py()
    return ids, np.diff(ends[bounds].astype(np.int64)) >> 2


def slices(texts: pa.Array, most: int = SLICE_BYTES) -> Iterator[pa.Array]:
    """Consecutive slices of about `most` bytes; a longer text is a slice of its own."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy())
    at = 0
    while at < len(texts):
        base = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, base + most, "right")))
        yield texts.slice(at, to - at)
        pa.default_memory_pool().release_unused()  # workers live on; what a slice took goes back before the next
        at = to


class WordEncoder:
    def __init__(self, path: str, memo: int = 100_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.model = self.library.model
        self.vocabulary = self.library.get_vocab_size(with_added_tokens=True)
        self.letters = byte_letters()
        self.pieces = TwoAges(self._piece, memo)

    def _piece(self, piece: str) -> bytes:
        if not piece.isascii():
            piece = piece.encode().decode("latin-1").translate(self.letters)
        return array("I", [t.id for t in self.model.tokenize(piece)]).tobytes()

    def whole(self, text: str) -> np.ndarray:
        """The ids of one text by the library's complete encode."""
        return np.array(self.library.encode(text, add_special_tokens=False).ids, "<u4")

    def usual(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        spaced = pc.replace_substring_regex(pc.utf8_lower(texts), PIECE, r" \1 ")
        return spread(pc.ascii_split_whitespace(pc.ascii_trim_whitespace(spaced)), self._known)

    def _known(self, piece: str) -> bytes:
        return self.pieces[piece] if piece else b""

    def encode(self, texts: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(ids of the texts end to end, number of ids of each text) for slices of the texts, in order; null is empty."""
        for part in slices(pc.fill_null(texts, ""), ENCODE_BYTES):
            odd = np.flatnonzero(pc.match_substring_regex(part, UNUSUAL).to_numpy(zero_copy_only=False))
            if not len(odd):
                yield self.usual(part)
                continue
            at = 0
            for k in [*odd.tolist(), len(part)]:
                if k > at:
                    yield self.usual(part.slice(at, k - at))
                if k < len(part):
                    ids = self.whole(part[k].as_py())
                    yield ids, np.array([len(ids)])
                at = k + 1


_ENCODERS: dict[str, WordEncoder] = {}


def word_encoder(path: str) -> WordEncoder:
    """One encoder per worker process and file; workers are reused, and so is the memo."""
    if path not in _ENCODERS:
        _ENCODERS[path] = WordEncoder(path)
    return _ENCODERS[path]


def end_every(ids: np.ndarray, counts: np.ndarray, end: int) -> tuple[np.ndarray, np.ndarray]:
    """The same with the id `end` after every text."""
    ends = np.cumsum(counts)
    return np.insert(ids, ends, np.uint32(end)).astype("<u4"), counts + 1
