"""Lower-cased words of texts as arrays."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from edgemill.llm.wordtokens import slices

BREAKS = r"[\t\n\r !-/:-@\[-\^`{-~\x{a1}-\x{a9}\x{ab}-\x{b1}\x{b4}\x{b6}-\x{b8}\x{bb}\x{bf}\x{d7}\x{f7}]+"
USUAL_ONLY = r"[^\t\n\r\x20-\x7e\x{a1}-\x{24f}]|\x{130}"
WORDS = re.compile(r"\w+")


def word_lists(texts: pa.Array) -> Iterator[tuple[np.ndarray, list[str], np.ndarray]]:
    """(codes of all words end to end, distinct words, number of words of each text), slice by slice; words are lower-cased \\w+ runs."""
    for part in slices(pc.fill_null(texts, "")):
        odd = np.flatnonzero(pc.match_substring_regex(part, USUAL_ONLY).to_numpy(zero_copy_only=False))
        at = 0
        for k in [*odd.tolist(), len(part)]:
            if k > at:
                spaced = pc.replace_substring_regex(pc.utf8_lower(part.slice(at, k - at)), BREAKS, " ")
                lists = pc.ascii_split_whitespace(pc.ascii_trim_whitespace(spaced))
                coded = lists.flatten().dictionary_encode()
                sizes = np.diff(lists.offsets.to_numpy())
                words = coded.dictionary.to_numpy(zero_copy_only=False).tolist()
                codes = coded.indices.to_numpy()
                if "" in words:  # texts without words split into one empty string
                    empty = codes == words.index("")
                    sizes = sizes - np.add.reduceat(empty, np.minimum(np.cumsum(sizes) - sizes, len(empty) - 1)) * (sizes > 0)
                    codes = codes[~empty]
                yield codes, words, sizes
            if k < len(part):
                words = WORDS.findall(part[k].as_py().lower())
                distinct = {w: i for i, w in enumerate(dict.fromkeys(words))}
                yield np.array([distinct[w] for w in words], np.int64), list(distinct), np.array([len(words)])
            at = k + 1
