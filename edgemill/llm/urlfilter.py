"""URL rules as one bit-parallel wildcard automaton.

Every rule is a glob over the canonical URL "." + host + path. All globs lie
side by side in one multiword bit mask (Shift-And): a bit per pattern position,
moved on by one shift a character, kept where a star stands. A host star does
not cross a slash, so host rules match the host alone. A batch of URLs runs in
lockstep: one numpy step a character position for all of them.

Host: after the first "://" up to "/", "?", "#" or the end, A-Z lower-cased;
path: from there up to "?", "#" or the end. Null URLs and URLs without "://"
have empty host and path and match no rule. Ties: the longest rule (host and path)
wins; of equal ones the first. Repeated rows are judged alike; an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgemill.llm.common import ship_package

#: (verdict, host and path): the rule fits the host and its subdomains where the path starts with the rule's.
HOST_RULES = [("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/")]
#: (verdict, glob over ".host/path"), used where no host rule fits; the longest that fits wins, and none means allow.
GLOB_RULES = [("block", "*spam*"), ("block", "*casino*"), ("block", "*.xxx/*"), ("block", "*/ads/*"), ("block", "*/wp-login*"), ("allow", "*.edu/*")]
OUT_SCHEMA = "page_id long, host string, path string, rule string, verdict string"
_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def host_and_path(url: str | None) -> tuple[str, str]:
    if url is None or (at := url.find("://")) < 0:
        return "", ""
    rest = url[at + 3 :]
    host = re.split("[/?#]", rest, maxsplit=1)[0]
    return host.translate(_LOWER), re.split("[?#]", rest[len(host) :], maxsplit=1)[0]


@dataclass(frozen=True)
class Glob:
    """parts: literals between stars; slash[i]: whether the star before part i may cross "/"; open_end: a star ends it."""

    parts: tuple[str, ...]
    slash: tuple[bool, ...]
    open_end: bool

    @staticmethod
    def of_host_rule(rule: str) -> Glob:
        return Glob((f".{rule}",), (False,), True)

    @staticmethod
    def of_glob(glob: str) -> Glob:
        parts = tuple(x for x in glob.split("*") if x)
        if not parts:
            raise ValueError("a glob needs a literal character")
        if not glob.startswith("*"):
            raise ValueError("globs start with * here: the canonical URL starts with a dot")
        return Glob(parts, (True,) * len(parts), glob.endswith("*"))


class ShiftAnd:
    """All globs at once; bytes are the alphabet, 64 positions a word.

    Bit layout of a glob: one bit per literal byte. Bit i is set after a
    prefix that ends with literal byte i matched; before a part, a star keeps
    "the part may start here" as a bit of its own.
    """

    def __init__(self, globs: list[Glob]):
        bits: list[tuple[str, int, bool]] = []  # kind, byte, star crosses a slash
        self.first, self.accept = [], []
        for g in globs:
            for i, part in enumerate(g.parts):
                star = len(bits)
                bits.append(("star", -1, g.slash[i]))
                if i == 0:
                    self.first.append(star)
                bits += [("byte", b, False) for b in part.encode()]
            if g.open_end:
                bits.append(("star", -1, True))
            self.accept.append(len(bits) - 1)
        self.words = max(1, -(-len(bits) // 64))
        self.take = np.zeros((256, self.words), np.uint64)  # bits whose byte is c
        self.stay = np.zeros((256, self.words), np.uint64)  # star bits that c does not end
        self.star = self._mask([k for k, b in enumerate(bits) if b[0] == "star" and k not in self.first])
        self.start = self._mask(self.first)
        for c in range(256):
            self.take[c] = self._mask([k for k, b in enumerate(bits) if b[1] == c])
            self.stay[c] = self._mask([k for k, b in enumerate(bits) if b[0] == "star" and (b[2] or c != 47)])

    def _mask(self, positions: list[int]) -> np.ndarray:
        out = np.zeros(self.words, np.uint64)
        for k in positions:
            out[k // 64] |= np.uint64(1) << np.uint64(k % 64)
        return out

    def _shift(self, state: np.ndarray) -> np.ndarray:
        moved = state << np.uint64(1)
        moved[:, 1:] |= state[:, :-1] >> np.uint64(63)
        return moved

    def run(self, texts: list[bytes]) -> np.ndarray:
        """Matrix texts x globs: whether the whole text matches."""
        if not texts:
            return np.zeros((0, len(self.accept)), bool)
        order = np.argsort([-len(t) for t in texts], kind="stable")
        lengths = np.array([len(texts[k]) for k in order])
        flat = np.frombuffer(b"".join(texts[k] for k in order), np.uint8)
        starts = np.cumsum(lengths) - lengths
        state = np.tile(self.start, (len(texts), 1))
        for p in range(int(lengths[0])):
            n = int(np.searchsorted(-lengths, -p, "left"))  # texts longer than p come first
            c = flat[starts[:n] + p]
            now = state[:n]
            after = (self._shift(now) & self.take[c]) | (now & self.stay[c])
            state[:n] = after | (self._shift(after) & self.star)  # a literal that is complete opens the star behind it
        result = np.zeros((len(texts), len(self.accept)), bool)
        for g, k in enumerate(self.accept):
            result[order, g] = (state[:, k // 64] >> np.uint64(k % 64)) & np.uint64(1)
        return result


def judge_urls(pages: DataFrame, host_rules=HOST_RULES, glob_rules=GLOB_RULES, id_col: str = "page_id", url_col: str = "url", slice_bytes: int = 4 << 20) -> DataFrame:
    """page_id, host, path, rule, verdict of every URL; one narrow pass that reads two columns."""
    spark = pages.sparkSession
    ship_package(spark)
    automaton = ShiftAnd([Glob.of_host_rule(r) for _, r in host_rules] + [Glob.of_glob(g) for _, g in glob_rules])
    n, rules = len(host_rules), [*host_rules, *glob_rules]
    by_length = sorted(range(len(rules)), key=lambda k: (k >= n, -len(rules[k][1]), k))

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            pairs = [host_and_path(u) for u in batch.column(1).to_pylist()]
            texts = [(f".{h}{p}" if h or p else "").encode() for h, p in pairs]
            which = np.full(len(pairs), -1)
            at = 0
            while at < len(texts):  # slices bound what a step holds, whatever the URLs' length
                to, size = at, 0
                while to < len(texts) and (to == at or size + len(texts[to]) <= slice_bytes):
                    size += len(texts[to])
                    to += 1
                hit = automaton.run(texts[at:to])
                for k in reversed(by_length):
                    which[at:to][hit[:, k]] = k
                at = to
            yield pa.RecordBatch.from_pydict({
                "page_id": batch.column(0), "host": [h for h, _ in pairs], "path": [p for _, p in pairs],
                "rule": pa.array([rules[k][1] if 0 <= k < n else None for k in which], pa.string()), "verdict": [rules[k][0] if k >= 0 else "allow" for k in which],
            })

    return pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url")).mapInArrow(judge, OUT_SCHEMA)


def oracle_sql(host_rules=HOST_RULES, glob_rules=GLOB_RULES) -> str:
    """The same verdicts in SQL."""
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    hosts = sorted(host_rules, key=lambda r: -len(r[1]))
    fits = {r: f"starts_with(path, '{r[r.index('/'):]}') AND ends_with('.' || host, '.{r[: r.index('/')]}')" for _, r in hosts}
    rule = "CASE " + " ".join(f"WHEN {fits[r]} THEN '{r}'" for _, r in hosts) + " END"
    verdict = "CASE " + " ".join(f"WHEN {fits[r]} THEN '{v}'" for v, r in hosts)
    verdict += "".join(f" WHEN (host <> '' OR path <> '') AND ('.' || host || path) LIKE '{g.replace('*', '%')}' THEN '{v}'" for v, g in sorted(glob_rules, key=lambda r: -len(r[1]))) + " ELSE 'allow' END"
    return f"""
    WITH cut AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
    named AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), '{upper}', '{lower}') AS host,
                     regexp_extract(substr(rest, length(regexp_extract(rest, '^[^/?#]*')) + 1), '^[^?#]*') AS path FROM cut)
    SELECT page_id, host, path, {rule} AS rule, {verdict} AS verdict FROM named"""
