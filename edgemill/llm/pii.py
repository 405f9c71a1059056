"""Personal data, also where it is disguised, with spans of the source text.

Base detectors (e-mail, IPv4, card, phone) run on the text itself. Texts that may
hold a disguise also go through a chain of transducers, each of which reads and
writes (character, source span) pairs: look-alike letters become ASCII and
invisible characters vanish, spelled digits become digits, and at/dot
disguises become "@" and ".". Detectors then run on the normalised text and
their matches are mapped back to source spans. Such a span is added where it
covers something that was normalised and overlaps no base span of its kind but
those it contains and extends.

Offsets are code points, end exclusive. Null and empty texts have no spans. All
detectors take linear time on any text. Repeated rows give equal
results; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgemill.llm.common import id_and_text, ship_package

KINDS = ("email", "ip", "card", "phone")
Span = tuple[int, int]

_LOCAL = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-"
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")

#: Spelled digits, 0 to 9, in English, German, French and Spanish (fixed values).
DIGIT_WORDS = {word: str(k) for words in (
    "zero one two three four five six seven eight nine",
    "null eins zwei drei vier fünf sechs sieben acht neun",
    "zéro un deux trois quatre cinq six sept huit neuf",
    "cero uno dos tres cuatro cinco seis siete ocho nueve",
) for k, word in enumerate(words.split())}
#: Look-alike letters of other scripts and the ASCII letters they pass for (fixed values).
LOOK_ALIKES = {pair[0]: pair[1] for pair in (
    "АA ВB ЕE КK МM НH ОO РP СC ТT УY ХX аa еe оo рp сc уy хx іi јj ѕs һh ԁd ԛq ԝw "
    "ΑA ΒB ΕE ΖZ ΗH ΙI ΚK ΜM ΝN ΟO ΡP ΤT ΥY ΧX αa οo ρp νv ιi κk τt υu"
).split()}
#: Characters that do not show (fixed values).
INVISIBLE = "\u00ad\u200b\u200c\u200d\u2060\ufeff"
_FULLWIDTH = {chr(0xFF00 + k): chr(0x20 + k) for k in range(1, 95)}
_FOLD = _FULLWIDTH | LOOK_ALIKES | {c: "" for c in INVISIBLE}
_FOLDED = re.compile("[" + "".join(map(re.escape, _FOLD)) + "]")
_WORDS = "|".join(DIGIT_WORDS)
_LETTER = r"[^\W\d_]"
_SPELLED = re.compile(rf"(?<!{_LETTER})(?:{_WORDS})(?:[\s-]+(?:{_WORDS}))*(?!{_LETTER})", re.I)
_PLUS = re.compile(r"(?<![A-Za-z])plus[ \t]+(?=[0-9])", re.I)
#: Placeholders for an "at" or "dot" that stands as a plain word: they count only together.
WEAK_AT, WEAK_DOT = "\ue000", "\ue001"
_AT_DOT = re.compile(r"\s*[\[({<]\s*(at|dot|@|\.)\s*[\])}>]\s*|(?<=[A-Za-z0-9])[ \t_]+(at|dot)[ \t_]+(?=[A-Za-z0-9])", re.I)
_HIDDEN_MAIL = re.compile(rf"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+{WEAK_DOT}-]+[@{WEAK_AT}][A-Za-z0-9-]+(?:[.{WEAK_DOT}][A-Za-z0-9-]+)+")
#: What \s means to Python; RE2 knows only the ASCII ones.
_SPACE = "\t-\r\x1c-\x20\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
#: Letters that Python's re.I takes for an ASCII i, s or k.
_CASE_KIN = {"\u0130": "i", "\u0131": "i", "\u017f": "s", "\u212a": "k"}
#: A text without a match holds no disguise: one branch for every transducer, none narrower than it. A plain "at" is left out, as
#: it shows nothing without another change. RE2 syntax, upper and lower case alike.
MAY_HIDE = (
    "[" + "".join(_FOLD) + "".join(_CASE_KIN) + "]"
    + rf"|(?:^|[^A-Za-z])(?:{_WORDS})(?:[^A-Za-z]|$)|plus[ \t]+[0-9]"
    + rf"|[\[({{<][{_SPACE}]*(?:at|dot|@|\.)[{_SPACE}]*[\])}}>]|[ \t_]dot[ \t_]"
)
#: RE2 patterns without which a base kind cannot match.
NEEDS = {"email": "@", "ip": r"[0-9]\.[0-9]", "card": r"[0-9](?:[ -]?[0-9]){12}", "phone": r"\+[0-9]"}


def emails(text: str) -> list[Span]:
    """Leftmost non-overlapping; the part before "@" is the run of its characters that ends there."""
    out: list[Span] = []
    free = 0
    for m in _DOMAIN.finditer(text):
        lo = max(free, text.rfind("@", 0, m.start()) + 1)
        start = lo + len(text[lo : m.start()].rstrip(_LOCAL))
        if start < m.start():
            out.append((start, m.end()))
            free = m.end()
    return out


def ips(text: str) -> list[Span]:
    small = lambda part: len(part := part.lstrip("0")) < 3 or len(part) == 3 and int(part) <= 255
    return [m.span() for m in _IP.finditer(text) if all(map(small, m[0].split(".")))]


def luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(reversed(digits)):
        d = int(d) << (k & 1)
        total += d - 9 if d > 9 else d
    return total % 10 == 0


def cards(text: str) -> list[Span]:
    out = []
    for m in _CARD.finditer(text):
        digits = m[0].replace(" ", "").replace("-", "")
        if 13 <= len(digits) <= 19 and luhn(digits):
            out.append(m.span())
    return out


def phones(text: str) -> list[Span]:
    return [m.span() for m in _PHONE.finditer(text) if 9 <= sum(map(str.isdigit, m[0])) <= 15]


DETECTORS = dict(zip(KINDS, (emails, ips, cards, phones)))


class Tape:
    """Text with the source span of every character."""

    def __init__(self, text: str, lo: np.ndarray | None = None, hi: np.ndarray | None = None, changed: np.ndarray | None = None):
        n = len(text)
        self.text = text
        self.lo = np.arange(n) if lo is None else lo
        self.hi = np.arange(1, n + 1) if hi is None else hi
        self.changed = np.zeros(n, bool) if changed is None else changed

    def rewrite(self, pattern: re.Pattern, output) -> Tape:
        """Replace every match by output(match); its characters share the source span of the match. None keeps it."""
        parts, lo, hi, changed, at = [], [], [], [], 0
        for m in pattern.finditer(self.text):
            out = output(m)
            if out is None or m.start() == m.end():
                continue
            a, b = m.span()
            parts += [self.text[at:a], out]
            lo += [self.lo[at:a], np.full(len(out), self.lo[a])]
            hi += [self.hi[at:a], np.full(len(out), self.hi[b - 1])]
            changed += [self.changed[at:a], np.ones(len(out), bool)]
            at = b
        if not parts:
            return self
        return Tape("".join([*parts, self.text[at:]]), *(np.concatenate([*x, y[at:]]) for x, y in ((lo, self.lo), (hi, self.hi), (changed, self.changed))))

    def source(self, span: Span) -> Span:
        return int(self.lo[span[0]]), int(self.hi[span[1] - 1])


def _digits(m: re.Match) -> str:
    word = "".join(_CASE_KIN.get(c, c) for c in m[0]).lower()
    return "".join(DIGIT_WORDS[w] for w in re.split(r"[\s-]+", word))


def _at_dot(m: re.Match) -> str:
    if m[1]:
        return "@" if m[1].lower() in ("at", "@") else "."
    return WEAK_AT if m[2].lower() == "at" else WEAK_DOT


def normalise(text: str) -> Tape:
    """The chain: characters, spelled digits, at/dot."""
    tape = Tape(text).rewrite(_FOLDED, lambda m: _FOLD[m[0]])
    tape = tape.rewrite(_SPELLED, _digits).rewrite(_PLUS, lambda m: "+")
    return tape.rewrite(_AT_DOT, _at_dot)


def hidden(text: str) -> dict[str, list[Span]]:
    """Source spans that only the normalised text shows."""
    tape = normalise(text)
    found: dict[str, list[Span]] = {k: [] for k in KINDS}
    if not tape.changed.any() and tape.text == text:
        return found
    # the placeholder of a plain "at" stays: no number goes across that word
    plain = tape.text.replace(WEAK_DOT, ".")
    # "a at b.c" alone is prose: a plain "at" needs a disguised dot, a plain "dot" between words a disguised at
    for m in _HIDDEN_MAIL.finditer(tape.text):
        s, at = m[0], max(m[0].find("@"), m[0].find(WEAK_AT))
        if s[at] == WEAK_AT and WEAK_DOT not in s[at:] and not tape.changed[m.start() + at + 1 : m.end()].any():
            continue
        lead = len(s) - len(s.lstrip("." + WEAK_DOT))
        if lead < at:
            found["email"].append((m.start() + lead, m.end()))
    for kind in KINDS[1:]:
        found[kind] = DETECTORS[kind](plain)
    invisible_at = np.flatnonzero(np.append(tape.lo[1:] != tape.hi[:-1], False)) if len(tape.lo) > 1 else np.zeros(0, int)

    def touched(a: int, b: int) -> bool:
        return bool(tape.changed[a:b].any()) or bool(((invisible_at >= a) & (invisible_at < b - 1)).any())

    return {k: [tape.source(s) for s in v if touched(*s)] for k, v in found.items()}


def find(text: str, base_kinds: tuple[str, ...] = KINDS, disguised: bool = True) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]:
    """(base spans, all spans), each by kind and then start; only base_kinds are looked for in the text itself."""
    base = {k: DETECTORS[k](text) if k in base_kinds else [] for k in KINDS}
    every = base
    if disguised:
        every = {}
        for kind, spans in hidden(text).items():
            extra, free = [], -1
            for a, b in sorted(spans):
                if a >= free and not any(a < d and c < b and not (a <= c and d <= b and (a, b) != (c, d)) for c, d in base[kind]):
                    extra.append((a, b))
                    free = b
            every[kind] = sorted(base[kind] + extra)
    spell = lambda by: [(k, a, b) for k in KINDS for a, b in by[k]]
    return spell(base), spell(every)


def joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def findings(texts: pa.Array) -> Iterator[tuple[str, list, list]]:
    """(text, base spans, all spans) of each text; compiled filters pass over texts that can hold none."""
    texts = pc.fill_null(texts, "")
    needs = np.stack([pc.match_substring_regex(texts, NEEDS[k]).to_numpy(zero_copy_only=False) for k in KINDS], axis=1)
    hides = pc.match_substring_regex(texts, MAY_HIDE, ignore_case=True).to_numpy(zero_copy_only=False)
    for k in range(len(texts)):
        if hides[k] or needs[k].any():
            text = texts[k].as_py()
            yield text, *find(text, tuple(np.array(KINDS)[needs[k]]), bool(hides[k]))
        else:
            yield None, [], []


REPORT_SCHEMA = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_disguised long"


def report(docs: DataFrame) -> DataFrame:
    """Counts and digest of the base spans, and all spans, of every document; one narrow pass."""
    ship_package(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = {c: [] for c in ("n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_disguised")}
            for _, base, every in findings(batch.column(1)):
                for kind in KINDS:
                    rows[f"n_{kind}"].append(sum(k == kind for k, _, _ in base))
                rows["base_sha256"].append(hashlib.sha256(joined(base).encode()).hexdigest())
                rows["spans"].append(joined(every))
                rows["n_disguised"].append(len(every) - len(base))
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column(0)} | rows)

    return id_and_text(docs).mapInArrow(run, REPORT_SCHEMA)


def masked(text: str, spans: list[tuple[str, int, int]]) -> str:
    """The text with every span as <KIND>; of overlapping spans the union takes the first one's kind."""
    out, at = [], 0
    for a, b, kind in sorted((a, b, k) for k, a, b in spans):
        if a >= at:
            out += [text[at:a], f"<{kind.upper()}>"]
        at = max(at, b)
    return "".join([*out, text[at:]])


def mask(docs: DataFrame, text_col: str = "text", length_col: str = "n_chars") -> DataFrame:
    """docs with personal data masked in the text and, where there is such a column, its length set anew; all columns stay."""
    ship_package(docs.sparkSession)
    names = docs.columns
    at = names.index(text_col)
    length_at = names.index(length_col) if length_col in names else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            changed, lengths = {}, None
            for k, (text, _, every) in enumerate(findings(batch.column(at))):
                if every:
                    changed[k] = masked(text, every)
            if changed:
                columns = list(batch.columns)
                texts = columns[at].to_pylist()
                for k, t in changed.items():
                    texts[k] = t
                columns[at] = pa.array(texts, columns[at].type)
                if length_at is not None:
                    lengths = columns[length_at].to_pylist()
                    for k, t in changed.items():
                        lengths[k] = len(t)
                    columns[length_at] = pa.array(lengths, columns[length_at].type)
                batch = pa.RecordBatch.from_arrays(columns, batch.schema.names)
            yield batch

    return docs.mapInArrow(run, docs.schema)
