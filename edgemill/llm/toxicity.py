"""Toxic passages as maximum-scoring segments of token log-odds.

Fit. Words, and beginnings of words, of labelled rows are counted by label. Their scores
are log-odds with an informative Dirichlet prior (the pooled counts of the fitted
rows, scaled by `prior`), less `shrink` of their deviations. Words whose likelihood ratio stands out
speak for label 1: it must be beyond what chance alone would give `false_cues` of so many words. Every other word shares
one small negative score, the log-odds of "any other word".  The fit reads a
bounded sample of labelled rows (`fit_rows`, the lowest hashes of doc_id, distinct
texts), so its tables do not grow with the corpus; scoring covers every word of
every text.

Scan. All maximal scoring segments of a text are found in one linear pass (runs
of other words count as one step). A segment's score S in a text of n words is
calibrated by the extreme-value law: lambda solves sum p(w) exp(lambda s(w)) = 1
under label-0 word frequencies, K is fitted to the best segments of simulated
label-0 sequences, and E = K n exp(-lambda S). The best sum statistic over the top
segments is the evidence of the text; isotonic regression on the fitted rows, each
weighed by scores that leave its own counts out, turns it into a probability.

Null and empty texts have no segments and get the score of no evidence. Very long
texts are scanned whole. Repeated rows score alike. With no labelled rows
of both kinds, or without a word that stands out, every score is 0. Labels that repeat for an id, or differ between equal texts, count as 1 if any is. Rows
with null doc_id are scored like any other and are never fitted on. An empty table gives no rows.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgemill.llm.common import id_and_text, materialise, ship_package
from edgemill.llm.words import WORDS, word_lists

THRESHOLD = 0.3
#: Beginnings of words, by length, that are cues of their own (written with a star): inflected and compound words share them.
PREFIXES = (4, 5, 6, 7, 8)
SCORE_SCHEMA = "doc_id long, score double, predicted int, evidence double, n_segments int"
SEGMENT_SCHEMA = "doc_id long, start int, end int, segment_score double, e_value double, passage string"


def held_out(doc_id):
    """Whether crc32 of the id as text leaves 2 modulo 4; false for a null id, which has no such remainder."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def maximal_segments(items: list[tuple[float, int, int]]) -> list[tuple[float, int, int]]:
    """All maximal scoring segments of (score, first, last) items in order, as (score, first, last).

    Each open segment keeps the totals before and after it and a link to the
    nearest earlier one with a lower total before it, so that a walk back skips
    what can never be joined again; linear over all.
    """
    total = 0.0
    open_: list[list] = []  # [before, after, first, last, link]
    for score, first, last in items:
        before, total = total, total + score
        if score <= 0:
            continue
        seg = [before, total, first, last, -1]
        while True:
            j = len(open_) - 1
            while j >= 0 and open_[j][0] >= seg[0]:
                j = open_[j][4]
            if j < 0 or open_[j][1] >= seg[1]:
                seg[4] = j
                open_.append(seg)
                break
            seg = [open_[j][0], seg[1], open_[j][2], seg[3], -1]
            del open_[j:]
    return [(after - before, first, last) for before, after, first, last, _ in open_]


@dataclass
class ToxicModel:
    scores: dict[str, float] = field(default_factory=dict)
    other: float = -1.0
    lam: float = 1.0
    k: float = 1.0
    edges: np.ndarray = field(default_factory=lambda: np.array([0.0]))
    levels: np.ndarray = field(default_factory=lambda: np.array([0.0]))

    def word_score(self, word: str) -> float:
        """The strongest listed cue of a word: the word itself or one of its beginnings."""
        best = self.scores.get(word, 0.0)
        for k in PREFIXES:
            if len(word) <= k:
                break
            best = max(best, self.scores.get(word[:k] + "*", 0.0))
        return best

    def items(self, positions: np.ndarray, values: np.ndarray, n: int) -> list[tuple[float, int, int]]:
        """Scored words and the runs of other words between them."""
        out, at = [], 0
        for p, v in zip(positions.tolist(), values.tolist()):
            if p > at:
                out.append((self.other * (p - at), at, p - 1))
            out.append((v, p, p))
            at = p + 1
        if at < n:
            out.append((self.other * (n - at), at, n - 1))
        return out

    def evidence(self, segments: list[tuple[float, int, int]], n: int) -> float:
        """-log p of the best sum statistic over the top segments."""
        if not segments:
            return 0.0
        base, best, total, logs = math.log(self.k * max(n, 1)), 0.0, 0.0, 0.0
        for r, s in enumerate(sorted((self.lam * s - base for s, _, _ in segments), reverse=True), 1):
            total += s
            logs += math.log(r) + (math.log(r - 1) if r > 1 else 0.0)
            if total <= 0:
                break
            best = max(best, total - (r - 1) * math.log(max(total, 1.0)) + logs)
        return best

    def e_value(self, score: float, n: int) -> float:
        return self.k * n * math.exp(-min(self.lam * score, 700.0))

    def probability(self, evidence: np.ndarray) -> np.ndarray:
        return np.interp(evidence, self.edges, self.levels)


def isotonic(x: np.ndarray, label1: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Rising rates for rising x, pooling adjacent violators; half a row of each label is added to a pool."""
    pools: list[list[float]] = []
    for a, b in zip(label1.tolist(), rows.tolist()):
        pools.append([a, b, 1])
        while len(pools) > 1 and pools[-2][0] / pools[-2][1] >= pools[-1][0] / pools[-1][1]:
            a2, b2, n2 = pools.pop()
            pools[-1][0] += a2
            pools[-1][1] += b2
            pools[-1][2] += n2
    return np.repeat([(a + 0.5) / (b + 1.0) for a, b, _ in pools], [int(n) for _, _, n in pools])


def solve_lambda(p: np.ndarray, s: np.ndarray) -> float:
    """The positive root of sum p exp(lambda s) = 1 (the mean is negative, some score positive)."""
    lo, hi = 1e-9, 1.0
    excess = lambda x: float(np.sum(p * np.exp(np.minimum(x * s, 700.0)))) - 1.0
    while excess(hi) < 0 and hi < 64:
        hi *= 2
    for _ in range(80):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if excess(mid) < 0 else (lo, mid)
    return hi


def fit_k(p: np.ndarray, s: np.ndarray, lam: float, words: int = 2000, runs: int = 400, seed: int = 7) -> float:
    """K from the mean of the best segment of simulated background sequences (the Gumbel mean gives log(K n))."""
    rng = np.random.default_rng(seed)
    steps = s[np.searchsorted(np.cumsum(p), rng.random((runs, words)) * p.sum()).clip(max=len(s) - 1)]
    path = np.concatenate([np.zeros((runs, 1)), np.cumsum(steps, axis=1)], axis=1)
    best = (path - np.minimum.accumulate(path, axis=1)).max(axis=1)
    return float(np.exp(np.clip(lam * best.mean() - np.euler_gamma, -20.0, math.log(words))) / words)


def least_root(cues: int, false_cues: float) -> float:
    """The least signed root from which on chance alone would give `false_cues` of so many cues."""
    lo, hi = 0.0, 40.0
    for _ in range(60):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if cues * 0.5 * math.erfc(mid / math.sqrt(2)) > false_cues else (lo, mid)
    return hi


def fit(docs: DataFrame, labels: DataFrame, fit_rows: int = 40_000, prior: float = 0.05, shrink: float = 0.0, false_cues: float = 1e-4) -> ToxicModel:
    """Learn from at most `fit_rows` labelled rows that are not held out."""
    spark = docs.sparkSession
    ship_package(spark)
    marks = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max(F.col("toxic").cast("int")).alias("label"))
    picked = marks.orderBy(F.xxhash64("doc_id"), "doc_id").limit(fit_rows)
    known = materialise(picked, "fit-ids")  # fit_rows rows of two numbers: what is broadcast has that bound
    rows = materialise(id_and_text(docs).join(F.broadcast(known), "doc_id").where(F.length("text") > 0).groupBy("text").agg(F.max("label").alias("label")), "fit-rows")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict[str, list[int]] = {}

        def note(names: list[str], row: np.ndarray, name: np.ndarray, y: np.ndarray) -> None:
            """Rows of each label that hold each cue."""
            with_0, with_1 = (np.bincount(name[y[row] == v], minlength=len(names)).tolist() for v in (0, 1))
            for w, a, b in zip(names, with_0, with_1):
                t = totals.get(w)
                if t is None:
                    totals[w] = [a, b]
                else:
                    t[0] += a
                    t[1] += b

        def flush():
            words = list(totals)
            table = np.array([totals[w] for w in words], np.int64).reshape(-1, 2)
            totals.clear()
            return pa.RecordBatch.from_pydict({"word": words} | {c: table[:, i] for i, c in enumerate(("d0", "d1"))})

        for batch in batches:
            label = batch.column(1).to_numpy()
            at = 0
            for codes, words, sizes in word_lists(batch.column(0)):
                y = label[at : at + len(sizes)]
                at += len(sizes)
                owner = np.repeat(np.arange(len(sizes)), sizes)
                once = np.unique(owner * len(words) + codes) if len(codes) else np.zeros(0, np.int64)
                row, word = once // max(1, len(words)), once % max(1, len(words))
                note(words, row, word, y)
                for k in PREFIXES:
                    names: dict[str, int] = {}
                    to = np.array([names.setdefault(w[:k] + "*", len(names)) if len(w) > k else -1 for w in words] or [-1])
                    begun = to[word]
                    pair = np.unique(row[begun >= 0] * max(1, len(names)) + begun[begun >= 0])
                    note(list(names), pair // max(1, len(names)), pair % max(1, len(names)), y)
                if len(totals) > 100_000:
                    yield flush()
        if totals:
            yield flush()

    counted = rows.select("text", "label").mapInArrow(count, "word string, d0 long, d1 long")
    words = materialise(counted.groupBy("word").agg(F.sum("d0").alias("d0"), F.sum("d1").alias("d1")), "fit-words")
    sizes = {r.label: r.n for r in rows.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    r0, r1 = sizes.get(0, 0), sizes.get(1, 0)
    if not r0 or not r1:
        return ToxicModel()

    # log-odds of a row holding the word; the prior is the pooled rate, worth `prior` rows for each fitted one
    rate, extra = r1 / (r0 + r1), prior * (r0 + r1)

    def says(d1, d0):
        """(log-odds, label 1 against 0, less `shrink` deviations; signed root of the likelihood ratio against equal rates)"""
        d = d1 + d0
        a = F.lit(prior) * d + 1e-3
        odds = lambda y, n: F.log((y + a) / (F.lit(n + extra) - y - a + 1))
        part = lambda y, p: F.when(y > 0, y * F.log(y / (d * p))).otherwise(0.0)
        root = F.sqrt(F.greatest(2 * (part(d1, rate) + part(d0, 1 - rate)), F.lit(0.0)))
        delta = odds(d1, r1) - odds(d0, r0) - shrink * F.sqrt(1 / (d1 + a) + 1 / (d0 + a))
        return F.round(delta, 2), F.when(d1 > d * rate, root).otherwise(0.0)

    d1, d0 = F.col("d1"), F.col("d0")
    # what a word says, and what it would say without one of its rows of either label: a fitted row is weighed without itself
    cases = {"all": says(d1, d0), "less1": says(d1 - 1, d0), "less0": says(d1, F.greatest(d0 - 1, F.lit(0)))}
    rooted = words.select("word", "d1", *(x.alias(f"{name}_{part}") for name, both in cases.items() for part, x in zip(("says", "root"), both)))
    least = least_root(words.count(), false_cues)
    kept = lambda name: F.when((F.col(f"{name}_root") >= least) & (F.col("d1") >= F.lit(2 if name == "less1" else 1)), F.greatest(F.col(f"{name}_says"), F.lit(0.01))).otherwise(0.0)
    counts = rooted.select("word", *(kept(name).alias(name) for name in cases))
    # words of the fitted rows: the list is bounded by the sample, not the corpus
    speaking = counts.where("all > 0 OR less0 > 0").collect()
    if not speaking:
        return ToxicModel()
    of = lambda name: {r.word: float(r[name]) for r in speaking if r[name] > 0}
    model = ToxicModel(of("all"))
    listed = spark.sparkContext.broadcast(model)

    def tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Words of each label by the score they get."""
        counts: Counter = Counter()
        for batch in batches:
            label, at = batch.column(1).to_numpy(), 0
            for codes, words, sizes in word_lists(batch.column(0)):
                y = np.repeat(label[at : at + len(sizes)], sizes)
                at += len(sizes)
                of = np.array([listed.value.word_score(w) for w in words] or [0.0])
                values, place = np.unique(of, return_inverse=True)
                for v in (0, 1):
                    for x, n in zip(values.tolist(), np.bincount(place[codes[y == v]], minlength=len(values)).tolist()):
                        counts[x, v] += n
        yield pa.RecordBatch.from_pydict({"score": [x for x, _ in counts], "label": pa.array([v for _, v in counts], pa.int32()), "n": list(counts.values())}, schema=pa.schema([("score", pa.float64()), ("label", pa.int32()), ("n", pa.int64())]))

    seen: dict[float, list[float]] = {0.0: [0.5, 0.5]} | {x: [0.5, 0.5] for x in model.scores.values()}
    for r in rows.select("text", "label").mapInArrow(tally, "score double, label int, n long").groupBy("score", "label").agg(F.sum("n").alias("n")).collect():
        seen[r.score][r.label] += r.n
    n0, n1 = (sum(x[v] for x in seen.values()) for v in (0, 1))
    other0, other1 = seen.pop(0.0)
    model.other = min(math.log(other1 / n1) - math.log(other0 / n0), -1e-4)
    p = np.array([x[0] / n0 for x in seen.values()] + [other0 / n0])
    s = np.array([*seen, model.other])
    # the law needs a background that falls on average; other words take up what the cues give it
    if (p * s).sum() >= 0:
        model.other = s[-1] = -2 * float((p[:-1] * s[:-1]).sum()) / float(p[-1])
    model.lam = solve_lambda(p, s)
    model.k = fit_k(p, s, model.lam)
    shared = spark.sparkContext.broadcast([replace(model, scores=of("less0")), replace(model, scores=of("less1"))])

    def weigh(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for y, without in enumerate(shared.value):
                some = batch.filter(pc.equal(batch.column(1), y))
                if some.num_rows:
                    yield pa.RecordBatch.from_pydict({"label": some.column(1), "bin": np.ceil(scan(without, some.column(0))[0] * 4).clip(max=4000).astype(np.int32)})

    bins = rows.select("text", "label").mapInArrow(weigh, "label int, bin int").groupBy("bin").agg(F.sum("label").alias("a"), F.count(F.lit(1)).alias("b")).orderBy("bin").collect()
    x = np.array([r.bin / 4 for r in bins])
    model.edges = x
    model.levels = isotonic(x, np.array([float(r.a) for r in bins]), np.array([float(r.b) for r in bins]))
    return model


def scan(model: ToxicModel, texts: pa.Array) -> tuple[np.ndarray, list[list[tuple[float, int, int]]], np.ndarray]:
    """Evidence, segments and number of words of each text."""
    evidence, segments, lengths = [], [], []
    for codes, words, sizes in word_lists(texts):
        of = np.array([model.word_score(w) for w in words] or [0.0])
        value = of[codes] if len(codes) else np.zeros(0)
        hits = np.flatnonzero(value)
        ends = np.cumsum(sizes)
        lo = np.searchsorted(hits, ends - sizes)
        hi = np.searchsorted(hits, ends)
        for a, b, end, n in zip(lo.tolist(), hi.tolist(), ends.tolist(), sizes.tolist()):
            if a == b:
                evidence.append(0.0)
                segments.append([])
            else:
                found = maximal_segments(model.items(hits[a:b] - (end - n), value[hits[a:b]], n))
                evidence.append(model.evidence(found, n))
                segments.append(found)
            lengths.append(n)
    return np.array(evidence), segments, np.array(lengths)


def score(docs: DataFrame, model: ToxicModel, threshold: float = THRESHOLD, most_e: float = 0.01) -> DataFrame:
    """doc_id, score, predicted, evidence and number of significant segments of every document; one narrow pass."""
    spark = docs.sparkSession
    ship_package(spark)
    shared = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            evidence, segments, n = scan(model, batch.column(1))
            p = model.probability(evidence)
            yield pa.RecordBatch.from_pydict({
                "doc_id": batch.column(0), "score": p, "predicted": (p >= threshold).astype(np.int32), "evidence": evidence,
                "n_segments": np.array([sum(model.e_value(s, m) <= most_e for s, _, _ in found) for found, m in zip(segments, n.tolist())], np.int32),
            })

    return id_and_text(docs).mapInArrow(run, SCORE_SCHEMA)


def toxic_segments(docs: DataFrame, model: ToxicModel, most_e: float = 0.01) -> DataFrame:
    """Every significant passage: code point span, score, E-value and text."""
    spark = docs.sparkSession
    ship_package(spark)
    shared = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            _, segments, n = scan(model, batch.column(1))
            out = {c: [] for c in ("doc_id", "start", "end", "segment_score", "e_value", "passage")}
            for k, found in enumerate(segments):
                found = [x for x in found if model.e_value(x[0], int(n[k])) <= most_e]
                if found:
                    text = batch.column(1)[k].as_py()
                    spans = [m.span() for m in WORDS.finditer(text)]
                    for s, first, last in found:
                        a, b = spans[first][0], spans[last][1]
                        for c, v in zip(out, (batch.column(0)[k].as_py(), a, b, s, model.e_value(s, int(n[k])), text[a:b])):
                            out[c].append(v)
            yield pa.RecordBatch.from_pydict(out, schema=pa.schema([("doc_id", pa.int64()), ("start", pa.int32()), ("end", pa.int32()), ("segment_score", pa.float64()), ("e_value", pa.float64()), ("passage", pa.string())]))

    return id_and_text(docs).mapInArrow(run, SEGMENT_SCHEMA)


def keep_clean(docs: DataFrame, model: ToxicModel, threshold: float = THRESHOLD, text_col: str = "text") -> DataFrame:
    """The rows whose score is below the threshold, with all their columns; one narrow pass."""
    spark = docs.sparkSession
    ship_package(spark)
    shared = spark.sparkContext.broadcast(model)
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            evidence, _, _ = scan(shared.value, batch.column(at))
            yield batch.filter(pa.array(shared.value.probability(evidence) < threshold))

    return docs.mapInArrow(run, docs.schema)
