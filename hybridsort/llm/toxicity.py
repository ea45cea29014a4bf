"""Toxicity scores from a lexicon with misspellings and the context of each hit.

The lexicon is learned from labelled rows: whole words and word stems whose documents are nearly
all toxic. Its trie is intersected with the Levenshtein automaton of distance one, and the product
is made deterministic, so one table walk tells whether a word is a term, begins with a stem, or is
a misspelled term. A word is walked only until the product automaton dies, which for most words is
after a few bytes, and all words of a buffer are walked together.

A digit or masking sign between letters belongs to the word, so that it is one edit. A large lexicon is cut into
blocks of BLOCK terms with an automaton each.

Hits are then weighed by their context window: a hit between quotation marks counts apart from one
that is not, and hits that crowd in a window count as a burst. A logistic model of these counts,
fitted to the same labelled rows, gives the score.

Defined results: null or empty text has no hits and gets the score of a text without hits; labels
that are null are not learned from; an id that is labelled both ways is toxic; without toxic training
rows the lexicon is empty and every score is 0; repeated rows are scored each; an empty table gives no
rows; a very long text is scored whole; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from .common import column, light_batches, text_slices, tidy

WORD_BYTE = np.zeros(256, bool)
WORD_BYTE[[*range(97, 123), 39, *range(128, 256)]] = True
#: What may stand for a letter inside a word.
MASK = np.zeros(256, bool)
MASK[list(b"0123456789*@$!#_+")] = True
#: Double quotation marks in UTF-8: straight, English, German low, French.
QUOTES = (b'"', b"\xe2\x80\x9c", b"\xe2\x80\x9d", b"\xe2\x80\x9e", b"\xc2\xab", b"\xc2\xbb")
NONE, EXACT, FUZZY = 0, 1, 2
#: Stems are learned from this length (bytes) to the last.
STEM, LONGEST_STEM = 4, 10
#: Least bytes of a whole word, and terms of an automaton at most.
WORD, BLOCK = 2, 150
FEATURES = 7


@dataclass
class Lexicon:
    words: list[bytes]
    stems: list[bytes]


class Automaton:
    """Deterministic product of the terms' trie and the distance-one automaton; dead state 0, start 1.

    Words of at least ``fuzzy_from`` bytes also match at one insertion, deletion or substitution.
    """

    def __init__(self, lexicon: Lexicon, fuzzy_from: int = 5):
        children: list[dict[int, int]] = [{}]
        exact, stem, fuzzy = set(), set(), set()
        deep = [0]  # longest word of at least fuzzy_from bytes below the node
        for term, is_stem in [(w, False) for w in lexicon.words] + [(s, True) for s in lexicon.stems]:
            node = 0
            path = [0]
            for b in term:
                if b not in children[node]:
                    children[node][b] = len(children)
                    children.append({})
                    deep.append(0)
                node = children[node][b]
                path.append(node)
            (stem if is_stem else exact).add(node)
            if not is_stem and len(term) >= fuzzy_from:
                fuzzy.add(node)
                for n in path:
                    deep[n] = 1
        self.alphabet = sorted({b for c in children for b in c})
        symbol = np.zeros(256, np.int32)  # 0: a byte of no term
        for k, b in enumerate(self.alphabet):
            symbol[b] = k + 1
        accepted = "stem"

        def closure(pairs: set) -> frozenset:
            more = set(pairs)
            for n, e in pairs:  # a letter of the term is left out
                if e == 0:
                    more |= {(c, 1) for c in children[n].values() if deep[c]}
            return frozenset(more)

        def step(state: frozenset, b: int | None):
            new = set()
            for n, e in state:
                child = children[n].get(b) if b is not None else None
                if child is not None and (e == 0 or deep[child]):
                    if e == 0 and child in stem:
                        return accepted
                    new.add((child, e))
                if e == 0 and deep[n]:
                    new.add((n, 1))  # a letter more
                    new |= {(c, 1) for k, c in children[n].items() if k != b and deep[c]}  # another letter
            return closure(new)

        states = {frozenset(): 0, closure({(0, 0)}): 1, accepted: 2}
        order = list(states)
        rows = [[0] * (len(self.alphabet) + 1), None, [2] * (len(self.alphabet) + 1)]
        for at in iter(lambda: next((i for i, r in enumerate(rows) if r is None), None), None):
            row = []
            for b in [None, *self.alphabet]:
                to = step(order[at], b)
                if to not in states:
                    states[to] = len(order)
                    order.append(to)
                    rows.append(None)
                row.append(states[to])
            rows[at] = row
        self.next = np.array(rows, np.int32)[:, symbol]
        self.kind = np.array([EXACT if s == accepted or any(e == 0 and n in exact for n, e in s) else FUZZY if any(n in fuzzy for n, _ in s) else NONE for s in order], np.int8)

    def match(self, data: np.ndarray, begins: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Kind of match of each word by this automaton."""
        state = np.ones(len(begins), np.int32)
        live, at = np.arange(len(begins)), begins.copy()
        while len(live):
            now = self.next[state[live], data[at]]
            state[live] = now
            at += 1
            on = (now > 0) & (now != 2) & (at < ends[live])
            live, at = live[on], at[on]
        return self.kind[state]


class Automata:
    """The automata of all blocks of a lexicon; stems and words are dealt in order."""

    def __init__(self, lexicon: Lexicon, block: int = BLOCK):
        terms = [(w, False) for w in lexicon.words] + [(s, True) for s in lexicon.stems]
        parts = [terms[i : i + block] for i in range(0, len(terms), block)]
        self.parts = [Automaton(Lexicon([t for t, stem in p if not stem], [t for t, stem in p if stem])) for p in parts]

    def match(self, data: np.ndarray, begins: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Kind of match of each word: exact if any block has it so."""
        found = np.zeros(len(begins), np.int8)
        for part in self.parts:
            kind = part.match(data, begins, ends)
            found = np.where((found == EXACT) | (kind == NONE), found, kind).astype(np.int8)
        return found


def _words(buffer: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    data = np.frombuffer(buffer, np.uint8)
    letter = WORD_BYTE[data]
    if len(data) > 2:
        inside = MASK[data[1:-1]] & letter[:-2] & letter[2:]
        letter = letter.copy()
        letter[1:-1] |= inside
    edge = np.diff(letter.view(np.int8), prepend=0, append=0)
    return data, np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def _quote_marks(buffer: bytes) -> np.ndarray:
    at = []
    for mark in QUOTES:
        k = buffer.find(mark)
        while k >= 0:
            at.append(k)
            k = buffer.find(mark, k + len(mark))
    return np.array(sorted(at), np.int64)


def features(buffer: bytes, starts: np.ndarray, automaton: Automaton | Automata, window: int = 8) -> np.ndarray:
    """Per text: log counts of plain and quoted exact hits and misspellings, the largest burst, the share of hits, and whether any plain hit is there."""
    n = len(starts) - 1
    out = np.zeros((n, FEATURES))
    data, begins, ends = _words(buffer)
    kind = automaton.match(data, begins, ends)
    hits = np.flatnonzero(kind)
    if not len(hits):
        return out
    row = np.searchsorted(starts, begins[hits], side="right") - 1
    first = np.searchsorted(begins, starts)
    marks = _quote_marks(buffer)
    low = np.maximum(hits - window, first[row])
    high = np.minimum(hits + window, first[row + 1] - 1)
    before = np.searchsorted(marks, begins[hits]) - np.searchsorted(marks, np.maximum(begins[low] - 3, starts[row]))
    after = np.searchsorted(marks, np.minimum(ends[high] + 3, starts[row + 1])) - np.searchsorted(marks, ends[hits])
    quoted = (before > 0) & (after > 0)
    burst = np.searchsorted(hits, high, side="right") - np.searchsorted(hits, low)
    exact = kind[hits] == EXACT
    for k, which in enumerate((exact & ~quoted, exact & quoted, ~exact & ~quoted, ~exact & quoted)):
        out[:, k] = np.log1p(np.bincount(row[which], minlength=n))
    np.maximum.at(out[:, 4], row[~quoted], np.log1p(burst[~quoted]))
    out[:, 5] = np.minimum(1, 20 * np.bincount(row[~quoted], minlength=n) / np.maximum(1, np.diff(first)))
    out[:, 6] = np.bincount(row[exact & ~quoted], minlength=n) > 0
    return out


@dataclass
class Model:
    lexicon: Lexicon
    weights: np.ndarray
    scale: np.ndarray

    def score(self, found: np.ndarray) -> np.ndarray:
        if not len(self.weights):
            return np.zeros(len(found))
        z = (found / self.scale) @ self.weights[1:] + self.weights[0]
        return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 30) -> tuple[np.ndarray, np.ndarray]:
    """Weights (intercept first) and column scales, by Newton steps."""
    scale = np.maximum(x.std(0), 1e-3)
    a = np.hstack([np.ones((len(x), 1)), x / scale])
    w = np.zeros(a.shape[1])
    penalty = np.full(len(w), ridge)
    penalty[0] = 1e-3
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -40, 40)))
        h = (a * (p * (1 - p) + 1e-9)[:, None]).T @ a + np.diag(penalty)
        move = np.linalg.solve(h, a.T @ (y - p) - penalty * w)
        w += move
        if np.abs(move).max() < 1e-6:
            break
    return w, scale


def _term_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Per batch: how many toxic and other documents have each word and each stem."""
    for batch in batches:
        counts: dict[tuple[bytes, bool], list[int]] = {}
        for text, toxic in zip(pc.utf8_lower(column(batch, "text")).to_pylist(), column(batch, "toxic").to_pylist(), strict=True):
            raw = (text or "").encode()
            data, begins, ends = _words(raw)
            words = {raw[a:b] for a, b in zip(begins.tolist(), ends.tolist(), strict=True)}
            terms = {(w, False) for w in words if len(w) >= WORD} | {(w[:k], True) for w in words for k in range(STEM, min(len(w), LONGEST_STEM + 1))}
            for term in terms:
                counts.setdefault(term, [0, 0])[toxic] += 1
        keys = list(counts)
        yield pa.RecordBatch.from_arrays(
            [pa.array([k[0] for k in keys], pa.binary()), pa.array([k[1] for k in keys], pa.bool_()), pa.array([counts[k][0] for k in keys], pa.int64()), pa.array([counts[k][1] for k in keys], pa.int64())],
            names=["term", "is_stem", "others", "toxic"],
        )


def _choose(found: list) -> Lexicon:
    """All terms; stems without those that a shorter one covers."""
    stems: set[bytes] = set()
    for stem in sorted((bytes(r["term"]) for r in found if r["is_stem"]), key=lambda s: (len(s), s)):
        if not any(stem[:k] in stems for k in range(STEM, len(stem))):
            stems.add(stem)
    return Lexicon(sorted(bytes(r["term"]) for r in found if not r["is_stem"]), sorted(stems))


def learn(docs: DataFrame, labels: DataFrame, train: Column, sample_rows: int = 6000, least_docs: int = 5, precision: float = 0.95, stem_kinds: int = 3, false_terms: float = 0.05) -> Model:
    """Fit lexicon and weights to labelled rows where ``train`` holds.

    At most ``sample_rows`` labels of either class are used, those with the smallest hash of their
    id; the lexicon has all terms that qualify there. A term enters if at least ``least_docs`` toxic documents have it
    and they make up ``precision`` of those that do, and if so many are no chance: of the terms that enter,
    a share of ``false_terms`` at most is expected to be there by chance, given all that were looked at. A stem must lead to ``stem_kinds`` times as many
    toxic documents as any one whole word that it begins.
    """
    known = labels.where(train & F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    picked = [known.where(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows) for y in (0, 1)]
    spark = docs.sparkSession
    picked_rows = [r for p in picked for r in p.collect()]
    chosen = spark.createDataFrame([tuple(r) for r in picked_rows], "doc_id long, toxic int")  # bounded by sample_rows
    sample = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id").select("text", "toxic").cache()
    try:
        counts = sample.mapInArrow(_term_counts, "term binary, is_stem boolean, others long, toxic long")
        counts = counts.groupBy("term", "is_stem").agg(F.sum("others").alias("others"), F.sum("toxic").alias("toxic"))
        terms = Observation()
        counts = counts.observe(terms, F.count(F.lit(1)).alias("n"))
        good = counts.where((F.col("toxic") >= least_docs) & (F.col("toxic") >= precision * (F.col("others") + F.col("toxic"))))
        found = good.collect()  # terms of the sample's documents
        share = sum(r["toxic"] for r in picked_rows) / max(1, len(picked_rows))
        lexicon = _choose(_leading(_significant(found, share, terms.get["n"], false_terms), stem_kinds))
        if not lexicon.words and not lexicon.stems:
            return Model(lexicon, np.zeros(0), np.ones(FEATURES))
        automaton = spark.sparkContext.broadcast(Automata(lexicon))

        def measure(batches):
            for batch in batches:
                for first, rows, buffer, starts in text_slices(pc.utf8_lower(column(batch, "text"))):
                    x = features(buffer, starts, automaton.value)
                    yield pa.RecordBatch.from_arrays([pa.array(x.tolist(), pa.list_(pa.float64())), column(batch, "toxic").slice(first, rows)], names=["x", "toxic"])

        measured = sample.mapInArrow(measure, "x array<double>, toxic int").collect()  # bounded by sample_rows
    finally:
        sample.unpersist()
    x = np.array([r["x"] for r in measured])
    y = np.array([r["toxic"] for r in measured], float)
    weights, scale = fit_logistic(x, y)
    return Model(lexicon, weights, scale)


def chance(toxic: int, others: int, share: float) -> float:
    """Probability that of so many documents at least ``toxic`` are toxic if each is with probability ``share``."""
    n = toxic + others
    if share <= 0 or share >= 1:
        return float(share >= 1)
    logs = [math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1) + k * math.log(share) + (n - k) * math.log(1 - share) for k in range(toxic, n + 1)]
    return min(1.0, sum(map(math.exp, logs)))


def _significant(found: list, share: float, looked_at: int, false_terms: float) -> list:
    """The terms up to the last one whose chance is within its share of the expected errors (step-up rule)."""
    ranked = sorted(((chance(r["toxic"], r["others"], share), bytes(r["term"]), r["is_stem"], r) for r in found), key=lambda x: x[:3])
    last = max((i for i, x in enumerate(ranked, 1) if x[0] <= false_terms * i / max(1, looked_at)), default=0)
    return [x[3] for x in ranked[:last]]


def _leading(found: list, stem_kinds: int) -> list:
    """Whole words, and the stems that no single word explains."""
    out = [r for r in found if not r["is_stem"]]
    most: dict[bytes, int] = {}
    for r in out:
        word = bytes(r["term"])
        for k in range(STEM, min(len(word), LONGEST_STEM) + 1):
            most[word[:k]] = max(most.get(word[:k], 0), r["toxic"])
    return out + [r for r in found if r["is_stem"] and r["toxic"] >= stem_kinds * most.get(bytes(r["term"]), 0)]


def score(self, found: np.ndarray) -> np.ndarray:
        if not len(self.weights):
            return np.zeros(len(found))
        z = (found / self.scale) @ self.weights[1:] + self.weights[0]
        return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 30) -> tuple[np.ndarray, np.ndarray]:
    """Weights (intercept first) and column scales, by Newton steps."""
    scale = np.maximum(x.std(0), 1e-3)
    a = np.hstack([np.ones((len(x), 1)), x / scale])
    w = np.zeros(a.shape[1])
    penalty = np.full(len(w), ridge)
    penalty[0] = 1e-3
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -40, 40)))
        h = (a * (p * (1 - p) + 1e-9)[:, None]).T @ a + np.diag(penalty)
        move = np.linalg.solve(h, a.T @ (y - p) - penalty * w)
        w += move
        if np.abs(move).max() < 1e-6:
            break
    return w, scale


def _term_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Per batch: how many toxic and other documents have each word and each stem."""
    for batch in batches:
        counts: dict[tuple[bytes, bool], list[int]] = {}
        for text, toxic in zip(pc.utf8_lower(column(batch, "text")).to_pylist(), column(batch, "toxic").to_pylist(), strict=True):
            raw = (text or "").encode()
            data, begins, ends = _words(raw)
            words = {raw[a:b] for a, b in zip(begins.tolist(), ends.tolist(), strict=True)}
            terms = {(w, False) for w in words if len(w) >= WORD} | {(w[:k], True) for w in words for k in range(STEM, min(len(w), LONGEST_STEM + 1))}
            for term in terms:
                counts.setdefault(term, [0, 0])[toxic] += 1
        keys = list(counts)
        yield pa.RecordBatch.from_arrays(
            [pa.array([k[0] for k in keys], pa.binary()), pa.array([k[1] for k in keys], pa.bool_()), pa.array([counts[k][0] for k in keys], pa.int64()), pa.array([counts[k][1] for k in keys], pa.int64())],
            names=["term", "is_stem", "others", "toxic"],
        )


def _choose(found: list) -> Lexicon:
    """All terms; stems without those that a shorter one covers."""
    stems: set[bytes] = set()
    for stem in sorted((bytes(r["term"]) for r in found if r["is_stem"]), key=lambda s: (len(s), s)):
        if not any(stem[:k] in stems for k in range(STEM, len(stem))):
            stems.add(stem)
    return Lexicon(sorted(bytes(r["term"]) for r in found if not r["is_stem"]), sorted(stems))


def learn(docs: DataFrame, labels: DataFrame, train: Column, sample_rows: int = 6000, least_docs: int = 5, precision: float = 0.95, stem_kinds: int = 3, false_terms: float = 0.05) -> Model:
    """Fit lexicon and weights to labelled rows where ``train`` holds.

    At most ``sample_rows`` labels of either class are used, those with the smallest hash of their
    id; the lexicon has all terms that qualify there. A term enters if at least ``least_docs`` toxic documents have it
    and they make up ``precision`` of those that do, and if so many are no chance: of the terms that enter,
    a share of ``false_terms`` at most is expected to be there by chance, given all that were looked at. A stem must lead to ``stem_kinds`` times as many
    toxic documents as any one whole word that it begins.
    """
    known = labels.where(train & F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    picked = [known.where(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows) for y in (0, 1)]
    spark = docs.sparkSession
    picked_rows = [r for p in picked for r in p.collect()]
    chosen = spark.createDataFrame([tuple(r) for r in picked_rows], "doc_id long, toxic int")  # bounded by sample_rows
    sample = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id").select("text", "toxic").cache()
    try:
        counts = sample.mapInArrow(_term_counts, "term binary, is_stem boolean, others long, toxic long")
        counts = counts.groupBy("term", "is_stem").agg(F.sum("others").alias("others"), F.sum("toxic").alias("toxic"))
        terms = Observation()
        counts = counts.observe(terms, F.count(F.lit(1)).alias("n"))
        good = counts.where((F.col("toxic") >= least_docs) & (F.col("toxic") >= precision * (F.col("others") + F.col("toxic"))))
        found = good.collect()  # terms of the sample's documents
        share = sum(r["toxic"] for r in picked_rows) / max(1, len(picked_rows))
        lexicon = _choose(_leading(_significant(found, share, terms.get["n"], false_terms), stem_kinds))
        if not lexicon.words and not lexicon.stems:
            return Model(lexicon, np.zeros(0), np.ones(FEATURES))
        automaton = spark.sparkContext.broadcast(Automata(lexicon))

        def measure(batches):
            for batch in batches:
                for first, rows, buffer, starts in text_slices(pc.utf8_lower(column(batch, "text"))):
                    x = features(buffer, starts, automaton.value)
                    yield pa.RecordBatch.from_arrays([pa.array(x.tolist(), pa.list_(pa.float64())), column(batch, "toxic").slice(first, rows)], names=["x", "toxic"])

        measured = sample.mapInArrow(measure, "x array<double>, toxic int").collect()  # bounded by sample_rows
    finally:
        sample.unpersist()
    x = np.array([r["x"] for r in measured])
    y = np.array([r["toxic"] for r in measured], float)
    weights, scale = fit_logistic(x, y)
    return Model(lexicon, weights, scale)


def chance(toxic: int, others: int, share: float) -> float:
    """Probability that of so many documents at least ``toxic`` are toxic if each is with probability ``share``."""
    n = toxic + others
    if share <= 0 or share >= 1:
        return float(share >= 1)
    logs = [math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1) + k * math.log(share) + (n - k) * math.log(1 - share) for k in range(toxic, n + 1)]
    return min(1.0, sum(map(math.exp, logs)))


def _significant(found: list, share: float, looked_at: int, false_terms: float) -> list:
    """The terms up to the last one whose chance is within its share of the expected errors (step-up rule)."""
    ranked = sorted(((chance(r["toxic"], r["others"], share), bytes(r["term"]), r["is_stem"], r) for r in found), key=lambda x: x[:3])
    last = max((i for i, x in enumerate(ranked, 1) if x[0] <= false_terms * i / max(1, looked_at)), default=0)
    return [x[3] for x in ranked[:last]]


def _leading(found: list, stem_kinds: int) -> list:
    """Whole words, and the stems that no single word explains."""
    words = {bytes(r["term"]): r["toxic"] for r in found if not r["is_stem"]}
    out = [r for r in found if not r["is_stem"]]
    for r in found:
        if r["is_stem"]:
            stem = bytes(r["term"])
            most = max((n for w, n in words.items() if w.startswith(stem)), default=0)
            if r["toxic"] >= stem_kinds * most:
                out.append(r)
    return out


def score(docs: DataFrame, model: Model, key: str = "doc_id") -> DataFrame:
    """key and score (double, 0 to 1) for every row."""
    shared = docs.sparkSession.sparkContext.broadcast((Automata(model.lexicon) if len(model.weights) else None, model))  # bounded by the lexicon
    kind = docs.schema[key].dataType.simpleString()

    @tidy
    def run(batches):
        automaton, fitted = shared.value
        for batch in light_batches(batches):
            found = []
            for _, rows, buffer, starts in text_slices(pc.utf8_lower(column(batch, "text"))):
                found.append(fitted.score(features(buffer, starts, automaton)) if automaton else np.zeros(rows))
            yield pa.RecordBatch.from_arrays([column(batch, key), pa.array(np.concatenate(found) if found else [], pa.float64())], names=[key, "score"])

    return docs.select(key, "text").mapInArrow(run, f"`{key}` {kind}, score double")
