"""Benchmark decontamination with a generalised suffix automaton.

The automaton recognises every word sequence of every benchmark item. A document's words are
streamed through it while the longest match ending at each word is tracked; where it reaches the
window length (or a whole shorter item), the words of the window are hit and the state tells the
items. Only stretches whose every pair of neighbouring words occurs in the benchmark are streamed,
as no window can match elsewhere; they are found for a whole buffer at once.

The automaton is broadcast, so its size is bounded: items are taken in blocks of at most
``block_words`` words, and each block has an automaton and a pass of its own. Between passes the rows
are staged, so that a task holds one automaton at a time.

Defined results: null or empty text has no words and no hits; an item without words has no window;
null items are ignored; repeated rows are judged each; an empty benchmark hits nothing; further
columns are ignored by ``find`` and kept by ``clean``.
"""

from __future__ import annotations

from array import array
from bisect import bisect_left
from collections.abc import Iterator
from itertools import accumulate, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column, light_batches, old_names, plain_names, staged, text_slices, tidy, without

#: ASCII letters (made lower-case), digits and all bytes of other characters stay; the rest parts words.
NORMAL = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
SPANS = "array<struct<first:int,past:int>>"


def normal_words(text: str | None) -> list[bytes]:
    return (text or "").encode().translate(NORMAL).split()


class Automaton:
    """Generalised suffix automaton over the words of items, with what is needed to report windows."""

    def __init__(self, items: list[tuple[int, list[bytes]]], window: int):
        self.window = window
        self.vocabulary: dict[bytes, int] = {}
        rows = [(item, [self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words]) for item, words in items if words]
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length = [-1], [0]
        own: list[set[int]] = [set()]
        self.own = own
        for item, ids in rows:
            last = 0
            for c in ids:
                last = self._extend(last, c)
                own[last].add(item)
        self._spread()
        #: Items shorter than the window: (words, item) at the state that holds the whole item.
        self.short: dict[int, list[tuple[int, int]]] = {}
        for item, ids in rows:
            if len(ids) < window:
                state = 0
                for c in ids:
                    state = self.next[state][c]
                self.short.setdefault(state, []).append((len(ids), item))
        self.least = min((min(len(ids), window) for _, ids in rows), default=window)
        width = len(self.vocabulary) + 1
        self.width = width
        pairs = [a * width + b for _, ids in rows for a, b in zip(ids, ids[1:], strict=False)]
        self.pairs = np.unique(np.array(pairs, np.int64))
        self._pack()

    def _pack(self) -> None:
        """The transitions, links and items as flat arrays: some 25 bytes a state in place of about a thousand."""
        steps = sorted((state * self.width + word, to) for state, following in enumerate(self.next) for word, to in following.items())
        self.codes, self.targets = array("q", (c for c, _ in steps)), array("i", (t for _, t in steps))
        self.link, self.length = array("i", self.link), array("i", self.length)
        self.first_item = array("i", accumulate((len(s) for s in self.items), initial=0))
        self.items = array("q", (x for s in self.items for x in sorted(s)))
        del self.next

    def _step(self, state: int, word: int) -> int:
        """The state after one more word, 0 if there is none."""
        code = state * self.width + word
        at = bisect_left(self.codes, code)
        return self.targets[at] if at < len(self.codes) and self.codes[at] == code else 0

    def _state(self, length: int, link: int, following: dict[int, int]) -> int:
        self.next.append(following)
        self.link.append(link)
        self.length.append(length)
        self.own.append(set())
        return len(self.length) - 1

    def _split(self, at: int, word: int, to: int) -> int:
        """The state for the suffixes of ``to`` that are no longer than ``at`` and the word."""
        if self.length[to] == self.length[at] + 1:
            return to
        copy = self._state(self.length[at] + 1, self.link[to], dict(self.next[to]))
        self.link[to] = copy
        while at >= 0 and self.next[at].get(word) == to:
            self.next[at][word] = copy
            at = self.link[at]
        return copy

    def _extend(self, last: int, word: int) -> int:
        if word in self.next[last]:
            return self._split(last, word, self.next[last][word])
        new = self._state(self.length[last] + 1, 0, {})
        at = last
        while at >= 0 and word not in self.next[at]:
            self.next[at][word] = new
            at = self.link[at]
        if at >= 0:
            self.link[new] = self._split(at, word, self.next[at][word])
        return new

    def _spread(self) -> None:
        """Items of each state whose strings can be a window: its own and those of all states that it is a suffix of."""
        for state in sorted(range(1, len(self.length)), key=lambda s: -self.length[s]):
            up = self.link[state]
            if up > 0 and self.length[up] >= self.window:
                self.own[up] |= self.own[state]
        self.items = [frozenset(s) if n >= self.window else frozenset() for s, n in zip(self.own, self.length, strict=True)]
        del self.own

    def stream(self, ids: list[int]) -> tuple[list[tuple[int, int]], set[int]]:
        """Hit words of a stretch as (first, past) runs in order, and the items that they come from."""
        runs: list[tuple[int, int]] = []
        items: set[int] = set()
        state = matched = 0
        window, step, link, length = self.window, self._step, self.link, self.length

        def hit(first: int, past: int) -> None:
            while runs and runs[-1][1] >= first:
                first = min(first, runs.pop()[0])
            runs.append((first, past))

        for i, word in enumerate(ids):
            to = step(state, word)
            while state and not to:
                state = link[state]
                matched = length[state]
                to = step(state, word)
            state = to
            matched = matched + 1 if state else 0
            if matched >= window:
                at = state
                while length[link[at]] >= window:
                    at = link[at]
                items.update(self.items[self.first_item[at] : self.first_item[at + 1]])
                hit(i + 1 - window, i + 1)
            if self.short:
                at, reach = state, matched
                while at > 0:
                    for words, item in self.short.get(at, ()):
                        if words <= reach:
                            items.add(item)
                            hit(i + 1 - words, i + 1)
                    at = link[at]
                    reach = length[at]
        return runs, items

    def find(self, buffer: bytes, starts: np.ndarray) -> tuple[np.ndarray, dict[int, tuple[list[tuple[int, int]], set[int]]]]:
        """Words of each text, and runs and items of the texts that have any."""
        buffer = buffer.translate(NORMAL)
        space = np.frombuffer(buffer, np.uint8) == 32
        begins = ~space
        begins[1:] &= space[:-1]
        words = buffer.split()
        first = np.searchsorted(np.flatnonzero(begins), starts)
        ids = np.fromiter(map(self.vocabulary.get, words, repeat(0)), np.int64, len(words))
        joined = np.zeros(len(ids) + 1, bool)  # joined[i]: words i - 1 and i are neighbours in some item
        if len(ids) > 1 and len(self.pairs):
            both = np.flatnonzero((ids[1:] > 0) & (ids[:-1] > 0))
            code = ids[both] * self.width + ids[both + 1]
            at = np.minimum(np.searchsorted(self.pairs, code), len(self.pairs) - 1)
            joined[both[self.pairs[at] == code] + 1] = True
        joined[first] = False
        out: dict[int, tuple[list, set]] = {}
        if not len(ids) or not self.vocabulary:
            return np.diff(first), out
        edge = np.flatnonzero(~joined)
        size = np.diff(edge)
        known = (size >= self.least) & (ids[edge[:-1]] > 0)
        for a, n in zip(edge[:-1][known].tolist(), size[known].tolist(), strict=True):
            runs, items = self.stream(ids[a : a + n].tolist())
            if items:
                row = int(np.searchsorted(first, a, side="right")) - 1
                got = out.setdefault(row, ([], set()))
                got[0].extend((x + a - int(first[row]), y + a - int(first[row])) for x, y in runs)
                got[1].update(items)
        return np.diff(first), out


def _blocks(benchmark: DataFrame, block_words: int) -> Iterator[list[tuple[int, list[bytes]]]]:
    block, size = [], 0
    for r in benchmark.select("item_id", "text").where("text is not null and item_id is not null").orderBy("item_id").toLocalIterator():
        words = normal_words(r["text"])
        if block and size + len(words) > block_words:
            yield block
            block, size = [], 0
        block.append((r["item_id"], words))
        size += len(words)
    yield block


def _merged(runs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(runs):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def _finding(shared, covered: float | None = None):
    """The pass of one block. With ``covered`` it is the last one, drops documents whose hit words exceed that share, and cuts the texts of the others."""

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automaton = shared.value
        for batch in light_batches(batches):
            old_spans, old_items = column(batch, "hit_spans").to_pylist(), column(batch, "hit_items").to_pylist()
            n_words: list[int] = []
            for first, rows, buffer, starts in text_slices(column(batch, "text")):
                counts, found = automaton.find(buffer, starts)
                n_words += counts.tolist()
                for row, (runs, items) in found.items():
                    old = [(s["first"], s["past"]) for s in old_spans[first + row]]
                    old_spans[first + row] = [{"first": a, "past": b} for a, b in _merged(old + runs)]
                    old_items[first + row] = sorted(items.union(old_items[first + row]))
            new = {"hit_spans": old_spans, "hit_items": old_items, "n_words": n_words}
            if covered is not None and any(old_spans):
                texts = column(batch, "text")
                new["text"] = [_cut(t.as_py(), s) if s else t.as_py() for t, s in zip(texts, old_spans, strict=True)]
            out = pa.RecordBatch.from_arrays([pa.array(new[f.name], f.type) if f.name in new else column(batch, f.name) for f in batch.schema], schema=batch.schema)
            if covered is not None:
                hit = [sum(s["past"] - s["first"] for s in spans) for spans in old_spans]
                out = out.filter(pa.array([not n or h <= covered * n for h, n in zip(hit, n_words, strict=True)], pa.bool_()))
            yield out

    return run


def _passes(docs: DataFrame, benchmark: DataFrame, window: int, block_words: int, covered: float | None = None) -> DataFrame:
    docs = without(docs, "n_words", "hit_spans", "hit_items")
    out = docs.withColumns({"n_words": F.lit(0).cast("long"), "hit_spans": F.array().cast(SPANS), "hit_items": F.array().cast("array<long>")})
    blocks = _blocks(benchmark, block_words)
    block = next(blocks)
    while block is not None:
        after = next(blocks, None)
        shared = docs.sparkSession.sparkContext.broadcast(Automaton(block, window))  # bounded by block_words
        out = out.mapInArrow(_finding(shared, covered if after is None else None), out.schema)
        if after is not None:  # a task never holds two automata
            out = staged(out, "decontaminated")
        block = after
    return out


def find(docs: DataFrame, benchmark: DataFrame, window: int = 10, block_words: int = 250_000) -> DataFrame:
    """docs with n_words (long), hit_spans (word ranges, disjoint, in order) and hit_items (item ids, sorted)."""
    return _passes(docs, benchmark, window, block_words)


def _cut(text: str, spans: list) -> str:
    """text without the hit words and what stands between them."""
    raw = text.encode()
    plain = raw.translate(NORMAL)
    space = np.frombuffer(plain, np.uint8) == 32
    edge = np.diff((~space).view(np.int8), prepend=0, append=0)
    begins, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    keep, at = [], 0
    for s in spans:
        keep.append(raw[at : begins[s["first"]]])
        at = int(ends[s["past"] - 1])
    return b"".join([*keep, raw[at:]]).decode()


def clean(docs: DataFrame, benchmark: DataFrame, window: int = 10, longest_coverage: float = 0.5, block_words: int = 250_000) -> DataFrame:
    """docs with hit spans cut out of the text; a document whose hit words exceed the coverage limit is dropped.

    ``n_chars``, if it is a column, follows the text.
    """
    docs, old = plain_names(docs)
    names = docs.columns
    out = _passes(docs, benchmark, window, block_words, longest_coverage)
    if "n_chars" in names:
        out = out.withColumn("n_chars", F.when(F.size("hit_spans") > 0, F.char_length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return old_names(out.select(*names), old)
