"""Language identification by prediction by partial matching.

One byte-context tree per language holds, for each context of up to three bytes, which bytes
followed it and how often. The escape probability of a context is d / (n + d) for d different
followers in n visits (method C), a known follower's probability is its count over n + d, and after
the empty context every byte has probability 1/256. The statistics are frozen once learned, so the
code length of a byte depends on four bytes only and is exact; a text's code length is their sum,
and the language with the shortest code is predicted.

A tree is learned from a bounded, documented sample: at most ``docs_per_lang`` documents for each
language, those with the smallest hash of their id, and those of at most ``longest`` bytes before longer
ones, of which only ``longest`` characters are learned.

Defined results: null text, or text with no letter, is ``und`` with score 0; rows without a language
are scored but not learned from; with nothing to learn from, all is ``und``; ties go to the language
first in order; repeated rows are scored each, and learned once; a very long text is scored whole, as one
buffer; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import column, light_batches, text_slices, tidy

ORDER = 3
#: Texts are set apart by so many newlines that each begins in the same context.
GAP = b"\n" * ORDER
LETTER = np.zeros(256, bool)
LETTER[[*range(65, 91), *range(97, 123)]] = True


class ContextTree:
    """Follower counts of the contexts of 0 to ORDER bytes, as sorted arrays."""

    def __init__(self, texts: list[bytes]):
        data = np.frombuffer(GAP + GAP.join(texts) + GAP, np.uint8).astype(np.uint32)
        code = np.zeros(len(data), np.uint32)
        self.levels = []
        for order in range(ORDER + 1):
            code = code[1:] if order else code
            code = (data[: len(data) - order] << np.uint32(8 * order)) | code if order else data.copy()
            grams, n = np.unique(code, return_counts=True)
            contexts, first = np.unique(grams >> np.uint32(8), return_index=True)
            kinds = np.diff(np.append(first, len(grams)))
            visits = np.add.reduceat(n, first)
            self.levels.append((grams, n.astype(np.float64), contexts, (visits + kinds).astype(np.float64), kinds.astype(np.float64)))

    def bits(self, quads: np.ndarray) -> np.ndarray:
        """Code length of the last byte of each quad after the three before it."""
        out = np.zeros(len(quads))
        open_ = np.ones(len(quads), bool)
        for order in range(ORDER, -1, -1):
            grams, n, contexts, total, kinds = self.levels[order]
            gram = quads & np.uint32((1 << (8 * (order + 1))) - 1) if order < ORDER else quads
            at = np.minimum(np.searchsorted(contexts, gram >> np.uint32(8)), len(contexts) - 1)
            met = open_ & (contexts[at] == gram >> np.uint32(8))
            g = np.minimum(np.searchsorted(grams, gram), len(grams) - 1)
            hit = met & (grams[g] == gram)
            out[hit] -= np.log2(n[g[hit]] / total[at[hit]])
            miss = met & ~hit
            out[miss] -= np.log2(kinds[at[miss]] / total[at[miss]])
            open_ &= ~hit
        out[open_] += 8
        return out


class CodeLengths:
    """Bits of each text under each tree; quads already met are looked up in a direct-mapped table."""

    SLOTS = 20

    def __init__(self, trees: list[ContextTree]):
        self.trees = trees
        self.tag = np.zeros(1 << self.SLOTS, np.uint32)
        self.tag[0] = 1
        self.cost = np.zeros((1 << self.SLOTS, len(trees)), np.float32)

    def __call__(self, buffer: bytes, starts: np.ndarray) -> np.ndarray:
        data = np.frombuffer(GAP + buffer, np.uint8)
        a = data.astype(np.uint32)
        quads = a[3:] | (a[2:-1] << np.uint32(8)) | (a[1:-2] << np.uint32(16)) | (a[:-3] << np.uint32(24))
        slot = (quads * np.uint32(2654435761)) >> np.uint32(32 - self.SLOTS)
        missing = np.flatnonzero(self.tag[slot] != quads)
        if len(missing):
            fresh = np.unique(quads[missing])
            at = (fresh * np.uint32(2654435761)) >> np.uint32(32 - self.SLOTS)
            empty = self.tag[at] == 0  # nothing is evicted: quads of this run may have been found there
            fresh, at = fresh[empty], at[empty]
            self.tag[at] = fresh  # where two share a slot, one of them stays and the others are computed below
            kept = self.tag[at] == fresh
            self.cost[at[kept]] = np.stack([t.bits(fresh[kept]) for t in self.trees], 1)
            missing = missing[self.tag[slot[missing]] != quads[missing]]
        cost = self.cost[slot]
        if len(missing):
            cost[missing] = np.stack([t.bits(quads[missing]) for t in self.trees], 1)
        return np.add.reduceat(cost, starts[:-1], axis=0, dtype=np.float64)


def learn(docs: DataFrame, train, docs_per_lang: int = 200, longest: int = 20_000) -> dict[str, ContextTree]:
    """A tree for each language of the rows where ``train`` holds; collects the bounded sample named above."""
    rows = docs.where(train & F.col("lang").isNotNull() & (F.octet_length("text") > 0))
    by_hash = Window.partitionBy("lang").orderBy("long", F.xxhash64("doc_id"), "doc_id")
    chosen = rows.select("doc_id", "lang", (F.octet_length("text") > longest).alias("long")).withColumn("rank", F.row_number().over(by_hash)).where(F.col("rank") <= docs_per_lang)
    chosen = chosen.select("doc_id", F.col("lang").alias("chosen_lang")).distinct()
    sample = rows.join(F.broadcast(chosen), (rows["doc_id"] == chosen["doc_id"]) & (F.col("lang") == F.col("chosen_lang"))).select("lang", F.substring("text", 1, longest).alias("text")).distinct()
    found: dict[str, list[bytes]] = {}
    for r in sample.toLocalIterator():
        found.setdefault(r["lang"], []).append(r["text"].encode())
    return {lang: ContextTree(sorted(found[lang])) for lang in sorted(found)}


def _predict(batches: Iterator[pa.RecordBatch], names: list[str], trees: list[ContextTree]) -> Iterator[pa.RecordBatch]:
    lengths = CodeLengths(trees) if trees else None
    for batch in light_batches(batches):
        texts = column(batch, "text")
        lang, score = [], []
        for first, rows, buffer, starts in text_slices(texts, GAP):
            letters = np.add.reduceat(LETTER[np.frombuffer(buffer, np.uint8)], starts[:-1], dtype=np.int64) > 0
            for i in np.flatnonzero(~letters).tolist():
                letters[i] = any(c.isalpha() for c in (texts[first + i].as_py() or ""))
            if lengths is None:
                lang += ["und"] * rows
                score += [0.0] * rows
                continue
            bits = lengths(buffer, starts)
            best = np.argmin(bits, 1)
            odds = np.exp2(np.maximum(bits.min(1, keepdims=True) - bits, -1000)).sum(1)
            lang += [names[b] if ok else "und" for b, ok in zip(best.tolist(), letters.tolist(), strict=True)]
            score += np.where(letters, 1 / odds, 0.0).tolist()
        keep = [c for c in batch.schema.names if c != "text"]
        yield pa.RecordBatch.from_arrays([*[column(batch, c) for c in keep], pa.array(lang, pa.string()), pa.array(score, pa.float64())], names=[*keep, "lang_pred", "score"])


def identify(docs: DataFrame, trees: dict[str, ContextTree], key: str = "doc_id") -> DataFrame:
    """key, lang_pred (string) and score (the posterior of the predicted language) for every row."""
    names = list(trees)
    shared = docs.sparkSession.sparkContext.broadcast([trees[n] for n in names])  # bounded by the sample
    kind = docs.schema[key].dataType.simpleString()

    @tidy
    def predict(batches):
        return _predict(batches, names, shared.value)

    return docs.select(key, "text").mapInArrow(predict, f"`{key}` {kind}, lang_pred string, score double")
