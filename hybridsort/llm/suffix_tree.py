"""Substring dedup of words by prefix-partitioned suffix trees.

Windows are partitioned by variable-length prefix keys: the smallest gram of a window, and the whole
window where that is frequent (see ``repeats``). The strings of the keys that meet in a task make one
suffix tree of bounded size. Its suffixes are split by prefixes of 1, 2, 4 and so on words until each
stands alone; the order so found and the common prefixes of neighbours are the tree, whose internal
nodes are the intervals of neighbours with a longer common prefix than those around them. A leaf whose
parent is as deep as a window, or deeper, is an occurrence of a repeat as long as its parent is deep, and
all words of it go. The left-diverse ones among the deep internal nodes are the maximal repeats.

Defined results: null or empty text has no words and loses none; texts shorter than a window lose
nothing; repeated rows and equal texts lose everything if a window long; rows without an id are
handled like others, told apart by their texts; an empty table gives no rows; other columns may have any
names; a very long text is cut at LONGEST windows into strings that overlap by a window.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import old_names, plain_names, split_words, word_hashes
from .repeats import Kind, remove


class SuffixTree:
    """Generalised suffix tree of sequences of numbers, laid end to end with a number of its own after each.

    ``order`` are the leaves from left to right, as positions; ``common`` is the depth of the lowest node
    above a leaf and the one before it.
    """

    def __init__(self, sequences: list[np.ndarray]):
        kinds = 1 + max((int(s.max()) for s in sequences if len(s)), default=-1)
        self.sizes = np.array([len(s) for s in sequences], np.int64)
        self.starts = np.cumsum(self.sizes + 1) - self.sizes - 1
        text = np.empty(int(self.sizes.sum()) + len(sequences), np.int64)
        for k, (at, s) in enumerate(zip(self.starts.tolist(), sequences, strict=True)):
            text[at : at + len(s)] = s
            text[at + len(s)] = kinds + k
        self.text, n = text, len(text)
        names, size = [np.unique(text, return_inverse=True)[1]], 1  # of the prefixes of 1, 2, 4, ... numbers
        while size <= int(self.sizes.max(initial=0)) and int(names[-1].max(initial=-1)) + 1 < n:
            last = names[-1]
            after = np.zeros(n, np.int64)
            after[:-size] = last[size:] + 1
            names.append(np.unique(last * (n + 1) + after, return_inverse=True)[1])
            size *= 2
        self.order = np.argsort(names[-1], kind="stable")
        self.common = np.zeros(n, np.int64)
        a, b = self.order[:-1], self.order[1:]
        depth = np.zeros(max(0, n - 1), np.int64)
        for k in range(len(names) - 1, -1, -1):
            inside = np.flatnonzero(np.maximum(a, b) + depth + (1 << k) <= n)
            equal = inside[names[k][a[inside] + depth[inside]] == names[k][b[inside] + depth[inside]]]
            depth[equal] += 1 << k
        self.common[1:] = depth

    def parents(self) -> np.ndarray:
        """For each position of the text, the depth of its leaf's parent: the longest prefix that occurs elsewhere too."""
        out = np.empty(len(self.text), np.int64)
        out[self.order] = np.maximum(self.common, np.append(self.common[1:], 0))
        return out

    def nodes(self, least: int) -> Iterator[tuple[int, int, int]]:
        """Depth, first and past leaf of each internal node of at least this depth."""
        open_: list[tuple[int, int]] = []
        for i, depth in enumerate([*self.common.tolist(), 0]):
            first = i - 1
            while open_ and open_[-1][0] > depth:
                high, first = open_.pop()
                yield high, first, i
            if depth >= least and (not open_ or open_[-1][0] < depth):
                open_.append((depth, first))

    def maximal_repeats(self, least: int) -> list[tuple[list[int], list[int]]]:
        """The repeats of at least this length that no number can lengthen to the left or right: their numbers and positions."""
        out = []
        for depth, first, past in self.nodes(least):
            at = np.sort(self.order[first:past])
            before = {-1 - p if p in set(self.starts.tolist()) else int(self.text[p - 1]) for p in at.tolist()}
            if len(before) > 1:
                out.append((self.text[at[0] : at[0] + depth].tolist(), at.tolist()))
        return out


def repeated_windows(payloads: list[bytes], sizes: np.ndarray, many: np.ndarray, length: int) -> np.ndarray:
    """For the windows of all payloads in turn, whether a deep node is above their leaf; ``many`` payloads occur more than once."""
    numbers: dict[bytes, int] = {}
    tree = SuffixTree([np.array([numbers.setdefault(w, len(numbers)) for w in p.split()], np.int64) for p in payloads])
    at = np.repeat(tree.starts - (np.cumsum(sizes) - sizes), sizes) + np.arange(int(sizes.sum()))
    return (tree.parents()[at] >= length) | np.repeat(many, sizes)


def words_kind(length: int, gram: int) -> Kind:
    def units(buffer, starts):
        words, _, first = split_words(buffer, starts)
        return word_hashes(words), first

    def join(parts):
        return b" ".join(w for part in parts for w in part)

    def solve(payloads, sizes, many, docs, starts):
        return repeated_windows(payloads, sizes, many, length)

    return Kind(length, gram, units, bytes.split, b" ".join, join, solve, keep_first=False)


def dedup(docs: DataFrame, length: int = 35, gram: int = 8, carry: list[str] | None = None) -> DataFrame:
    """Per row doc_id, text, n_units (words), n_removed, n_spans and kept_bytes (the words left, one blank between)."""
    return remove(docs, words_kind(length, gram), carry)


def clean(docs: DataFrame, length: int = 35) -> DataFrame:
    """docs with repeated windows taken out of the texts; texts that lose nothing stay as they are, and n_chars follows."""
    docs, old = plain_names(docs)
    others = [c for c in docs.columns if c not in ("doc_id", "text")]
    out = dedup(docs, length, carry=others)
    changed = F.col("n_removed") > 0
    out = out.withColumn("text", F.when(changed, F.col("kept_bytes").cast("string")).otherwise(F.col("text")))
    if "n_chars" in others:
        out = out.withColumn("n_chars", F.when(changed, F.char_length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return old_names(out.select(*[F.col(c).cast(docs.schema[c].dataType).alias(c) for c in docs.columns]), old)
