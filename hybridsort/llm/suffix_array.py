"""Substring dedup of bytes by suffix arrays built with induced sorting.

Segments that may repeat are gathered into shards (see ``repeats``). A shard's suffix array is built
by induced sorting: suffixes are classified as smaller or larger than their successor, the
leftmost-smaller substrings are sorted by one round of induction and named, the string of names is
sorted, and the array is induced from it in one pass up and one down. Both passes work bucket by
bucket on whole arrays. Names have a large alphabet, for which buckets do not pay, so their string is
sorted by rank doubling. The common prefixes of neighbours are computed in text order, up to the window.

Runs of suffixes with a common prefix of a window or more are the occurrences of one string; all
but the earliest go.

Defined results: null or empty text has no bytes; texts shorter than a window lose nothing; of
equal texts the smallest id stays; rows equal in id and text are one occurrence; rows without an id
stand where half of their text's digest would as an id; an empty table gives no rows; other columns may
have any names; a very long text is cut at LONGEST windows into strings that overlap by a window.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from .common import mix
from .repeats import Kind, remove


def by_doubling(x: np.ndarray, depth: int | None = None) -> np.ndarray:
    """Suffix array of any integers, by their first ``depth`` of them if it is given."""
    rank, size = np.unique(x, return_inverse=True)[1].astype(np.int64), 1
    while True:
        after = np.full(len(x), -1, np.int64)
        after[:-size] = rank[size:]
        pairs = rank * (len(x) + 1) + after + 1
        values, rank = np.unique(pairs, return_inverse=True)
        if len(values) == len(x) or size >= len(x) or (depth and 2 * size >= depth):
            return np.argsort(rank, kind="stable")
        size *= 2


def _deal(buckets: list[list], at: np.ndarray, chars: np.ndarray) -> None:
    """Append positions to the buckets of their characters, in order."""
    if not len(at):
        return
    order = np.argsort(chars, kind="stable")
    at, chars = at[order], chars[order]
    edge = np.flatnonzero(np.diff(chars)) + 1
    for part, c in zip(np.split(at, edge), chars[np.concatenate([[0], edge])].tolist(), strict=True):
        buckets[c].append(part)


def _induce(x: np.ndarray, smaller: np.ndarray, seeds: np.ndarray) -> np.ndarray:
    """All suffixes in order, from the leftmost-smaller ones in (at least bucket) order."""
    n = len(x)
    none = np.zeros(0, np.int64)
    large: list[list] = [[] for _ in range(256)]
    small: list[list] = [[] for _ in range(256)]
    seeded: list[list] = [[] for _ in range(256)]
    _deal(seeded, seeds, x[seeds])
    large[x[n - 1]].append(np.array([n - 1]))

    def before(at: np.ndarray, want: bool) -> np.ndarray:
        at = at[at > 0] - 1
        return at[smaller[at] == want]

    def scan(buckets: list[list], c: int, want: bool) -> np.ndarray:
        """A bucket in scanning order; it may grow by itself, wave by wave, while it is read."""
        wave = np.concatenate(buckets[c]) if buckets[c] else none
        waves = [none]
        while len(wave):
            waves.append(wave)
            at = before(wave, want)
            chars = x[at]
            own = chars == c
            _deal(buckets, at[~own], chars[~own])
            wave = at[own]
        return np.concatenate(waves)

    larger = []
    for c in range(256):
        larger.append(scan(large, c, False))
        if seeded[c]:
            at = before(np.concatenate(seeded[c]), False)
            _deal(large, at, x[at])
    out = []
    for c in range(255, -1, -1):
        out.append(scan(small, c, True)[::-1])
        out.append(larger[c])
        at = before(larger[c][::-1], True)
        _deal(small, at, x[at])
    return np.concatenate(out[::-1])


def suffix_array(x: np.ndarray, depth: int | None = None) -> np.ndarray:
    """Suffix array of bytes; a suffix that is a prefix of another comes first.

    With ``depth``, suffixes with so many first bytes in common may stand in any order.
    """
    n = len(x)
    if n < 2:
        return np.arange(n)
    differs = np.flatnonzero(x[1:] != x[:-1])
    following = np.searchsorted(differs, np.arange(n))  # where the run of equal bytes ends
    smaller = np.zeros(n, bool)
    inside = following < len(differs)
    end = differs[following[inside]]
    smaller[inside] = x[end] < x[end + 1]
    seeds = np.flatnonzero(smaller[1:] & ~smaller[:-1]) + 1
    if len(seeds) > 1:
        lead = np.zeros(n, bool)
        lead[seeds] = True
        order = _induce(x, smaller, seeds)
        order = order[lead[order]]
        # A substring reaches to the next seed inclusive; prefix sums of mixed powers tell equal ones.
        past = np.append(seeds[1:], n - 1)
        total = np.concatenate([[np.uint64(0)], np.cumsum((x.astype(np.uint64) + np.uint64(1)) * _powers(n))])
        value = mix((total[past + 1] - total[seeds]) * _powers(n)[n - 1 - seeds]) ^ mix((past - seeds).astype(np.uint64) + np.uint64(77))
        value[-1] = np.uint64(1)  # the last one ends at the end of the text
        place = np.searchsorted(seeds, order)
        ranked = seeds[place]
        same = np.flatnonzero(value[place][1:] == value[place][:-1])
        same = same[_equal(x, ranked[same], ranked[same + 1], past[place][same] + 1 - ranked[same])]
        fresh = np.ones(len(ranked), np.int64)
        fresh[0] = 0
        fresh[same + 1] = 0
        names = np.cumsum(fresh)
        reduced = np.empty(len(seeds), np.int64)
        reduced[place] = names
        seeds = seeds[by_doubling(reduced, depth)] if names[-1] + 1 < len(seeds) else order
    return _induce(x, smaller, seeds)


def _equal(x: np.ndarray, a: np.ndarray, b: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Whether the bytes from a and from b agree for ``size`` bytes each."""
    out, at, k = np.ones(len(a), bool), np.arange(len(a)), 0
    while len(at):
        out[at[x[a[at] + k] != x[b[at] + k]]] = False
        k += 1
        at = at[out[at] & (size[at] > k)]
    return out


_power = np.ones(1, np.uint64)


def _powers(n: int) -> np.ndarray:
    global _power
    if len(_power) < n:
        _power = np.concatenate([[np.uint64(1)], np.cumprod(np.full(2 * n, 0x9E3779B97F4A7C15, np.uint64))])
    return _power[:n]


def permuted_common_prefixes(x: np.ndarray, order: np.ndarray, most: int) -> np.ndarray:
    """For each position, in text order, the bytes that its suffix shares with the one before it in ``order``, ``most`` at most."""
    n = len(x)
    before = np.full(n, n, np.int64)
    before[order[1:]] = order[:-1]
    eight = np.zeros(n + most + 8, np.uint64)
    for k in range(8):
        eight[: max(0, n - k)] |= x[k:].astype(np.uint64) << np.uint64(8 * k)
    left = n - np.maximum(np.arange(n), before)  # what is left of the shorter suffix; nothing for the first
    out = np.zeros(n, np.int64)
    at, k = np.arange(n), 0
    while len(at) and k < most:
        differ = eight[at + k] ^ eight[before[at] + k]
        low = differ & (~differ + np.uint64(1))
        out[at] = k + np.where(differ == 0, 8, np.searchsorted(_LOWEST, low, side="right") - 1)
        at, k = at[differ == 0], k + 8
    return np.minimum(np.minimum(out, left), most)


#: The first bit of each byte of a number.
_LOWEST = np.uint64(1) << (np.uint64(8) * np.arange(8, dtype=np.uint64))


def later_windows(payloads: list[bytes], sizes: np.ndarray, docs: np.ndarray, starts: np.ndarray, length: int) -> np.ndarray:
    """For the windows of all payloads in turn, whether an equal window starts earlier."""
    x = np.frombuffer(b"".join(payloads), np.uint8)
    order = suffix_array(x, length)
    share = permuted_common_prefixes(x, order, length) >= length
    string = np.empty(len(x), np.int64)
    string[order] = np.cumsum(~share[order])
    units = sizes + length - 1
    offset = np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    at = np.repeat(np.cumsum(units) - units, sizes) + offset
    doc, start = np.repeat(docs, sizes), np.repeat(starts, sizes) + offset
    ranked = np.lexsort((start, doc, string[at]))
    own = string[at][ranked]
    later = np.zeros(len(at), bool)
    later[ranked[1:]] = own[1:] == own[:-1]
    return later


def bytes_kind(length: int, gram: int) -> Kind:
    def units(buffer, starts):
        data = np.frombuffer(buffer, np.uint8)
        own = np.ones(len(data), bool)
        own[starts[1:] - 1] = False  # what sets texts apart
        return mix(data[own].astype(np.uint64) + np.uint64(1)), starts - np.arange(len(starts))

    def solve(payloads, sizes, many, docs, starts):
        return later_windows(payloads, sizes, docs, starts, length)

    return Kind(length, gram, units, lambda text: text, bytes, b"".join, solve, keep_first=True)


def dedup(docs: DataFrame, length: int = 100, gram: int = 32, carry: list[str] | None = None) -> DataFrame:
    """Per row doc_id, text, n_units (bytes), n_removed, n_spans and kept_bytes (what is left)."""
    return remove(docs, bytes_kind(length, gram), carry)
