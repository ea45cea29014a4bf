"""Sorting kernels on one task's keys: arrays of n rows and w bytes. Each returns the order of the rows."""

from __future__ import annotations

import numpy as np


def as_bytes(keys: list[str] | np.ndarray, width: int) -> np.ndarray:
    """Hex keys as an array of bytes."""
    return np.frombuffer(bytes.fromhex("".join(keys)), np.uint8).reshape(-1, width)


def comparison_sort(keys: np.ndarray, stable: bool = True) -> np.ndarray:
    """A merge or quick sort of whole keys."""
    if not keys.shape[1]:
        return np.arange(len(keys))
    return np.argsort(_wide(keys), kind="stable" if stable else "quicksort")


def _wide(keys: np.ndarray) -> np.ndarray:
    """Keys that numpy can compare: a zero byte at the end is kept by a mark after it."""
    n, width = keys.shape
    return np.ascontiguousarray(np.hstack([keys, np.ones((n, 1), np.uint8)])).view(f"S{width + 1}").ravel()


def counting_scatter(digit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Stable order of one digit, and the start of each value's bucket (257 of them)."""
    starts = np.concatenate([[0], np.cumsum(np.bincount(digit, minlength=256))])
    return np.argsort(digit, kind="stable"), starts  # a radix pass for bytes


def blocked_scatter(digit: np.ndarray, block: int = 1 << 15) -> tuple[np.ndarray, np.ndarray]:
    """The same, gathering a cache-sized block by destination before it is written out."""
    starts = np.concatenate([[0], np.cumsum(np.bincount(digit, minlength=256))])
    out, at = np.empty(len(digit), np.int64), starts[:-1].copy()
    for low in range(0, len(digit), block):
        part = digit[low : low + block]
        order = np.argsort(part, kind="stable")
        counts = np.bincount(part, minlength=256)
        to = np.repeat(at - (np.cumsum(counts) - counts), counts) + np.arange(len(part))
        out[to] = low + order
        at += counts
    return out, starts


def compare_below(n: int) -> int:
    """Bucket size from which a radix pass pays, for n keys: a pass costs a call for each bucket, a comparison finish one for all of them."""
    return max(4096, n // 64)


def _tail(keys: np.ndarray, rows: np.ndarray, depth: int) -> np.ndarray:
    """Up to eight bytes of the rows' keys from ``depth`` on, as one number in key order."""
    part = keys[rows, depth : depth + 8]
    if part.shape[1] < 8:
        part = np.hstack([part, np.zeros((len(part), 8 - part.shape[1]), np.uint8)])
    return np.ascontiguousarray(part).view(">u8").ravel().astype(np.uint64)


def finish(keys: np.ndarray, order: np.ndarray, edges: np.ndarray, depth: int) -> None:
    """Sort all buckets order[edges[i] : edges[i + 1]] by the bytes from ``depth`` on, together; ties keep the order of the rows.

    A bucket's number and as many bytes as fit beside it are compared as one integer; what ties is looked
    at again, further right.
    """
    width = keys.shape[1]
    bucket = np.repeat(np.arange(len(edges) - 1, dtype=np.uint64), np.diff(edges))
    at = np.arange(edges[0], edges[-1])
    while len(at):
        own = order[at]
        taken = -(-int(bucket[-1]).bit_length() // 8)
        value = (bucket << np.uint64(64 - 8 * taken) if taken else np.uint64(0)) | (_tail(keys, own, depth) >> np.uint64(8 * taken))
        by = np.argsort(value)
        order[at], value = own[by], value[by]
        depth += 8 - taken
        fresh = np.append(True, value[1:] != value[:-1])
        tied = ~(fresh & np.append(fresh[1:], True))
        if not tied.any():
            return
        at, bucket = at[tied], (np.cumsum(fresh[tied]) - 1).astype(np.uint64)
        if depth >= width:
            order[at] = order[at][np.lexsort((order[at], bucket))]
            return


def msd_sort(keys: np.ndarray, compare_limit: int | None = None, scatter=counting_scatter) -> np.ndarray:
    """Most significant digit first, level by level: large buckets get a radix pass each, those below the limit one comparison finish together."""
    n, width = keys.shape
    order = np.arange(n)
    limit = compare_below(n) if compare_limit is None else compare_limit
    buckets, depth = [(0, n)], 0
    while buckets and depth < width:
        small = [(low, high) for low, high in buckets if high - low < limit]
        if small:
            rows = np.concatenate([np.arange(low, high) for low, high in small])
            own, edges = order[rows], np.cumsum([0] + [high - low for low, high in small])
            finish(keys, own, edges, depth)
            order[rows] = own
        deeper = []
        for low, high in buckets:
            if high - low < limit:
                continue
            by, starts = scatter(np.ascontiguousarray(keys[order[low:high], depth]))
            order[low:high] = order[low:high][by]
            sizes = np.diff(starts)
            deeper += [(low + int(starts[b]), low + int(starts[b + 1])) for b in np.flatnonzero(sizes > 1)]
        buckets, depth = deeper, depth + 1
    return order


def lsd_sort(keys: np.ndarray, digits: int = 1) -> np.ndarray:
    """Least significant digit first: a stable pass for each digit (of one or two bytes)."""
    order = np.arange(len(keys))
    at = keys.shape[1]
    while at > 0:
        low = max(0, at - digits)
        part = keys[order, low:at].astype(np.uint16)
        value = part[:, 0] if at - low == 1 else part[:, 0] << np.uint16(8) | part[:, 1]
        order = order[np.argsort(value.astype(np.uint8) if at - low == 1 else value, kind="stable")]
        at = low
    return order


def inplace_sort(keys: np.ndarray, compare_limit: int = 64) -> np.ndarray:
    """Most significant digit first in one array: cycles are followed until every bucket is filled. Not stable."""
    n, width = keys.shape
    order = np.arange(n)
    work = [(0, n, 0)]
    while work:
        low, high, depth = work.pop()
        if high - low < 2 or depth == width:
            continue
        if high - low < compare_limit:
            own = order[low:high]
            order[low:high] = own[comparison_sort(keys[own, depth:])]
            continue
        counts = np.bincount(keys[order[low:high], depth], minlength=256)
        ends = (low + np.cumsum(counts)).tolist()
        heads = (np.array(ends) - counts).tolist()
        starts = list(heads)
        for b in range(256):
            while heads[b] < ends[b]:
                row = order[heads[b]]
                to = int(keys[row, depth])
                while to != b:
                    at = heads[to]
                    heads[to] += 1
                    order[at], row = row, order[at]
                    to = int(keys[row, depth])
                order[heads[b]] = row
                heads[b] += 1
        work += [(starts[b], ends[b], depth + 1) for b in range(256) if ends[b] - starts[b] > 1]
    return order


def kway_merge(runs: list[np.ndarray]) -> np.ndarray:
    """The order of several sorted arrays of keys, laid end to end; equal keys keep the order of the runs.

    Neighbours are merged pair by pair: each key of one is placed in the other by binary search.
    """
    width = max((r.shape[1] for r in runs), default=0)
    at, parts = 0, []
    for r in runs:
        parts.append((_wide(r) if width else np.zeros(len(r), "S1"), np.arange(at, at + len(r))))
        at += len(r)
    while len(parts) > 1:
        merged = []
        for (a, x), (b, y) in zip(parts[::2], parts[1::2], strict=False):
            left = np.arange(len(a)) + np.searchsorted(b, a, side="left")
            right = np.arange(len(b)) + np.searchsorted(a, b, side="right")
            keys, order = np.empty(len(a) + len(b), a.dtype), np.empty(len(a) + len(b), np.int64)
            keys[left], keys[right] = a, b
            order[left], order[right] = x, y
            merged.append((keys, order))
        parts = merged + parts[len(parts) - len(parts) % 2 :]
    return parts[0][1] if parts else np.zeros(0, np.int64)


KERNELS = {
    "msd": msd_sort,
    "msd_blocked": lambda k, limit=None: msd_sort(k, limit, blocked_scatter),
    "lsd": lsd_sort,
    "inplace": inplace_sort,
    "stable": lambda k: comparison_sort(k, True),
    "quick": lambda k: comparison_sort(k, False),
}
