"""Accumulators: each takes the (column, value) pairs of one chunk and returns its merged pairs in column order.

Besides the single-chunk forms there are forms over many chunks at once (``*_many``), which the chunk kernel uses: ``seg`` numbers the
chunk of every pair, chunks do not fall.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass
from typing import Protocol

import numpy as np

from sparsetier.functions.params import StorageModel

#: Elements from which on a dense buffer beats sorting, and the size at which sorting is fastest.
THRESHOLD, PACK_TARGET = 256, 32


def _first_of_runs(*keys) -> np.ndarray:
    if not len(keys[0]):
        return np.zeros(0, dtype=np.int64)
    change = np.zeros(len(keys[0]), dtype=bool)
    change[0] = True
    for k in keys:
        change[1:] |= k[1:] != k[:-1]
    return np.flatnonzero(change)


def compress(a: np.ndarray, b: np.ndarray, p: np.ndarray):
    """Merge neighbours of equal (a, b)."""
    at = _first_of_runs(a, b)
    return a[at], b[at], np.add.reduceat(p, at) if len(at) else p


def sort_many(seg: np.ndarray, cols: np.ndarray, p: np.ndarray):
    """One sort by (chunk, column), then equal neighbours are merged."""
    if not len(cols):
        return seg, cols, p
    low, width = cols.min(), int(cols.max() - cols.min()) + 1
    first = seg.min()
    if (int(seg.max() - first) + 1) * width < 1 << 62:
        order = np.argsort((seg - first) * width + (cols - low))
    else:
        order = np.lexsort((cols, seg))
    return compress(seg[order], cols[order], p[order])


class DenseBuffer:
    """Value buffer and bit map that outlive a chunk; only touched slots are reset."""

    def __init__(self, dtype):
        self.values, self.seen = np.zeros(0, dtype=dtype), np.zeros(0, dtype=bool)

    def merge(self, slots: np.ndarray, p: np.ndarray, width: int):
        if width > len(self.values):
            self.values, self.seen = np.zeros(width, dtype=self.values.dtype), np.zeros(width, dtype=bool)
        np.add.at(self.values, slots, p)
        self.seen[slots] = True
        touched = np.flatnonzero(self.seen[:width]) if width < 16 * len(slots) else np.unique(slots)
        out = self.values[touched].copy()
        self.values[touched] = 0
        self.seen[touched] = False
        return touched, out


def dense_many(seg: np.ndarray, cols: np.ndarray, p: np.ndarray, buffer: DenseBuffer, slots: int = 1 << 20):
    """Every chunk gets its span of one buffer; as many chunks at a time as fit ``slots``, a wider one alone."""
    if not len(cols):
        return seg, cols, p
    at = _first_of_runs(seg)
    low, high = np.minimum.reduceat(cols, at), np.maximum.reduceat(cols, at)
    span = high - low + 1
    ends = np.append(at[1:], len(seg))
    out, n = [], 0
    total = np.cumsum(span)
    while n < len(at):
        stop = max(n + 1, int(np.searchsorted(total, (total[n - 1] if n else 0) + slots, side="right")))
        base = total[n:stop] - span[n:stop] - (total[n - 1] if n else 0)
        s = slice(at[n], ends[stop - 1])
        chunk = np.repeat(np.arange(stop - n), ends[n:stop] - at[n:stop])
        touched, sums = buffer.merge(cols[s] - low[n:stop][chunk] + base[chunk], p[s], int(total[stop - 1] - (total[n - 1] if n else 0)))
        own = np.searchsorted(base, touched, side="right") - 1
        out.append((seg[at[n:stop]][own], touched - base[own] + low[n:stop][own], sums))
        n = stop
    return tuple(np.concatenate(x) for x in zip(*out))


def accumulate_dense(cols: np.ndarray, vals: np.ndarray, width: int):
    return DenseBuffer(vals.dtype).merge(cols, vals, width)


def accumulate_sort(cols: np.ndarray, vals: np.ndarray, width: int = 0):
    return sort_many(np.zeros(len(cols), dtype=np.int64), cols, vals)[1:]


def accumulate_hash(cols: np.ndarray, vals: np.ndarray, width: int = 0):
    table: dict[int, float] = {}
    for c, v in zip(cols.tolist(), vals.tolist()):
        table[c] = table.get(c, 0) + v
    keys = sorted(table)
    return np.array(keys, dtype=np.int64), np.array([table[k] for k in keys], dtype=vals.dtype)


def accumulate_heap(runs: list[tuple[np.ndarray, np.ndarray]]):
    """Merge of sorted runs (the scaled rows of B)."""
    cols, vals = [], []
    for c, v in heapq.merge(*(zip(c.tolist(), v.tolist()) for c, v in runs), key=lambda x: x[0]):
        if cols and cols[-1] == c:
            vals[-1] += v
        else:
            cols.append(c)
            vals.append(v)
    return np.array(cols, dtype=np.int64), np.array(vals)


def accumulate_symbolic(cols: np.ndarray, width: int) -> int:
    """Number of distinct columns by a bit map alone."""
    seen = np.zeros(width, dtype=bool)
    seen[cols] = True
    return int(seen.sum())


def accumulate_hybrid(cols: np.ndarray, vals: np.ndarray, width: int, threshold: int = THRESHOLD):
    return accumulate_sort(cols, vals) if len(cols) < threshold else accumulate_dense(cols, vals, width)


def bitonic_sort(x: np.ndarray) -> np.ndarray:
    """Sorting network over a power-of-two length; a reference for tests, ``np.sort`` is vectorised itself."""
    x = x.copy()
    n, k = len(x), 2
    while k <= n:
        j = k // 2
        while j:
            i = np.arange(n)
            i = i[(i ^ j) > i]
            swap = (x[i] > x[i ^ j]) == ((i & k) == 0)
            a, b = i[swap], (i ^ j)[swap]
            x[a], x[b] = x[b], x[a]
            j //= 2
        k *= 2
    return x


def pack_chunks(counts, target: int = PACK_TARGET, threshold: int = THRESHOLD) -> list[int]:
    """Pack number of every chunk, left to right: a chunk of ``threshold`` pairs or more is alone; another joins the open pack
    while that brings the pack strictly nearer to ``target``."""
    packs, pack, size = [], -1, None
    for n in counts:
        if n >= threshold:
            pack, size = pack + 1, None
        elif size is not None and abs(size + n - target) < abs(size - target):
            size += n
        else:
            pack, size = pack + 1, n
        packs.append(pack)
    return packs


class Accumulator(Protocol):
    def merge(self, cols: np.ndarray, vals: np.ndarray, width: int): ...

    def storage(self, value_bytes: int) -> StorageModel: ...


@dataclass(frozen=True)
class Kernel:
    """A plug-in: how it merges one chunk, and the slots and bytes it holds for a chunk of a width."""

    function: object
    slots: object
    extra: int = 0

    def merge(self, cols, vals, width):
        return self.function(cols, vals, width)

    def storage(self, value_bytes: int = 8) -> StorageModel:
        return StorageModel(slot_bytes=value_bytes + self.extra, slots=self.slots)


#: A hash table is reckoned at half full, with an 8-byte key a slot; sorting holds the pairs alone.
REGISTRY: dict[str, Accumulator] = {
    "dense": Kernel(accumulate_dense, lambda width: width, 1),
    "sort": Kernel(accumulate_sort, lambda width: min(width, THRESHOLD), 8),
    "hash": Kernel(accumulate_hash, lambda width: 2 * width, 8),
    "hybrid": Kernel(accumulate_hybrid, lambda width: width, 1),
}
