"""The chunk kernel: one pass over sorted pairs that merges every row by its category."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame

from sparsetier.operators import accumulators as A

SORT, DENSE, FINE = 0, 1, 2
#: Pairs merged at a time, and pairs of one row from which on a part of it is merged and carried on.
WORK, CARRY = 1 << 19, 1 << 21


@dataclass(frozen=True)
class KernelPlan:
    shift: int
    accumulator: str = "hybrid"  # of chunks: hybrid, sort or dense
    threshold: int = A.THRESHOLD
    pack: bool = True
    symbolic: bool = False


def packs_by_prefix(count: np.ndarray, small: np.ndarray, target: int = A.PACK_TARGET) -> np.ndarray:
    """Head chunk of the pack of every chunk, for rows of counts: neighbouring small chunks whose pairs before them fall into one
    multiple of ``target``. The batch form of the greedy rule, without a loop."""
    before = (np.cumsum(count, axis=1) - count) // target
    key = (before * (count.shape[1] + 1) + np.cumsum(~small, axis=1)) * 2 + small
    first = np.ones(count.shape, dtype=bool)
    first[:, 1:] = key[:, 1:] != key[:, :-1]
    return np.maximum.accumulate(np.where(first.ravel(), np.arange(count.size), 0))


def fine_rows(row: np.ndarray, j: np.ndarray, p: np.ndarray, plan: KernelPlan, buffer: A.DenseBuffer):
    """Fine level over rows numbered 0, 1, …: histogram, choice by chunk size, scatter to chunks with local columns, accumulate, shift
    back. Small chunks are scattered and sorted by one sort."""
    if not len(j):
        return row, j, p
    chunk = j >> plan.shift
    low = np.minimum.reduceat(chunk, A._first_of_runs(row))
    n_chunks = int((chunk - low[row]).max()) + 1
    number = row * n_chunks + chunk - low[row]
    count = np.bincount(number, minlength=len(low) * n_chunks).reshape(-1, n_chunks)
    small = {"hybrid": count < plan.threshold, "sort": np.ones(count.shape, bool), "dense": np.zeros(count.shape, bool)}[plan.accumulator]
    pick, out = small.ravel()[number], []
    local = j - (chunk << plan.shift)
    if pick.any():
        seg, cols = number[pick], local[pick]
        if plan.pack:  # columns count from the pack's first chunk
            head = packs_by_prefix(count, small)[seg]
            cols = cols + ((seg - head) << plan.shift)
            seg = head
        out.append(A.sort_many(seg, cols, p[pick]))
    if not pick.all():
        seg = number[~pick]
        order = np.argsort(seg.astype(np.uint16), kind="stable") if count.size <= 1 << 16 else np.argsort(seg)
        out.append(A.dense_many(seg[order], local[~pick][order], p[~pick][order], buffer))
    seg, cols, sums = (np.concatenate(x) for x in zip(*out))
    own = seg // n_chunks
    return own, cols + ((seg % n_chunks + low[own]) << plan.shift), sums


def merge_rows(key, j, p, n_rows: int, plan: KernelPlan, buffer: A.DenseBuffer):
    """Merged (key, j, p) of whole pieces of rows, each by its category."""
    kind, out = key // n_rows & 3, []
    for category in (SORT, DENSE, FINE):
        own = kind == category
        if not own.any():
            continue
        a, b, c = (key, j, p) if own.all() else (key[own], j[own], p[own])
        at = A._first_of_runs(a)
        row = np.repeat(np.arange(len(at)), np.diff(np.append(at, len(a))))
        if category == SORT:
            r, cols, sums = A.sort_many(row, b, c)
        elif category == DENSE:
            r, cols, sums = A.dense_many(row, b, c, buffer)
        else:
            r, cols, sums = fine_rows(row, b, c, plan, buffer)
        out.append((a[at][r], cols, sums))
    return tuple(np.concatenate(x) for x in zip(*out))


def piece_key(sub: Column, kind, i: Column, n_rows: int, n_subs: int) -> Column:
    """One number for (piece, category, row): sorting by it is a radix sort, and it takes a column in the exchange, not three."""
    if n_rows * n_subs >= 1 << 60:
        raise ValueError("rows times pieces exceed a 64-bit key")
    return ((sub * 4 + kind) * n_rows + i).alias("key")


def chunked_merge(pairs: DataFrame, n_rows: int, plan: KernelPlan, value: str = "long") -> DataFrame:
    """(i, j, v) from (key, j, p): one exchange by key, then a pass over sorted pairs. Holds ``WORK`` pairs, or one
    row piece's; of a piece with more than ``CARRY`` pairs the part at hand is merged first. With ``symbolic``: (i, nnz) per piece."""
    dtype = {"long": np.int64, "double": np.float64}[value]
    arrow = {"long": pa.int64(), "double": pa.float64()}[value]

    def run(batches):
        held, weight = [], 0
        buffer = A.DenseBuffer(dtype)

        def pack(key, j, p):
            if plan.symbolic:
                order = np.argsort(key, kind="stable")
                at = A._first_of_runs(key[order])
                return pa.RecordBatch.from_arrays([pa.array(key[order][at] % n_rows), pa.array(np.diff(np.append(at, len(key))))], names=["i", "nnz"])
            return pa.RecordBatch.from_arrays([pa.array(key % n_rows), pa.array(j), pa.array(p, arrow)], names=["i", "j", "v"])

        for batch in batches:
            held.append([batch.column(c).to_numpy() for c in ("key", "j", "p")])
            weight += batch.num_rows
            if weight < WORK:
                continue
            key, j, p = (np.concatenate(x) for x in zip(*held))
            cut = int(np.searchsorted(key, key[-1]))
            if cut:
                yield pack(*merge_rows(key[:cut], j[:cut], p[:cut], n_rows, plan, buffer))
            rest = [x[cut:] for x in (key, j, p)]
            if len(rest[0]) >= CARRY:
                rest = list(merge_rows(*rest, n_rows, plan, buffer))
            held, weight = [rest], min(len(rest[0]), WORK - WORK // 4)
        if held:
            key, j, p = (np.concatenate(x) for x in zip(*held))
            if len(key):
                yield pack(*merge_rows(key, j, p, n_rows, plan, buffer))

    dealt = pairs.select("key", "j", "p").repartition("key").sortWithinPartitions("key")
    return dealt.mapInArrow(run, "i long, nnz long" if plan.symbolic else f"i long, j long, v {value}")


def compress_sorted(pairs: DataFrame, value: str = "long") -> DataFrame:
    """(i, j, v) from (i, j, p) that is sorted by (i, j) in every partition: equal neighbours are merged, also across batches."""
    arrow = {"long": pa.int64(), "double": pa.float64()}[value]

    def run(batches):
        held = None
        for batch in batches:
            cols = [batch.column(c).to_numpy() for c in ("i", "j", "p")]
            if held is not None:
                cols = [np.concatenate([h, c]) for h, c in zip(held, cols)]
            i, j, p = A.compress(*cols)
            held = [i[-1:], j[-1:], p[-1:]]
            if len(i) > 1:
                yield pa.RecordBatch.from_arrays([pa.array(i[:-1]), pa.array(j[:-1]), pa.array(p[:-1], arrow)], names=["i", "j", "v"])
        if held is not None and len(held[0]):
            yield pa.RecordBatch.from_arrays([pa.array(held[0]), pa.array(held[1]), pa.array(held[2], arrow)], names=["i", "j", "v"])

    return pairs.select("i", "j", "p").mapInArrow(run, f"i long, j long, v {value}")


def heap_rows(pairs: DataFrame) -> DataFrame:
    """(i, j, v) from (i, k, j, p) sorted by (i, k, j) in every partition: a heap merges the scaled rows of B of one row at a time."""

    def run(batches):
        held = None

        def merged(i, k, j, p):
            cols, sums, rows = [], [], []
            at = A._first_of_runs(i)
            for a, b in zip(at, np.append(at[1:], len(i))):
                cuts = A._first_of_runs(k[a:b])
                c, v = A.accumulate_heap(list(zip(np.split(j[a:b], cuts[1:]), np.split(p[a:b], cuts[1:]))))
                cols.append(c)
                sums.append(v)
                rows.append(np.full(len(c), i[a]))
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate(x), pa.int64()) for x in (rows, cols, sums)], names=["i", "j", "v"])

        for batch in batches:
            cols = [batch.column(c).to_numpy() for c in ("i", "k", "j", "p")]
            if held is not None:
                cols = [np.concatenate([h, c]) for h, c in zip(held, cols)]
            cut = int(np.searchsorted(cols[0], cols[0][-1])) if len(cols[0]) else 0
            if cut:
                yield merged(*(c[:cut] for c in cols))
            held = [c[cut:] for c in cols]
        if held is not None and len(held[0]):
            yield merged(*held)

    return pairs.select("i", "k", "j", "p").mapInArrow(run, "i long, j long, v long")
