"""Accumulators on a stream of (column, value) pairs from the line items, chunk by chunk."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.functions import params as P
from sparsetier.operators import accumulators as A
from sparsetier.operators import blocks as B
from sparsetier.queries.base import INTER, add, pair, table

SHIFT, HELD = 6, 1 << 18
_SQL = "select l_partkey >> 6 chunk, l_partkey & 63 col, cast(sum(l_quantity) as bigint) v from lineitem group by 1, 2"


def stream(spark, d) -> DataFrame:
    return table(spark, d, "lineitem").where("l_partkey is not null").select(
        F.shiftright("l_partkey", SHIFT).alias("chunk"), F.col("l_partkey").bitwiseAND((1 << SHIFT) - 1).alias("col"), F.col("l_quantity").cast("long").alias("v"))


def accumulate(pairs: DataFrame, merge, width: int) -> DataFrame:
    """(chunk, col, v) by one accumulator. Chunks stand together after one exchange; of a chunk longer than ``HELD`` pairs what is at
    hand is merged and carried on, so that a chunk holds its width at most."""

    def run(batches):
        held = None

        def merged(chunk, col, v):
            out = []
            at = A._first_of_runs(chunk)
            for a, b in zip(at, np.append(at[1:], len(chunk))):
                c, s = merge(col[a:b], v[a:b], width)
                out.append((np.full(len(c), chunk[a]), c, s))
            return [np.concatenate(x) for x in zip(*out)]

        def pack(cols):
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["chunk", "col", "v"])

        for batch in batches:
            cols = [batch.column(c).to_numpy() for c in ("chunk", "col", "v")]
            held = cols if held is None else [np.concatenate([h, c]) for h, c in zip(held, cols)]
            if len(held[0]) >= HELD:
                cut = int(np.searchsorted(held[0], held[0][-1]))
                if cut:
                    yield pack(merged(*(c[:cut] for c in held)))
                held = merged(*(c[cut:] for c in held))
        if held is not None and len(held[0]):
            yield pack(merged(*held))

    return pairs.repartition("chunk").sortWithinPartitions("chunk").mapInArrow(run, "chunk long, col long, v long")


def _heap(col, v, width):
    runs = [s for s in np.array_split(np.arange(len(col)), max(1, len(col) // 64))]
    ordered = [r[np.argsort(col[r], kind="stable")] for r in runs]
    return A.accumulate_heap([(col[r], v[r]) for r in ordered])


for _name, _merge in {"a1_dense": A.accumulate_dense, "a2_sort": A.accumulate_sort, "a3_hash": A.accumulate_hash, "a4_heap": _heap, "a5_hybrid": A.accumulate_hybrid}.items():
    add(_name, lambda s, d, merge=_merge: accumulate(stream(s, d), merge, 1 << SHIFT), _SQL)

add("a3_hash_native", lambda s, d: stream(s, d).groupBy("chunk", "col").agg(F.sum("v").alias("v")), _SQL)
add("a7_symbolic", lambda s, d: accumulate(stream(s, d).withColumn("v", F.lit(1).cast("long")), lambda c, v, w: (np.flatnonzero(np.bincount(c, minlength=w)), np.ones(len(np.unique(c)), dtype=np.int64)), 1 << SHIFT).groupBy("chunk").agg(F.count("*").alias("nnz")),
    "select l_partkey >> 6 chunk, count(distinct l_partkey) nnz from lineitem group by 1")


def packs(counts: DataFrame, target: int = A.PACK_TARGET, threshold: int = A.THRESHOLD) -> DataFrame:
    """(i, chunk, cnt, pack) by a fold over each row's counts."""
    rows = counts.groupBy("i").agg(F.sort_array(F.collect_list(F.struct("chunk", "cnt"))).alias("cells"))
    start = F.struct(F.lit(-1).cast("long").alias("pack"), F.lit(-1).cast("long").alias("size"), F.array().cast("array<bigint>").alias("packs"))

    def step(acc, x):
        n = x["cnt"]
        alone, joins = n >= threshold, (acc["size"] >= 0) & (F.abs(acc["size"] + n - target) < F.abs(acc["size"] - target))
        pack = F.when(~alone & joins, acc["pack"]).otherwise(acc["pack"] + 1)
        size = F.when(alone, F.lit(-1).cast("long")).when(joins, acc["size"] + n).otherwise(n)
        return F.struct(pack.alias("pack"), size.alias("size"), F.concat(acc["packs"], F.array(pack)).alias("packs"))

    folded = rows.select("i", "cells", F.aggregate("cells", start, step)["packs"].alias("packs"))
    return folded.select("i", F.explode(F.arrays_zip("cells", "packs")).alias("x")).select("i", F.col("x.cells.chunk").alias("chunk"), F.col("x.cells.cnt").alias("cnt"), F.col("x.packs").alias("pack"))


_FOLD = (INTER + ", h as (select i, j >> 4 chunk, count(*) cnt, row_number() over (partition by i order by j >> 4) n from x group by 1, 2), "
         "r as (with recursive f as (select i, n, chunk, cnt, 0::bigint pack, case when cnt >= 256 then -1 else cnt end size from h where n = 1 union all "
         "select h.i, h.n, h.chunk, h.cnt, case when h.cnt < 256 and f.size >= 0 and abs(f.size + h.cnt - 32) < abs(f.size - 32) then f.pack else f.pack + 1 end, "
         "case when h.cnt >= 256 then -1 when f.size >= 0 and abs(f.size + h.cnt - 32) < abs(f.size - 32) then f.size + h.cnt else h.cnt end "
         "from f join h on h.i = f.i and h.n = f.n + 1) select * from f) select i, chunk, cnt, pack from r")
add("a6_packs", lambda s, d: packs(B.histogram(B.expand(*pair(s, d)), 4)), _FOLD)


def _models(s, d):
    rows = [(name, log, A.REGISTRY[name].storage(4).argmin_pow2(1 << log)) for name in ("dense", "hash", "sort") for log in range(8, 31, 2)]
    return s.createDataFrame(rows, "accumulator string, log_columns long, best_count long")


add("s11_storage_models", _models,
    "with g as (select name accumulator, slot, r.range log_columns, cast(1 as bigint) << r.range w from (values ('dense', 5), ('hash', 12), ('sort', 12)) a(name, slot), range(8, 31, 2) r), "
    "c as (select cast(1 as bigint) << range n from range(31)), b as (select *, case accumulator when 'dense' then w // n when 'hash' then 2 * (w // n) else least(w // n, 256) end * slot + n * 136 bytes from g join c on n <= w) "
    "select accumulator, log_columns, first(n order by bytes, n) best_count from b group by 1, 2")
