"""The experiment workloads: accumulator rates, sweeps over chunk counts and lengths, growing matrices."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsetier.functions import measures as C
from sparsetier.functions import params as P
from sparsetier.operators import accumulators as A
from sparsetier.operators import blocks as B
from sparsetier.plans import kernel as K
from sparsetier.plans import products as M
from sparsetier.plans import two_level as T
from sparsetier.sources import matrices as S


def accumulator_rates(spark: SparkSession, length: int = 1 << 18, logs=range(3, 17), pairs: int = 1 << 20) -> DataFrame:
    """(accumulator, log_size, m_per_s): million pairs merged per second, on streams of one length cut into pieces of a size; one task
    per (accumulator, size), each over ``pairs`` pairs."""
    rows = [(name, log) for name in ("sort", "dense", "hash") for log in logs]
    jobs = spark.createDataFrame(rows, "accumulator string, log_size int").repartition(len(rows))

    def run(batches):
        import pyarrow as pa

        rng = np.random.default_rng(1)
        for batch in batches:
            out = []
            for name, log in zip(batch.column("accumulator").to_pylist(), batch.column("log_size").to_pylist()):
                n, size = pairs if name != "hash" else pairs >> 3, 1 << log
                col, val = rng.integers(0, length, n), np.ones(n, dtype=np.float32)
                seg = np.repeat(np.arange(-(-n // size)), size)[:n]
                buffer = A.DenseBuffer(np.float32)
                at = time.perf_counter()
                if name == "sort":
                    A.sort_many(seg, col, val)
                elif name == "dense":
                    for a in range(0, n, max(size, 1 << 12)):  # short pieces share a call
                        A.dense_many(seg[a:a + max(size, 1 << 12)], col[a:a + max(size, 1 << 12)], val[a:a + max(size, 1 << 12)], buffer)
                else:
                    for a in range(0, n, size):
                        A.accumulate_hash(col[a:a + size], val[a:a + size])
                out.append((name, log, n / (time.perf_counter() - at) / 1e6))
            cols = list(zip(*out)) or [()] * 3
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.string()), pa.array(cols[1], pa.int32()), pa.array(cols[2], pa.float64())], names=["accumulator", "log_size", "m_per_s"])

    return jobs.mapInArrow(run, "accumulator string, log_size int, m_per_s double")


def stream_rates(stream: DataFrame, logs) -> DataFrame:
    """(accumulator, log_size, m_per_s): the same rates on a given stream (idx, val), all of it through every accumulator and size where
    its partitions are."""

    def run(batches):
        import pyarrow as pa

        buffer, spent = A.DenseBuffer(np.float64), {}
        for batch in batches:
            col, val = batch.column("idx").to_numpy(zero_copy_only=False), batch.column("val").to_numpy(zero_copy_only=False)
            for log in logs:
                seg = np.arange(len(col)) >> log
                work = {"sort": lambda: A.sort_many(seg, col, val), "dense": lambda: A.dense_many(seg, col, val, buffer),
                        "hash": lambda: [A.accumulate_hash(col[a:a + (1 << log)], val[a:a + (1 << log)]) for a in range(0, len(col), 1 << log)]}
                for name, merge in work.items():
                    at = time.perf_counter()
                    merge()
                    n, seconds = spent.get((name, log), (0, 0.0))
                    spent[name, log] = n + len(col), seconds + time.perf_counter() - at
        rows = [(name, log, n, seconds) for (name, log), (n, seconds) in spent.items() if n]
        yield pa.RecordBatch.from_pylist([dict(zip(("accumulator", "log_size", "n", "seconds"), r)) for r in rows], pa.schema([("accumulator", pa.string()), ("log_size", pa.int32()), ("n", pa.int64()), ("seconds", pa.float64())]))

    parts = stream.mapInArrow(run, "accumulator string, log_size int, n long, seconds double")
    return parts.groupBy("accumulator", "log_size").agg((F.sum("n") / F.sum("seconds") / 1e6).alias("m_per_s"))


def block_seconds(pairs: DataFrame, length: int, n_chunks: int) -> list[tuple[str, float]]:
    """Seconds of histogram, prefix sum, reorder, accumulation and plain copy of a stream (pos, idx, val), one chunk count."""
    shift = max(0, (length // n_chunks).bit_length() - 1)
    rows = pairs.select(F.shiftright("pos", 16).alias("i"), F.col("pos").alias("k"), F.col("idx").alias("j"), F.col("val").cast("long").alias("p"))
    hist = B.histogram(rows, shift)
    n_rows = 1 << 31
    keyed = rows.select(K.piece_key(F.shiftright("j", shift), K.FINE, F.col("i"), n_rows, n_chunks), "j", "p")
    dealt = keyed.repartition("key").sortWithinPartitions("key")  # the exchange by chunk is the reordering
    work = {"copy": pairs, "histogram": hist, "prefix_sum": B.prefix_sum(hist, ["i"], "chunk", "cnt"), "reorder": dealt, "accumulate": K.chunked_merge(keyed, n_rows, K.KernelPlan(shift))}
    return [(name, C.PhaseTimer(1, 0).time(name, lambda df=df: C.drain(df))) for name, df in work.items()]


def chunk_sweep(spark, size: int = 1 << 17, length: int = 1 << 20, logs=(0, 4, 8, 12)) -> DataFrame:
    """(log_chunks, block, seconds, multiple of the copy) at one length."""
    stream = S.index_stream(spark, size, length)
    rows = []
    for log in logs:
        found = block_seconds(stream, length, 1 << log)
        rows += [(log, name, seconds, seconds / found[0][1]) for name, seconds in found]
    return spark.createDataFrame(rows, "log_chunks int, block string, seconds double, multiple double")


def length_sweep(spark, size: int = 1 << 17, logs=(12, 18, 24)) -> DataFrame:
    """(log_length, log_chunks, block, seconds, multiple): the model's chunk count for each length."""
    rows = []
    for log in logs:
        n = P.optimal_fine_chunks(1 << log, P.SPR, P.TypeSizes())
        found = block_seconds(S.index_stream(spark, size, 1 << log), 1 << log, n)
        rows += [(log, n.bit_length() - 1, name, seconds, seconds / found[0][1]) for name, seconds in found]
    return spark.createDataFrame(rows, "log_length int, log_chunks int, block string, seconds double, multiple double")


def power_law_sweep(spark, scales=range(5, 10)) -> DataFrame:
    """(scale, nnz, products, nnz_c) of the squares of growing power-law matrices."""
    out = None
    for scale in scales:
        a = S.power_law_matrix(spark, scale)
        row = C.compression(a, a).select(F.lit(scale).cast("long").alias("scale"), F.col("products"), F.col("nnz").alias("nnz_c"))
        out = row if out is None else out.unionByName(row)
    return out


def uniform_sweep(spark, logs=(10, 13, 16), rows: int = 64, per_row: int = 16, coarse: bool = True, spec=P.TOY) -> DataFrame:
    """(log_columns, level, nnz_c, total) of products with one number of rows and growing columns. Only the rows of B that A asks
    for are generated."""
    out = None
    for log in logs:
        a = S.uniform_matrix(spark, rows, 1 << 10, per_row, 42)
        b = needed_uniform(a, 1 << 10, 1 << log, per_row, 43)
        c = T.two_level(a, b, spec, T.Options(coarse=coarse))
        plan = T.chunk_plan(1 << log, spec, "numeric", T.Options(coarse=coarse))
        row = c.df.agg(F.count("*").alias("nnz_c"), F.sum("v").alias("total")).select(F.lit(log).cast("long").alias("log_columns"), F.lit(plan.level).alias("level"), "nnz_c", "total")
        out = row if out is None else out.unionByName(row)
    return out


def needed_uniform(a: S.SparseMatrix, n: int, m: int, per_row: int, seed: int) -> S.SparseMatrix:
    """The uniform matrix of ``S.uniform_matrix``, but only the rows that A's columns name."""
    rows = B.needed_rows(a).select("i", F.explode(F.sequence(F.lit(0), F.lit(per_row - 1))).alias("t"))
    cells = rows.select("i", (S.portable_hash(F.col("i") * per_row + F.col("t"), seed) % m).alias("j")).distinct()
    return S.SparseMatrix(cells.withColumn("v", F.lit(1).cast("long")), n, m)


def census_of(matrices: dict, spec=P.TOY) -> DataFrame:
    """(matrix, category, n_rows, products) of the squares of several matrices."""
    out = None
    for name, a in matrices.items():
        rows = T.setup(a, a, spec)[1]
        part = B.census(rows).withColumn("matrix", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


def model_and_measure(spark, length: int = 1 << 20, size: int = 1 << 16, logs=(0, 4, 8, 12)) -> DataFrame:
    """(log_chunks, model_bytes, seconds): the storage model beside the measured total."""
    stream, rows = S.index_stream(spark, size, length), []
    for log in logs:
        seconds = sum(t for name, t in block_seconds(stream, length, 1 << log) if name != "copy")
        rows.append((log, P.fine_storage(length, 1 << log, P.SPR, P.TypeSizes()), seconds))
    return spark.createDataFrame(rows, "log_chunks int, model_bytes double, seconds double")


def collection_times(spark, sf_dir) -> DataFrame:
    """(case, method, seconds, status) of squares over matrices of several structures, for win rates."""
    n = 1 << 11
    cases = {"band": S.banded_matrix(spark, n, 2), "mixed": S.mixed_matrix(spark), "power_law": S.power_law_matrix(spark, 9), "uniform": S.uniform_matrix(spark, n, n, 8, 42), "users": S.next_user(spark, sf_dir)}
    methods = {"two_level": T.two_level, "relational": M.relational, "expand_sort_compress": M.expand_sort_compress, "hash": M.hash_product, "segmented_b": M.segmented_b}
    out = None
    for name, a in cases.items():
        rows = C.method_times(a, a, methods).withColumn("case", F.lit(name))
        out = rows if out is None else out.unionByName(rows)
    return spark.createDataFrame(out.collect(), out.schema)  # a few rows of times
