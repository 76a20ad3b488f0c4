"""Cost and accuracy measures: times, speed-ups, volumes, and how far from ideal they are."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.functions import params as P
from sparsetier.operators import blocks as B
from sparsetier.plans import products as M
from sparsetier.plans import two_level as T
from sparsetier.sources.matrices import SparseMatrix

TIMES = "method string, seconds double, status string"


def drain(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


class PhaseTimer:
    """Mean seconds of each phase after ``warm`` runs that do not count."""

    def __init__(self, repeats: int = 10, warm: int = 1):
        self.repeats, self.warm, self.seconds = repeats, warm, {}

    def time(self, phase: str, work) -> float:
        for _ in range(self.warm):
            work()
        at = time.perf_counter()
        for _ in range(self.repeats):
            work()
        self.seconds[phase] = (time.perf_counter() - at) / self.repeats
        return self.seconds[phase]

    def total(self) -> float:
        return sum(self.seconds.values())


def phase_seconds(a: SparseMatrix, b: SparseMatrix, spec=P.SPR, repeats: int = 1, warm: int = 0) -> DataFrame:
    """(phase, seconds) of the two-level method."""
    timer = PhaseTimer(repeats, warm)
    timer.time("setup", lambda: drain(T.setup(a, b, spec)[1]))
    timer.time("symbolic", lambda: drain(T.symbolic_phase(a, b, spec)))
    timer.time("numeric", lambda: drain(T.two_level(a, b, spec).df))
    return a.df.sparkSession.createDataFrame([*timer.seconds.items(), ("total", timer.total())], "phase string, seconds double")


def method_times(a: SparseMatrix, b: SparseMatrix, methods: dict, repeats: int = 1, warm: int = 0) -> DataFrame:
    """(method, seconds, status): a method that fails has its error's name as status and no seconds."""
    rows = []
    for name, method in methods.items():
        try:
            rows.append((name, PhaseTimer(repeats, warm).time(name, lambda: drain(method(a, b).df)), "ok"))
        except Exception as error:  # the measure counts failures
            rows.append((name, None, type(error).__name__))
    return a.df.sparkSession.createDataFrame(rows, TIMES)


def speedups(times: DataFrame, ours: str) -> DataFrame:
    """(case, method, speedup): seconds of every other method over ours."""
    own = times.where(F.col("method") == ours).select("case", F.col("seconds").alias("own"))
    return times.where((F.col("method") != ours) & (F.col("status") == "ok")).join(own, "case").select("case", "method", F.try_divide("seconds", "own").alias("speedup"))


def win_rate(times: DataFrame, ours: str) -> DataFrame:
    """(cases, wins, win_rate, worst_slowdown): how often ours is fastest, and its largest ratio to the best other."""
    best = times.where(F.col("status") == "ok").groupBy("case").agg(F.min(F.when(F.col("method") != ours, F.col("seconds"))).alias("other"), F.min(F.when(F.col("method") == ours, F.col("seconds"))).alias("own"))
    won = F.coalesce(F.col("own") <= F.col("other"), F.col("own").isNotNull())
    return best.agg(F.count("*").alias("cases"), F.count_if(won).alias("wins"), F.avg(won.cast("double")).alias("win_rate"), F.max(F.try_divide("own", "other")).alias("worst_slowdown"))


def volumes(a: SparseMatrix, b: SparseMatrix, types=T.TYPES) -> DataFrame:
    """(n_inter, read_bytes, write_bytes) in one plan: least volumes of the product."""
    zero = F.lit(0).cast("long")
    parts = B.intermediate_rows(a, b).select(F.col("n_inter"), zero.alias("nnz_a"), zero.alias("nnz_c")).unionByName(
        a.df.select(zero.alias("n_inter"), F.lit(1).cast("long").alias("nnz_a"), zero.alias("nnz_c"))).unionByName(
        M.symbolic(a, b).select(zero.alias("n_inter"), zero.alias("nnz_a"), F.col("nnz").alias("nnz_c")))
    one = parts.agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("n_inter", "nnz_a", "nnz_c")))
    pair = 2 * types.column + types.value
    return one.select("n_inter", (2 * (a.n_rows + 1) * types.row_pointer + F.col("nnz_a") * (4 * types.row_pointer + pair) + F.col("n_inter") * pair).alias("read_bytes"),
                      ((a.n_rows + 1) * types.row_pointer + F.col("nnz_c") * (types.column + types.value)).alias("write_bytes"))


def ideal_time(a, b, bytes_per_second: float) -> DataFrame:
    """(ideal_seconds): least volumes over a bandwidth."""
    return volumes(a, b).select(((F.col("read_bytes") + F.col("write_bytes")) / F.lit(float(bytes_per_second))).alias("ideal_seconds"))


def fill(c: SparseMatrix) -> DataFrame:
    """(nnz, per_row): non-zeros of a result and their average per row, empty rows included."""
    return c.df.agg(F.count("*").alias("nnz")).select("nnz", (F.col("nnz") / F.lit(float(c.n_rows))).alias("per_row"))


def compression(a, b) -> DataFrame:
    """(products, nnz, ratio): elementary products per non-zero of the result."""
    rows = B.expand(a, b).groupBy("i", "j").agg(F.count("*").alias("n"))
    return rows.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("products"), F.count("*").alias("nnz")).select("products", "nnz", F.try_divide("products", "nnz").alias("ratio"))


def coarse_bounds(a: SparseMatrix, b: SparseMatrix, rows: DataFrame) -> DataFrame:
    """(best, worst) work of the coarse level on the given rows: their non-zeros, and these times the columns of B."""
    return B.select_rows(a, rows).df.agg(F.count("*").alias("best")).select("best", (F.col("best") * b.n_cols).alias("worst"))


def coarse_memory(rows: DataFrame, plan: P.ChunkPlan, spec, types=T.TYPES) -> DataFrame:
    """(pair_bytes, counter_bytes) that the coarse level holds for the given rows at once."""
    return rows.agg((F.coalesce(F.sum("n_inter"), F.lit(0)) * (types.value + types.column)).alias("pair_bytes"),
                    (F.count("*") * P.coarse_counter_bytes(plan.n_coarse, spec, types)).alias("counter_bytes"))


def difference(x: SparseMatrix, y: SparseMatrix) -> DataFrame:
    """(cells, max_abs_diff, only_left, only_right) of two results."""
    both = x.df.select("i", "j", F.col("v").alias("xv")).join(y.df.select("i", "j", F.col("v").alias("yv")), ["i", "j"], "full")
    return both.agg(F.count("*").alias("cells"), F.coalesce(F.max(F.abs(F.col("xv") - F.col("yv"))), F.lit(0)).cast("long").alias("max_abs_diff"),
                    F.count_if(F.col("yv").isNull()).alias("only_left"), F.count_if(F.col("xv").isNull()).alias("only_right"))


def stream_bandwidth(df: DataFrame, row_bytes: int) -> DataFrame:
    """(rows, seconds, bytes_per_second) of reading and writing every row once."""
    n, timer = df.count(), PhaseTimer(1, 1)
    seconds = timer.time("copy", lambda: drain(df))
    return df.sparkSession.createDataFrame([(n, seconds, 2 * n * row_bytes / seconds)], "rows long, seconds double, bytes_per_second double")
