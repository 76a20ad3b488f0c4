"""Cost and accuracy measures on co-purchase and on the square of part to next part."""

from __future__ import annotations

from pyspark.sql import functions as F

from sparsetier.functions import measures as C
from sparsetier.functions import params as P
from sparsetier.plans import products as M
from sparsetier.plans import two_level as T
from sparsetier.queries.base import COP, INTER, OP, PP, add, pair, table
from sparsetier.queries.core import _SQCAT, _square_rows
from sparsetier.sources import matrices as S
from sparsetier.store import Scratch

_VOLUMES = INTER + (", n as (select max(p_partkey) + 2 n from part), w as (select (select count(*) from x) n_inter, 16 * n + (select count(*) from op) * 56 + (select count(*) from x) * 24 read_bytes, "
                    "8 * n + (select count(*) from (select distinct i, j from x)) * 16 write_bytes from n) ")
COMPETITORS = {"two_level": T.two_level, "relational": M.relational, "expand_sort_compress": M.expand_sort_compress, "segmented_b": M.segmented_b, "hash": M.hash_product,
               "portable_sql": M.portable_sql, "semiring": M.semiring, "heap": M.heap_product, "library": lambda a, b: M.library_product(a, b, limit=1 << 26)}

add("c1_n_inter", lambda s, d: s.createDataFrame([(M.total_products(*pair(s, d)),)], "n_inter long"), INTER + "select count(*) n_inter from x")
add("c2_ideal_volumes", lambda s, d: C.volumes(*pair(s, d)), _VOLUMES + "select * from w")
add("c4_ideal_time", lambda s, d: C.ideal_time(*pair(s, d), 1e11), _VOLUMES + "select (read_bytes + write_bytes) / 1e11::double ideal_seconds from w")


def _multiple(s, d):
    """Seconds of the numeric phase over the ideal time at the bandwidth of a copy."""
    a, b = pair(s, d)
    rate = C.stream_bandwidth(table(s, d, "lineitem").select("l_partkey", "l_quantity"), 16).first().bytes_per_second
    ideal = C.ideal_time(a, b, rate).first()[0]
    seconds = C.PhaseTimer(1, 1).time("numeric", lambda: C.drain(T.two_level(a, b).df))
    return s.createDataFrame([(ideal, seconds, seconds / ideal)], "ideal_seconds double, seconds double, multiple double")


def _times(s, d):
    """Seconds of every method's product in both cases; the matrices are made from their tables once, before the clock starts."""
    scratch = Scratch(s)
    stored = lambda m, tag: S.SparseMatrix(scratch.write(m.df, tag), m.n_rows, m.n_cols)
    a, op = stored(S.next_part(s, d), "next_part"), stored(S.order_part(s, d), "order_part")
    cases = {"co_purchase": (op.transpose(), op), "next_part": (a, a)}
    out = None
    for name, (x, y) in cases.items():
        rows = C.method_times(x, y, {k: COMPETITORS[k] for k in ("two_level", "relational", "expand_sort_compress", "hash", "segmented_b")}).withColumn("case", F.lit(name))
        out = rows if out is None else out.unionByName(rows)
    scratch.clear()
    return s.createDataFrame(out.collect(), out.schema)  # a few rows of times


add("c5_ideal_multiple", _multiple)
add("c6_speedup", lambda s, d: C.speedups(_times(s, d), "two_level"))
add("c7_phase_seconds", lambda s, d: C.phase_seconds(*pair(s, d)))
add("c8_fill", lambda s, d: C.fill(M.relational(*pair(s, d))), COP + "select count(*) nnz, count(*) / cast((select max(p_partkey) + 1 from part) as double) per_row from c")
add("c10_stream_bandwidth", lambda s, d: C.stream_bandwidth(table(s, d, "lineitem").select("l_partkey", "l_quantity"), 16))


def _spans(s, d):
    """(l_suppkey, width): columns that a supplier's row of parts spans."""
    return table(s, d, "lineitem").where("l_suppkey is not null and l_partkey is not null").groupBy("l_suppkey").agg((F.max("l_partkey") - F.min("l_partkey") + 1).alias("width"))


def _excess(s, d):
    """Of every supplier's row of parts as wide as it spans: bytes beyond the private cache by chunk count."""
    n = F.expr("shiftleft(1L, cast(log_chunks as int))")
    rows = _spans(s, d).withColumn("log_chunks", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(20).cast("long"))))
    return rows.select("l_suppkey", "log_chunks", F.greatest(F.lit(0.0), P.fine_storage(F.col("width"), n, P.SPR, P.TypeSizes()).cast("double") - P.SPR.l2_bytes).alias("excess_bytes"))


def _breakpoints(s, d):
    specs = {spec.name: spec for spec in (P.SKX, P.SPR)}
    found = F.udf(lambda machine, width: P.breakpoints(width, specs[machine], P.TypeSizes()), "dense_fits long, reorder_breaks long")
    rows = _spans(s, d).withColumn("machine", F.explode(F.array(*map(F.lit, specs)))).withColumn("b", found("machine", "width"))
    return rows.select("machine", "l_suppkey", "b.dense_fits", "b.reorder_breaks")


_SPANS = "with s as (select l_suppkey, max(l_partkey) - min(l_partkey) + 1 width from lineitem where l_suppkey is not null and l_partkey is not null group by 1) "
add("c11_working_set_excess", _excess, _SPANS + "select l_suppkey, r.range log_chunks, greatest(0.0::double, cast(width * 5 as double) / (1 << r.range) + cast((1 << r.range) * 136 as double) - 2097152) excess_bytes from s, range(21) r")
add("c12_breakpoints", _breakpoints,
    _SPANS + ", g as (select * from s, (values ('SKX', 1048576), ('SPR', 2097152)) m(machine, l2)), n as (select cast(1 as bigint) << range c from range(50)) "
    "select machine, l_suppkey, (select min(c) from n where cast(width as double) * 5 / c <= l2) dense_fits, (select min(c) from n where c * 136 > l2) reorder_breaks from g")
add("c13_compression", lambda s, d: C.compression(*pair(s, d)), INTER + "select count(*) products, count(distinct (i, j)) nnz, count(*) / cast(count(distinct (i, j)) as double) ratio from x")
add("c14_coarse_bounds", lambda s, d: C.coarse_bounds(a := S.next_part(s, d), a, _square_rows(s, d)),
    _SQCAT + "select count(*) best, cast(count(*) * (select max(p_partkey) + 1 from part) as bigint) worst from pp where i in (select i from t where category = 'coarse')")
add("c15_coarse_memory", lambda s, d: C.coarse_memory(_square_rows(s, d), P.ChunkPlan("coarse", 2048, 4, 9, 4, 7), P.TOY),
    _SQCAT + "select cast(coalesce(sum(n_inter), 0) * 16 as bigint) pair_bytes, cast(count(*) * 4 * 136 as bigint) counter_bytes from t where category = 'coarse'")
add("c16_failures", lambda s, d: C.method_times(*pair(s, d), COMPETITORS))
add("c17_win_rate", lambda s, d: C.win_rate(_times(s, d), "two_level"))
add("c18_accuracy", lambda s, d: C.difference(T.two_level(*pair(s, d)), M.relational(*pair(s, d))), COP + "select count(*) cells, 0::bigint max_abs_diff, 0::bigint only_left, 0::bigint only_right from c")
