"""Experiment workloads and generators."""

from __future__ import annotations

from pyspark.sql import functions as F

from sparsetier.functions import measures as C
from sparsetier.functions import params as P
from sparsetier.plans import two_level as T
from sparsetier.plans import workloads as W
from sparsetier.queries.base import UU, USQUARE, add, portable_hash_sql as H, table
from sparsetier.queries.core import FINE, TOY
from sparsetier.sources import matrices as S


def uniform_sql(n, m, per_row, seed, ids=None):
    return f"select distinct cast(r // {per_row} as bigint) i, cast({H('r', seed)} % {m} as bigint) j, 1::bigint v from ({ids or f'select range r from range({n * per_row})'})"


def power_law_sql(scale, per_row=16, seed=7, ids=None):
    bits = ", ".join(f"{H(f'r * 64 + {level}', seed)} % 100 u{level}" for level in range(scale))
    row = " + ".join(f"case when u{level} >= 76 then {1 << (scale - 1 - level)} else 0 end" for level in range(scale))
    col = " + ".join(f"case when (u{level} >= 57 and u{level} < 76) or u{level} >= 95 then {1 << (scale - 1 - level)} else 0 end" for level in range(scale))
    return f"select cast({row} as bigint) i, cast({col} as bigint) j, count(*) v from (select {bits} from ({ids or f'select range r from range({(1 << scale) * per_row})'})) group by 1, 2"


def square_sql(matrix):
    return f"with m as ({matrix}) select a.i, b.j, cast(sum(a.v * b.v) as bigint) v from m a join m b on a.j = b.i group by 1, 2"


MIXED = ("select a.range i, b.range - 2 + a.range j, 1::bigint v from range(682) a, range(5) b where b.range - 2 + a.range >= 0 "
         "union all select a.range, b.range - 20 + a.range, 1::bigint from range(682, 1365) a, range(41) b where b.range - 20 + a.range < 2048 "
         f"union all select distinct i, cast({H('i * 20 + t', 42)} % 2048 as bigint), 1::bigint from (select a.range i, b.range t from range(1365, 2048) a, range(20) b)")
BAND = "select a.range i, b.range - 2 + a.range j, 1::bigint v from range(2000) a, range(5) b where b.range - 2 + a.range between 0 and 1999"

#: The same generators on given keys: draws by order key, a band around the parts and a mixed matrix over the suppliers of the line items.
ORDERS = "select o_orderkey r from orders where o_orderkey is not null"
PART_BAND = ("select k i, k - 2 + r.range j, 1::bigint v from (select distinct l_partkey k from lineitem where l_partkey is not null), range(5) r, (select max(l_partkey) + 1 n from lineitem) "
             "where k - 2 + r.range >= 0 and k - 2 + r.range < n")
SUPPLIER_MIXED = ("with k as (select distinct l_suppkey k, (select max(l_suppkey) + 1 from lineitem) n from lineitem where l_suppkey is not null) "
                  "select k i, k - 2 + r.range j, 1::bigint v from k, range(5) r where k < n // 3 and k - 2 + r.range >= 0 and k - 2 + r.range < n "
                  "union all select k, k - 20 + r.range, 1::bigint from k, range(41) r where k >= n // 3 and k < 2 * n // 3 and k - 20 + r.range >= 0 and k - 20 + r.range < n "
                  f"union all select distinct k, cast({H('k * 20 + t', 42)} % n as bigint), 1::bigint from k, (select range t from range(20)) where k >= 2 * n // 3")


def order_keys(s, d):
    return S.keys(s, d, "orders", "o_orderkey")


def part_band(s, d):
    return S.banded_matrix(s, S._size(s, d, "lineitem", "l_partkey"), 2, S.keys(s, d, "lineitem", "l_partkey"))


def supplier_mixed(s, d):
    return S.mixed_matrix(s, S._size(s, d, "lineitem", "l_suppkey"), 42, S.keys(s, d, "lineitem", "l_suppkey"))


add("g1_uniform", lambda s, d: S.uniform_matrix(s, S._size(s, d, "orders", "o_orderkey") // 16 + 1, 4096, 16, 42, order_keys(s, d)).df, uniform_sql(0, 4096, 16, 42, ORDERS))
add("g2_power_law", lambda s, d: S.power_law_matrix(s, 12, ids=order_keys(s, d)).df, power_law_sql(12, ids=ORDERS))
add("g3_banded", lambda s, d: part_band(s, d).df, PART_BAND)
add("g3_banded_square", lambda s, d: T.two_level(a := part_band(s, d), a, TOY).df, square_sql(PART_BAND))
add("g4_mixed", lambda s, d: supplier_mixed(s, d).df, SUPPLIER_MIXED)
add("g5_index_stream", lambda s, d: S.index_stream(s, 0, 1 << 18, ids=order_keys(s, d)), f"select r pos, cast({H('r', 42)} % 262144 as bigint) idx, r % 7 + 1 val from ({ORDERS})")
add("m7_mixed", lambda s, d: T.two_level(a := supplier_mixed(s, d), a, TOY).df, square_sql(SUPPLIER_MIXED))
add("m7_mixed_fine", lambda s, d: T.two_level(a := supplier_mixed(s, d), a, FINE).df, square_sql(SUPPLIER_MIXED))
add("m7_uniform", lambda s, d: T.two_level(S.uniform_matrix(s, 64, 4096, 16, 42), S.uniform_matrix(s, 4096, 4096, 16, 43), TOY).df,
    f"with a as ({uniform_sql(64, 4096, 16, 42)}), b as ({uniform_sql(4096, 4096, 16, 43)}) select a.i, b.j, count(*) v from a join b on a.j = b.i group by 1, 2")
add("p8_stream_copy", lambda s, d: table(s, d, "lineitem").select(F.col("l_partkey").alias("idx"), F.col("l_quantity").alias("val")), "select l_partkey idx, l_quantity val from lineitem")
add("w1_accumulator_rates", lambda s, d: W.accumulator_rates(s, pairs=1 << 18))
add("c9_rate", lambda s, d: W.stream_rates(table(s, d, "lineitem").where("l_partkey is not null").select(F.col("l_partkey").alias("idx"), F.col("l_quantity").alias("val")), (5, 8, 9)))
add("w2_chunk_sweep", lambda s, d: W.chunk_sweep(s, size=1 << 15))
add("w3_length_sweep", lambda s, d: W.length_sweep(s, size=1 << 15))
add("w4_user_square", lambda s, d: T.two_level(a := S.next_user(s, d), a, TOY).df, USQUARE + "select * from c")
add("w4_collection_times", lambda s, d: W.collection_times(s, d))
add("w4_win_rate", lambda s, d: C.win_rate(W.collection_times(s, d), "two_level"))
add("w5_power_law_square", lambda s, d: T.two_level(S.power_law_matrix(s, 9), S.power_law_matrix(s, 9), TOY).df, square_sql(power_law_sql(9)))
add("w5_sweep", lambda s, d: W.power_law_sweep(s),
    " union all ".join(f"select {n}::bigint scale, cast(sum(c) as bigint) products, count(*) nnz_c from (select a.i, b.j, count(*) c from ({power_law_sql(n)}) a join ({power_law_sql(n)}) b on a.j = b.i group by 1, 2)" for n in range(5, 10)))
_UNIFORM = " union all ".join(
    f"select {n}::bigint log_columns, '{{{n}}}' \"level\", count(*) nnz_c, cast(sum(v) as bigint) total from (select a.i, b.j, count(*) v from ({uniform_sql(64, 1024, 16, 42)}) a join ({uniform_sql(1024, 1 << n, 16, 43)}) b on a.j = b.i group by 1, 2)" for n in (10, 13, 16))


def _levels(coarse):
    out = _UNIFORM
    for n in (10, 13, 16):
        out = out.replace(f"{{{n}}}", T.chunk_plan(1 << n, TOY, "numeric", T.Options(coarse=coarse)).level)
    return out


add("w6_uniform_sweep", lambda s, d: W.uniform_sweep(s), _levels(True))
add("w7_coarse_off", lambda s, d: W.uniform_sweep(s, coarse=False), _levels(False))


def _census_sql(name, matrix, columns, level):
    return (f"select '{name}' matrix, category, count(*) n_rows, cast(sum(n) as bigint) products from (select n, case when n < 256 then 'sort' when (hi - lo + 1) * 9 <= 2048 then 'dense' else '{level}' end category from "
            f"(select a.i, count(*) n, min(b.j) lo, max(b.j) hi from ({matrix}) a join ({matrix}) b on a.j = b.i group by 1)) group by 2")


add("w8_census", lambda s, d: W.census_of({"band": S.banded_matrix(s, 2000, 2), "mixed": S.mixed_matrix(s), "power_law": S.power_law_matrix(s, 8)}),
    _census_sql("band", BAND, 2000, "coarse") + " union all " + _census_sql("mixed", MIXED, 2048, "coarse") + " union all " + _census_sql("power_law", power_law_sql(8), 256, T.chunk_plan(256, TOY, "numeric", T.Options()).level))
add("w10_model_and_measure", lambda s, d: W.model_and_measure(s, size=1 << 14))


def _optimum(s, d):
    rows = [(n, P.optimal_fine_chunks(1 << n, P.SPR, P.TypeSizes())) for n in range(8, 34)]
    return s.createDataFrame(rows, "log_columns long, best_count long")


add("w10_optimum", _optimum, "with g as (select range log_columns, cast(1 as bigint) << range w from range(8, 34)), n as (select cast(1 as bigint) << range c from range(34)) "
    "select log_columns, arg_min(c, cast(w as double) * 5 / c + c * 136) best_count from g join n on c <= w group by 1")
