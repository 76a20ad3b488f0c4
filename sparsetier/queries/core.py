"""Storage forms, setup, building blocks and products."""

from __future__ import annotations

from pyspark.sql import functions as F

from sparsetier.functions import params as P
from sparsetier.operators import blocks as B
from sparsetier.plans import products as M
from sparsetier.plans import two_level as T
from sparsetier.queries.base import COP, INTER, OP, PP, PS, SQUARE, add, pair
from sparsetier.sources import matrices as S

TOY, FINE = P.TOY, P.TOY_FINE
#: A private cache so small that rows of every kind are met on the given tables.
TINY = P.SystemSpec("tiny", 1024)

# ---- storage forms

add("f1_from_table", lambda s, d: S.order_part(s, d).df, f"with {OP} select * from op")
add("f2_row_packed", lambda s, d: B.unpack_rows(B.row_packed(S.order_part(s, d))).withColumn("pos", F.col("pos").cast("long")),
    f"with {OP} select i, row_number() over (partition by i order by j) - 1 pos, j, v from op")
_POINTERS = ("select i, cast(sum(c) over (order by i) - c as bigint) \"start\", cast(sum(c) over (order by i) as bigint) \"end\" from n")
add("f3_row_pointers", lambda s, d: B.row_pointers(S.order_part(s, d)),
    f"with {OP}, n as (select r.range i, count(op.j) c from range((select max(o_orderkey) + 1 from orders)) r left join op on op.i = r.range group by 1) " + _POINTERS)
add("f4_unpack", lambda s, d: B.unpack_rows(B.row_packed(S.next_part(s, d))).select("i", "j", "v"), f"with {PP} select * from pp")
_LONG = "(select i from op group by i having count(*) >= 5)"


def _long_rows(m):
    return m.df.groupBy("i").agg(F.count("*").alias("c")).where("c >= 5").select("i")


def _column_packed(s, d):
    m = S.order_part(s, d)
    packed = B.column_packed(m, _long_rows(m))
    return packed.select("k", F.explode(F.arrays_zip("rows", "vals")).alias("x")).select("k", F.col("x.rows").alias("i"), F.col("x.vals").alias("v"))


add("f5_column_packed", _column_packed, f"with {OP} select j k, i, v from op where i in {_LONG}")
add("f5_column_pointers", lambda s, d: B.column_pointers(m := S.order_part(s, d), _long_rows(m)),
    f"with {OP}, n as (select r.range i, count(op.j) c from range((select max(p_partkey) + 1 from part)) r left join (select * from op where i in {_LONG}) op on op.j = r.range group by 1) " + _POINTERS)
add("f6_transpose", lambda s, d: S.order_part(s, d).transpose().df, f"with {OP} select j i, i j, v from op")
add("f7_row_subset", lambda s, d: B.select_rows(m := S.order_part(s, d), _long_rows(m)).df, f"with {OP} select * from op where i in {_LONG}")
add("f8_needed_rows", lambda s, d: B.needed_rows(S.next_part(s, d)), f"with {PP} select distinct j i from pp")
add("f9_pruned", lambda s, d: B.prune(S.part_supplier(s, d), B.needed_rows(S.next_part(s, d))).df, f"with {PP}, {PS} select * from ps where i in (select j from pp)")
add("f10_describe", lambda s, d: B.describe(S.order_part(s, d)), f"with {OP} select count(*) nnz, count(distinct i) used_rows, count(distinct j) used_cols from op")
add("f11_ceil_pow2", lambda s, d: S.order_part(s, d).df.groupBy("i").agg(F.max("j").alias("m")).where("m > 1").select("i", "m", F.expr("shiftleft(1L, length(bin(m - 1)))").alias("width")),
    f"with {OP} select i, max(j) m, cast(1 << length(bin(max(j) - 1)) as bigint) width from op group by i having max(j) > 1")
add("f12_key_index", lambda s, d: B.index_keys(s.read.parquet(f"{d}/part.parquet"), "p_name"),
    "select distinct p_name \"key\", dense_rank() over (order by p_name) - 1 id from part where p_name is not null")

# ---- setup

add("s12_intermediate_rows", lambda s, d: B.intermediate_rows(*pair(s, d)), INTER + "select i, count(*) n_inter, min(j) jmin, max(j) jmax from x group by 1")


def _categories(s, d):
    a, b = pair(s, d)
    return B.categorize(a, b, P.plan_chunks(b.n_cols, TOY, T.TYPES), TOY, T.TYPES)


_CAT = INTER + (", r as (select i, count(*) n_inter, min(j) jmin, max(j) jmax from x group by 1), t as (select *, case when n_inter < 256 then 'sort' "
                "when (jmax - jmin + 1) * 9 <= 2048 then 'dense' when (select max(p_partkey) + 1 from part) <= 512 then 'fine' else 'coarse' end category from r) ")
_SQCAT = (f"with {PP}, r as (select a.i, count(*) n_inter, min(b.j) jmin, max(b.j) jmax from pp a join pp b on a.j = b.i group by 1), t as (select *, case when n_inter < 256 then 'sort' "
          "when (jmax - jmin + 1) * 9 <= 2048 then 'dense' when (select max(p_partkey) + 1 from part) <= 512 then 'fine' else 'coarse' end category from r) ")
add("s14_categories", _categories, _CAT + "select * from t")
add("s15_census", lambda s, d: B.census(_categories(s, d)), _CAT + "select category, count(*) n_rows, cast(sum(n_inter) as bigint) products from t group by 1")


def _square_rows(s, d, category="coarse"):
    a = S.next_part(s, d)
    return B.categorize(a, a, P.plan_chunks(a.n_cols, TOY, T.TYPES), TOY, T.TYPES).where(F.col("category") == category)


add("s17_coarse_volume", lambda s, d: B.coarse_volume(_square_rows(s, d)), _SQCAT + "select cast(coalesce(sum(n_inter), 0) as bigint) products, cast(coalesce(sum(n_inter), 0) * 16 as bigint) bytes from t where category = 'coarse'")
add("s18_batches", lambda s, d: B.batches(B.intermediate_rows(*pair(s, d)), 10_000),
    INTER + ", r as (select i, count(*) n_inter from x group by 1) select i, n_inter, cast(floor((sum(n_inter) over (order by i) - n_inter) / 10000) as bigint) batch_id from r")
add("s18_two_limits", lambda s, d: B.coarse_batches(B.intermediate_rows(*pair(s, d)), T.TYPES, 1 << 20, 1 << 16, P.coarse_counter_bytes(4, TOY, T.TYPES)),
    INTER + ", r as (select i, count(*) n_inter, cast(greatest(ceil(count(*) * 16 * 1000000 / 1048576), 8301) as bigint) w from x group by 1) "
    "select i, n_inter, cast(floor((sum(w) over (order by i) - w) / 1000000) as bigint) batch_id from r")


def _closed_forms(spark, d):
    rows = []
    for spec in (P.SKX, P.SPR, P.EMR):
        for phase in ("numeric", "symbolic"):
            for log in range(10, 45, 2):
                w, t = 1 << log, P.TypeSizes()
                rows.append((spec.name, phase, log, P.dense_slot_bytes(phase, t), P.fine_chunk_bytes(spec, t), P.optimal_fine_chunks(w, spec, t, phase),
                             float(P.min_fine_storage(w, spec, t, phase)), P.max_fine_columns(spec, t, phase)))
    return spark.createDataFrame(rows, "machine string, phase string, log_columns long, slot_bytes long, chunk_bytes long, best_count long, least_bytes double, widest long")


def _plans(spark, d):
    rows = []
    for spec in (P.SKX, P.SPR, P.EMR):
        for phase in ("numeric", "symbolic"):
            for log in range(10, 45, 2):
                plan = P.plan_chunks(1 << log, spec, P.TypeSizes(), phase)
                rows.append((spec.name, phase, log, plan.level, plan.n_coarse, plan.n_fine, plan.shift_coarse, plan.shift_fine))
    return spark.createDataFrame(rows, "machine string, phase string, log_columns long, level string, n_coarse long, n_fine long, shift_coarse long, shift_fine long")


_FORMS = ("with g as (select machine, l2, phase, slot, cast(r.range as bigint) log_columns, cast(1 as bigint) << r.range w from (values ('SKX', 1048576), ('SPR', 2097152), ('EMR', 2097152)) m(machine, l2), "
          "(values ('numeric', 5), ('symbolic', 1)) p(phase, slot), range(10, 45, 2) r), "
          "f as (select *, 2 * sqrt(cast(w as double) * slot * 136) least_bytes, cast(1 as bigint) << cast(floor(log2(cast(l2 as double) * l2 / (4 * slot * 136))) as int) widest, "
          "least(cast(1 as bigint) << cast(greatest(0, round(log2(sqrt(cast(w as double) * slot / 136)))) as int), w) best_count from g) ")
add("s4_closed_forms", _closed_forms, _FORMS + "select machine, phase, log_columns, cast(slot as bigint) slot_bytes, cast(136 as bigint) chunk_bytes, best_count, least_bytes, widest from f")
add("s10_plans", _plans, _FORMS + ", h as (select *, case when least_bytes < l2 then w else least(w, widest) end inside from f), k as (select *, "
    "least(cast(1 as bigint) << cast(greatest(0, round(log2(sqrt(cast(inside as double) * slot / 136)))) as int), inside) n_fine from h) "
    "select machine, phase, log_columns, case when inside < w then 'coarse' else 'fine' end level, w // inside n_coarse, n_fine, cast(log2(inside) as bigint) shift_coarse, cast(log2(inside // n_fine) as bigint) shift_fine from k")


def _storage(spark, d):
    """The storage curve, as expressions over the counts."""
    n = F.expr("shiftleft(1L, cast(id as int))")
    width, slot, chunk = 1 << 29, P.dense_slot_bytes("numeric", P.TypeSizes()), P.fine_chunk_bytes(P.SPR, P.TypeSizes())
    return spark.range(21).select(F.col("id").alias("log_chunks"), (F.lit(float(width * slot)) / n + n * chunk).alias("bytes"))


add("s3_storage_sweep", _storage, "select r.range log_chunks, cast(2684354560 as double) / (1 << r.range) + cast((1 << r.range) * 136 as double) bytes from range(21) r")
add("s20_task_spec", lambda s, d: s.createDataFrame([(x.name, x.l2_bytes, x.line_bytes, P.plan_chunks(1 << 40, x, T.TYPES).n_coarse) for x in [P.spec_from_spark(s)]], "name string, bytes long, line long, n_coarse long"))

# ---- building blocks

_X64 = INTER + ", h as (select i, j >> 6 chunk, count(*) cnt from x group by 1, 2) "
add("p1_histogram", lambda s, d: B.histogram(B.expand(*pair(s, d)), 6), _X64 + "select * from h")
add("p1b_histogram_by_length", lambda s, d: B.histogram_by_length(B.expand(*pair(s, d)), 60), INTER + "select i, cast(floor(j / 60) as bigint) chunk, count(*) cnt from x group by 1, 2")
add("p2_prefix_sum", lambda s, d: B.prefix_sum(B.histogram(B.expand(*pair(s, d)), 6), ["i"], "chunk", "cnt"),
    _X64 + "select i, chunk, cnt, cast(sum(cnt) over w - cnt as bigint) \"start\", cast(sum(cnt) over w as bigint) \"end\" from h window w as (partition by i order by chunk)")
add("p2b_offsets_across", lambda s, d: B.offsets_across(B.histogram(B.expand(*pair(s, d)), 6), "chunk", "i", "cnt"),
    _X64 + "select chunk, i, cnt, cast(sum(cnt) over (order by chunk, i) - cnt as bigint) \"start\" from h")
add("p3_reorder", lambda s, d: B.reorder(B.expand(*pair(s, d)), 6),
    INTER + "select i, j >> 6 chunk, row_number() over (partition by i, j >> 6 order by j, k) - 1 pos, j - ((j >> 6) << 6) local_j, p from x")
add("p4_shift_and_back", lambda s, d: B.reorder(B.expand(*pair(s, d)), 6).groupBy("i", B.to_global(F.col("chunk"), F.col("local_j"), 6).alias("j")).agg(F.sum("p").alias("v")), COP + "select * from c")
add("p5_rowwise", lambda s, d: B.expand(*pair(s, d)).select("i", "k", "j", "p"), INTER + "select i, k, j, p from x")
add("p6_outer", lambda s, d: T.coarse_pairs(*pair(s, d), T.chunk_plan(1 << 11, TOY, "numeric", T.Options())).select("i", "j", "p"), INTER + "select i, j, p from x")

# ---- products, all on co-purchase

for _name, _method in {
    "m1_rowwise_dense": M.rowwise_dense, "m1b_relational": M.relational, "m2_expand_sort_compress": M.expand_sort_compress,
    "m4_fine_level": lambda a, b: T.fine_level(a, b, FINE), "m4b_fine_level_sql": M.fine_level_sql, "m6_coarse_fine": lambda a, b: T.coarse_fine(a, b, TOY),
    "m6_batches": lambda a, b: T.coarse_fine(a, b, TOY, T.Options(batch_bytes=1 << 18)),
    "m7_two_level": T.two_level, "m7_two_level_toy": lambda a, b: T.two_level(a, b, TOY), "m7_salted": lambda a, b: T.two_level(a, b, TOY, T.Options(hub_products=64)),
    "m8_no_coarse": lambda a, b: T.two_level(a, b, TOY, T.Options(coarse=False)), "m8b_no_categories": lambda a, b: T.two_level(a, b, TINY, T.Options(categorize=False)),
    "m8b_sort_only": lambda a, b: T.fine_level(a, b, FINE, T.Options(accumulator="sort")), "m8b_dense_only": lambda a, b: T.fine_level(a, b, FINE, T.Options(accumulator="dense")),
    "m8b_no_packing": lambda a, b: T.fine_level(a, b, FINE, T.Options(pack=False)), "m8b_fixed_chunks": lambda a, b: T.fine_level(a, b, FINE, T.Options(n_fine=4)),
    "m9_segmented_b": M.segmented_b, "m10_hash": M.hash_product, "m11_heap": M.heap_product, "m13_plus_times": M.semiring, "m14_portable_sql": M.portable_sql,
    "m15_outer": M.outer_product, "m15b_blocked_outer": M.blocked_outer, "m17_broadcast": M.broadcast_product, "m18_grid": M.grid, "m20_auto": M.product,
}.items():
    add(_name, lambda spark, d, method=_method: method(*pair(spark, d)).df, COP + "select * from c")

add("m3_symbolic", lambda s, d: M.symbolic(*pair(s, d)), COP + "select i, count(*) nnz from c group by 1")
add("m3b_symbolic_chunks", lambda s, d: T.symbolic_phase(*pair(s, d), TINY), COP + "select i, count(*) nnz from c group by 1")
add("m3_result_pointers", lambda s, d: T.result_pointers(*pair(s, d), TOY),
    COP + ", n as (select r.range i, count(c.j) c from range((select max(p_partkey) + 1 from part)) r left join c on c.i = r.range group by 1) " + _POINTERS)
add("m3c_estimate", lambda s, d: M.symbolic_estimate(*pair(s, d)))
add("m5_coarse_level", lambda s, d: T.coarse_level(a := S.next_part(s, d), a, TOY),
    f"with {PP}, n as (select cast(floor(b.j / (case when (select max(p_partkey) + 1 from part) <= 512 then 1 << 30 else 512 end)) as bigint) coarse, a.i, count(*) n from pp a join pp b on a.j = b.i group by 1, 2) "
    "select coarse, i, n, cast(sum(n) over (order by coarse, i) - n as bigint) \"start\" from n")
add("m6_customer_part", lambda s, d: T.two_level(S.customer_order(s, d), S.order_part(s, d)).df,
    f"with {OP} select o_custkey i, j, cast(sum(v) as bigint) v from orders join op on o_orderkey = i group by 1, 2")
add("m7_square", lambda s, d: T.two_level(a := S.next_part(s, d), a, TOY).df, SQUARE + "select * from c")
add("m7_square_fine", lambda s, d: T.two_level(a := S.next_part(s, d), a, FINE).df, SQUARE + "select * from c")
add("m1b_square", lambda s, d: M.relational(a := S.next_part(s, d), a).df, SQUARE + "select * from c")
add("m7_report", lambda s, d: T.report(a := S.next_part(s, d), a, TOY).drop("n_coarse", "n_fine"),
    _SQCAT + "select category, count(*) n_rows, cast(sum(n_inter) as bigint) products, case when (select max(p_partkey) + 1 from part) <= 512 then 'fine' else 'coarse' end level from t group by 1")
add("m8_square_no_coarse", lambda s, d: T.two_level(a := S.next_part(s, d), a, TOY, T.Options(coarse=False)).df, SQUARE + "select * from c")
add("m9_segment_summary", lambda s, d: M.segment_summary(S.part_supplier(s, d)).select("i", F.col("seg").cast("long").alias("seg"), "cnt", "first_j"),
    "with ps as (select distinct l_partkey i, l_suppkey j from lineitem) select i, cast(floor(j / ((select max(s_suppkey) + 8 from supplier) // 8)) as bigint) seg, count(*) cnt, min(j) first_j from ps group by 1, 2")
add("m12_library", lambda s, d: M.library_product(a := S.part_supplier(s, d).transpose(), a.transpose()).df,
    f"with {PS} select a.j i, b.j j, cast(sum(a.v * b.v) as bigint) v from ps a join ps b on a.i = b.i group by 1, 2")
_SEMI = f"with {OP} select a.j i, b.j j, {{}} v from op a join op b on a.i = b.i group by 1, 2"
add("m13_min_plus", lambda s, d: M.semiring(*pair(s, d), "min_plus").df, _SEMI.format("min(a.v + b.v)"))
add("m13_max_min", lambda s, d: M.semiring(*pair(s, d), "max_min").df, _SEMI.format("max(least(a.v, b.v))"))
add("m13_or_and", lambda s, d: M.semiring(*pair(s, d), "or_and").df, _SEMI.format("cast(bool_or(a.v <> 0 and b.v <> 0) as bigint)"))
add("m13_plus_pair", lambda s, d: M.semiring(*pair(s, d), "plus_pair").df, _SEMI.format("count(*)"))
add("m16_masked", lambda s, d: M.masked(a := S.next_part(s, d), a, a).df, SQUARE + "select * from c where exists (select 1 from pp where pp.i = c.i and pp.j = c.j)")
add("m19_gram", lambda s, d: M.gram(S.order_part(s, d)).df, COP + "select * from c")
add("m19_triple", lambda s, d: M.triple((p := S.part_supplier(s, d, True)).transpose(), S.next_part(s, d), p).df,
    f"with {PS}, {PP}, x as (select ps.j i, pp.j j, sum(ps.v * pp.v) v from ps join pp on ps.i = pp.i group by 1, 2) "
    "select x.i, ps.j, cast(sum(x.v * ps.v) as bigint) v from x join ps on x.j = ps.i group by 1, 2")
