"""Registered queries against their SQL in DuckDB, and properties of the closed forms."""

import glob
import os
import re

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from sparsetier import queries
from sparsetier.functions import measures as C
from sparsetier.functions import params as P
from sparsetier.operators import accumulators as A
from sparsetier.operators import blocks as B
from sparsetier.plans import kernel as K
from sparsetier.plans import products as M
from sparsetier.plans import two_level as T
from sparsetier.sources import files
from sparsetier.sources import matrices as S

DATA = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for path in glob.glob(f"{DATA}/*.parquet"):
        con.sql(f"create view {os.path.basename(path)[:-8]} as select * from '{path}'")
    return con


def rounded(row):
    return tuple((v is not None, round(v, 9) if isinstance(v, float) else v) for v in row)


def same_rows(got, want):
    """Rows as multisets, nulls included, whole numbers and floats alike."""
    order = lambda rows: sorted(map(rounded, rows), key=lambda r: tuple((x, str(type(v)) if isinstance(v, str) else "", v if x else 0) for x, v in r))
    return order(got) == order(want)


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_query_equals_sql(spark, duck, name):
    got = queries.queries()[name](spark, DATA)
    want = duck.sql(queries.oracle_sql()[name])
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    place = [want.columns.index(c) for c in cols]
    rows = got.select(*(f"`{c}`" for c in cols)).collect()
    assert same_rows(rows, [tuple(r[p] for p in place) for r in want.fetchall()])


#: Win rates are tested below; these two run all methods over again.
AGAIN = {"c17_win_rate", "w4_win_rate"}


@pytest.mark.parametrize("name", sorted(n for n in queries.queries() if n not in queries.oracle_sql() and n not in AGAIN))
def test_measure_gives_rows(spark, name):
    """Timings and estimates have no SQL; they give rows of a stable schema."""
    got = queries.queries()[name](spark, DATA)
    assert got.columns and got.count() > 0


# ---- the two-level product meets all of its categories


@pytest.mark.parametrize("spec, level", [(P.TOY, "coarse"), (P.TOY_FINE, "fine")])
def test_mixed_matrix_has_rows_of_every_category(spark, spec, level):
    a = S.mixed_matrix(spark)
    found = {r.category: r.n_rows for r in T.report(a, a, spec).collect()}
    assert set(found) == {"sort", "dense", level} and min(found.values()) >= 0.1 * sum(found.values())


@pytest.mark.parametrize("options", [T.Options(), T.Options(accumulator="sort"), T.Options(accumulator="dense"), T.Options(pack=False), T.Options(categorize=False), T.Options(n_fine=2), T.Options(hub_products=8)])
def test_options_agree(spark, options):
    a = S.power_law_matrix(spark, 7)
    tiny = P.SystemSpec("tiny", 700)
    want = sorted(map(tuple, M.relational(a, a).df.collect()))
    assert sorted(map(tuple, T.two_level(a, a, tiny, options).df.collect())) == want


def test_small_parts_and_splits_agree(spark, monkeypatch):
    """Rows dealt in pieces, merged in parts and carried on: every limit of the kernel at its smallest."""
    monkeypatch.setattr(T, "SPLIT", 16)
    monkeypatch.setattr(K, "WORK", 64)
    monkeypatch.setattr(K, "CARRY", 96)
    a = S.power_law_matrix(spark, 6)
    for spec in (P.SystemSpec("tiny", 700), P.TOY_FINE):
        assert sorted(map(tuple, T.two_level(a, a, spec).df.collect())) == sorted(map(tuple, M.relational(a, a).df.collect()))


def cells(spark, rows, n=8, m=8, value="long"):
    return S.SparseMatrix(spark.createDataFrame(rows, f"i long, j long, v {value}"), n, m)


def test_edges(spark):
    """Empty matrices, no match, one cell, cancelling values (the zero stays stored), indices over 2**32, doubles."""
    empty, one = cells(spark, []), cells(spark, [(3, 3, 5)])
    far = cells(spark, [(0, 1 << 33, 2), (1, 1 << 33, 3)], 2, 1 << 34)
    wide = cells(spark, [(1 << 33, 1 << 34, 7)], 1 << 34, 1 << 35)
    half = cells(spark, [(0, 0, 0.5), (0, 1, 0.25)], value="double")
    cancel = (cells(spark, [(0, 0, 1), (0, 1, 1)]), cells(spark, [(0, 5, 1), (1, 5, -1)]))
    for method in (T.two_level, M.expand_sort_compress, M.segmented_b, M.hash_product, M.outer_product, M.relational, lambda a, b: T.fine_level(a, b, P.TOY)):
        run = lambda a, b: sorted(map(tuple, method(a, b).df.collect()))
        assert run(empty, one) == run(one, empty) == run(empty, empty) == [] == run(one, cells(spark, [(2, 2, 1)]))
        assert run(one, one) == [(3, 3, 25)]
        assert run(*cancel) == [(0, 5, 0)]
        assert run(far, wide) == [(0, 1 << 34, 14), (1, 1 << 34, 21)]
        assert run(half, cells(spark, [(0, 2, 3), (1, 2, 4)])) == [(0, 2, 2.5)]


def test_worked_example(spark):
    a = cells(spark, [(0, 1, 2), (0, 4, 1), (0, 6, 3), (1, 0, 1), (1, 4, 2), (7, 7, 1)])
    b = cells(spark, [(0, 1, 1), (0, 6, 2), (1, 0, 1), (1, 3, 2), (1, 7, 1), (4, 2, 1), (4, 3, 1), (4, 5, 2), (6, 0, 3), (6, 4, 1), (6, 6, 1), (6, 7, 2), (7, 7, 5)])
    rows = cells(spark, [r for r in [(0, 1, 2), (0, 4, 1), (0, 6, 3), (1, 0, 1), (1, 4, 2)]])
    assert sorted(r.i for r in B.needed_rows(rows).collect()) == [0, 1, 4, 6]
    pairs = B.expand(rows, b)
    assert [tuple(r) for r in B.histogram(pairs, 2).orderBy("i", "chunk").collect()] == [(0, 0, 5), (0, 1, 5), (1, 0, 3), (1, 1, 2)]
    assert [r.cnt for r in B.histogram(pairs, 1).orderBy("i", "chunk").collect()] == [2, 3, 2, 3, 1, 2, 1, 1]
    assert [r.start for r in B.offsets_across(B.histogram(pairs, 2), "i", "chunk", "cnt").orderBy("start").collect()] == [0, 5, 10, 13]
    want = [(0, 0, 11), (0, 2, 1), (0, 3, 5), (0, 4, 3), (0, 5, 2), (0, 6, 3), (0, 7, 8), (1, 1, 1), (1, 2, 2), (1, 3, 2), (1, 5, 4), (1, 6, 2), (7, 7, 5)]
    assert sorted(map(tuple, T.two_level(a, b).df.collect())) == sorted(map(tuple, T.coarse_fine(a, b, P.SystemSpec("t", 600)).df.collect())) == want
    assert [tuple(r) for r in T.result_pointers(a, b).orderBy("i").select("start").collect()] == [(0,), (7,), (12,), (12,), (12,), (12,), (12,), (12,)]


# ---- plans


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark):
    """The two-level product deals its pairs in one exchange and joins A with B once; expand-sort-compress keeps its sort."""
    a = S.mixed_matrix(spark)
    text = plan_of(T.two_level(a, a, P.TOY).df)
    assert text.count("MapInArrow") == 1 and text.count("REPARTITION_BY_COL") == 1
    text = plan_of(M.expand_sort_compress(a, a).df)
    assert re.search(r"MapInArrow[^\n]*\n\s*\+- \*?(\(\d+\) )?Sort \[i", text) and "REPARTITION_BY_COL" in text
    pruned = plan_of(queries.queries()["o1_scan"](spark, DATA))
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThanOrEqual(l_quantity,25.0)]" in pruned and "l_tax" not in pruned


# ---- accumulators


@pytest.mark.parametrize("size", [0, 1, 31, 255, 256, 257, 2000])
def test_accumulators_agree(size):
    rng = np.random.default_rng(size)
    cols, vals = rng.integers(0, 512, size), rng.integers(-5, 6, size)
    want = [(c, int(vals[cols == c].sum())) for c in sorted(set(cols.tolist()))]
    for name, kernel in A.REGISTRY.items():
        got = kernel.merge(cols, vals, 512)
        assert list(zip(*(x.tolist() for x in got))) == want, name
    runs = [(np.sort(cols[s]), vals[s][np.argsort(cols[s], kind="stable")]) for s in np.array_split(np.arange(size), 7)]
    assert [(int(c), int(v)) for c, v in zip(*A.accumulate_heap(runs))] == want
    assert A.accumulate_symbolic(cols, 512) == len(want)
    buffer = A.DenseBuffer(np.int64)
    seg = np.sort(rng.integers(0, 9, size))
    dense, ordered = A.dense_many(seg, cols, vals, buffer, 700), A.sort_many(seg, cols, vals)
    assert [x.tolist() for x in dense] == [x.tolist() for x in ordered] and not buffer.values.any() and not buffer.seen.any()


def test_sorting_network():
    x = np.random.default_rng(3).integers(0, 50, 64)
    assert A.bitonic_sort(x).tolist() == sorted(x.tolist())


def test_packs():
    rng = np.random.default_rng(4)
    counts = rng.integers(1, 60, 200).tolist() + [300, 5, 300]
    packs = A.pack_chunks(counts)
    assert packs == sorted(packs) and set(packs) == set(range(packs[-1] + 1))
    for n, c in enumerate(counts):
        if c >= A.THRESHOLD:
            assert packs.count(packs[n]) == 1


def test_greedy_batches():
    rows = [(n, s) for n, s in enumerate([5, 5, 5, 20, 1, 1, 1, 1])]
    assert B.greedy_batches(rows, 10, 3) == [0, 0, 1, 2, 3, 3, 3, 4]


def test_sketch_is_near(spark):
    rows = queries.queries()["m3c_estimate"](spark, DATA).collect()
    exact = {r.i: r.nnz for r in queries.queries()["m3_symbolic"](spark, DATA).collect()}
    assert all(abs(r.estimate - exact[r.i]) <= max(3, 0.2 * exact[r.i]) and r.upper >= exact[r.i] for r in rows)


def test_coordinate_text_file(spark, tmp_path):
    path = tmp_path / "m.txt"
    path.write_text("% a comment\n3 4 4\n1 1 5\n3 4 4\n2 3 -1\n1 2 7\n")
    want = [(0, 0, 5), (0, 1, 7), (1, 2, -1), (2, 3, 4)]
    m = files.read_coordinate_text(spark, str(path))
    assert (m.n_rows, m.n_cols) == (3, 4) and sorted(map(tuple, m.df.collect())) == want
    spark.dataSource.register(files.CoordinateTextSource)
    assert sorted(map(tuple, spark.read.format("coordinate_text").option("piece_bytes", 7).load(str(path)).collect())) == want


def test_bucketed_join_needs_no_exchange(spark):
    a = S.banded_matrix(spark, 200, 2)
    left, right = files.write_bucketed(a, "bucketed_a", "j"), files.write_bucketed(a, "bucketed_b", "i")
    joined = left.hint("merge").join(right.withColumnRenamed("i", "k").withColumnRenamed("j", "j2"), left.j == F.col("k"))
    assert "Exchange" not in plan_of(joined)
    for name in ("bucketed_a", "bucketed_b"):
        spark.sql(f"drop table {name}")


def test_win_rate(spark):
    times = spark.createDataFrame([("a", "x", 1.0, "ok"), ("a", "y", 2.0, "ok"), ("b", "x", 3.0, "ok"), ("b", "y", 2.0, "ok"), ("c", "x", 1.0, "ok"), ("c", "y", None, "MemoryError")], "case string, method string, seconds double, status string")
    assert tuple(C.win_rate(times, "x").first()) == (3, 2, pytest.approx(2 / 3), 1.5)


# ---- closed forms

@pytest.mark.parametrize("width", [1 << n for n in range(4, 31, 3)])
@pytest.mark.parametrize("phase", ["numeric", "symbolic"])
def test_chunk_count_is_the_argmin(width, phase):
    types = P.TypeSizes()
    best = min((1 << n for n in range(31)), key=lambda n: P.fine_storage(width, n, P.SPR, types, phase))
    assert P.optimal_fine_chunks(width, P.SPR, types, phase) == min(best, width)


def test_published_crossovers():
    types = P.TypeSizes()
    assert P.max_fine_columns(P.SKX, types) == 1 << 28 and P.max_fine_columns(P.SPR, types) == 1 << 30
    assert P.max_fine_columns(P.SKX, types, "symbolic") == 1 << 30 and P.max_fine_columns(P.SPR, types, "symbolic") == 1 << 32
