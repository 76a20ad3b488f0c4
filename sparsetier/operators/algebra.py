"""Element-wise and structural operators on coordinate matrices."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.sources.matrices import SparseMatrix


def _like(m: SparseMatrix, df: DataFrame) -> SparseMatrix:
    return SparseMatrix(df, m.n_rows, m.n_cols)


def scale(m: SparseMatrix, c) -> SparseMatrix:
    return _like(m, m.df.select("i", "j", (F.col("v") * c).alias("v")))


def hadamard(a: SparseMatrix, b: SparseMatrix) -> SparseMatrix:
    return _like(a, a.df.join(b.df.withColumnRenamed("v", "w"), ["i", "j"]).select("i", "j", (F.col("v") * F.col("w")).alias("v")))


def combine(a: SparseMatrix, b: SparseMatrix, sign: int = 1) -> SparseMatrix:
    """a + sign * b; cells that cancel stay stored."""
    return _like(a, a.df.unionByName(scale(b, sign).df).groupBy("i", "j").agg(F.sum("v").alias("v")))


def band(m: SparseMatrix, width: int) -> SparseMatrix:
    return _like(m, m.df.where(F.abs(F.col("i") - F.col("j")) <= width))


def triangle(m: SparseMatrix, upper: bool = True, strict: bool = True) -> SparseMatrix:
    i, j = (F.col("i"), F.col("j")) if upper else (F.col("j"), F.col("i"))
    return _like(m, m.df.where(i < j if strict else i <= j))


def prune(m: SparseMatrix, least) -> SparseMatrix:
    return _like(m, m.df.where(F.col("v") >= least))


def submatrix(m: SparseMatrix, i0: int, i1: int, j0: int, j1: int) -> SparseMatrix:
    """Rows i0 … i1 - 1 and columns j0 … j1 - 1, numbered from 0."""
    inside = m.df.where((F.col("i") >= i0) & (F.col("i") < i1) & (F.col("j") >= j0) & (F.col("j") < j1))
    return SparseMatrix(inside.select((F.col("i") - i0).alias("i"), (F.col("j") - j0).alias("j"), "v"), i1 - i0, j1 - j0)


def diagonal(m: SparseMatrix) -> DataFrame:
    return m.df.where("i = j").select("i", "v")


def trace(m: SparseMatrix) -> DataFrame:
    return diagonal(m).agg(F.coalesce(F.sum("v"), F.lit(0)).alias("trace"))


def normalized(m: SparseMatrix, axis: str = "i") -> DataFrame:
    """(i, j, v, total, share): each cell beside the sum of its row (axis i) or column (axis j)."""
    totals = m.df.groupBy(axis).agg(F.sum("v").alias("total"))
    return m.df.join(totals, axis).select("i", "j", "v", "total", F.try_divide(F.col("v"), F.col("total")).alias("share"))


def norms(m: SparseMatrix) -> DataFrame:
    """(frobenius2, max_row_sum, max_col_sum)."""
    size = F.abs("v")
    by = m.df.agg(F.sum(F.col("v") * F.col("v")).alias("x")).select(F.lit(0).alias("g"), "x")
    rows = m.df.groupBy("i").agg(F.sum(size).alias("x")).agg(F.max("x").alias("x")).select(F.lit(1).alias("g"), "x")
    cols = m.df.groupBy("j").agg(F.sum(size).alias("x")).agg(F.max("x").alias("x")).select(F.lit(2).alias("g"), "x")
    return by.unionByName(rows).unionByName(cols).agg(*(F.max(F.when(F.col("g") == n, F.col("x"))).alias(name) for n, name in enumerate(("frobenius2", "max_row_sum", "max_col_sum"))))


def triangle_count(m: SparseMatrix) -> DataFrame:
    """(triangles) of the simple undirected graph of a matrix: ordered paths i < j < k closed by an edge, the mask applied in the join."""
    edges = m.df.where("i <> j").select(F.least("i", "j").alias("i"), F.greatest("i", "j").alias("j")).distinct()
    paths = edges.select("i", F.col("j").alias("k")).join(edges.select(F.col("i").alias("k"), "j"), "k")
    return paths.join(edges, ["i", "j"], "left_semi").agg(F.count("*").alias("triangles"))
