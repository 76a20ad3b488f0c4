"""User-defined functions, aggregates and table functions, and the SQL surface."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType, StructField, StructType


@F.pandas_udf(LongType())
def chunk_of(j: pd.Series, shift: pd.Series) -> pd.Series:
    return j // (2 ** shift)


@F.pandas_udf(LongType())
def dense_chunk_sum(local: pd.Series, values: pd.Series) -> int:
    """Sum of the squares of a chunk's merged cells: an aggregate that needs the dense buffer."""
    return int((np.bincount(local, weights=values) ** 2).sum()) if len(local) else 0


@F.pandas_udf(ArrayType(LongType()))
def dense_rows_sum(row: pd.Series, local: pd.Series, values: pd.Series) -> list:
    """The sums of ``dense_chunk_sum`` of all rows of a block in one call: (row, sum) one behind the other. Sums are of whole numbers
    throughout; as in SQL a row without any value has none."""
    found, at = np.unique(row.to_numpy(), return_inverse=True)
    there = values.notna().to_numpy()
    width = int(local.max()) + 1
    buffer = np.zeros((len(found), width), dtype=np.int64)
    np.add.at(buffer, (at[there], local.to_numpy()[there]), values[there].astype("int64").to_numpy())
    some = np.bincount(at[there], minlength=len(found)) > 0
    return [x for r, q, s in zip(found.tolist(), (buffer * buffer).sum(axis=1).tolist(), some.tolist()) for x in (r, q if s else None)]


def row_sums(cells: DataFrame, width: int, block: int = 12) -> DataFrame:
    """(i, q): ``dense_rows_sum`` of the cells (i, j, v) over columns modulo ``width``, a power of two; one call for a block of rows,
    as a call for each row costs far more than its sum."""
    sums = cells.groupBy(F.shiftright("i", block).alias("rb")).agg(dense_rows_sum("i", F.col("j").bitwiseAND(width - 1), "v").alias("s"))
    pairs = F.transform(F.sequence(F.lit(1), F.size("s"), F.lit(2)), lambda k: F.struct(F.element_at("s", k).alias("i"), F.element_at("s", k + 1).alias("q")))
    return sums.select(F.inline(pairs))


@F.udtf(returnType=StructType([StructField("j", LongType()), StructField("v", LongType())]))
class ExpandRow:
    def eval(self, cols: list, vals: list):
        yield from zip(cols or [], vals or [])


@F.udtf(returnType=StructType([StructField("i", LongType()), StructField("j", LongType())]))
class BandedEntries:
    """Cells of a band of half width ``half`` in an n x n matrix; one call per row keeps it distributed."""

    def eval(self, i: int, n: int, half: int):
        for j in range(max(0, i - half), min(n, i + half + 1)):
            yield i, j


def register(spark: SparkSession) -> None:
    spark.udf.register("chunk_of", chunk_of)
    spark.udtf.register("expand_row", ExpandRow)
    spark.udtf.register("banded_entries", BandedEntries)


PRODUCT_SQL = "select a.i, b.j, sum(a.v * b.v) as v from {a} a join {b} b on a.j = b.i group by a.i, b.j"
SYMBOLIC_SQL = "select a.i, count(distinct b.j) as nnz from {a} a join {b} b on a.j = b.i group by a.i"
CATEGORY_SQL = ("select i, n_inter, case when n_inter < :least then 'sort' when (jmax - jmin + 1) * :slot <= :cache then 'dense' else :level end as category from "
                "(select a.i, sum(b.c) as n_inter, min(b.lo) as jmin, max(b.hi) as jmax from {a} a join (select i, count(*) c, min(j) lo, max(j) hi from {b} group by i) b on a.j = b.i group by a.i)")


def product_sql(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.sparkSession.sql(PRODUCT_SQL, a=a, b=b)


def symbolic_sql(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.sparkSession.sql(SYMBOLIC_SQL, a=a, b=b)
