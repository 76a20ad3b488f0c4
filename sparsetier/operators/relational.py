"""Relational operators around matrices: joins by range and time, top-k, ranks, pivots."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def range_join(points: DataFrame, ranges: DataFrame, keys: list[str], at: str, start: str, end: str) -> DataFrame:
    """Points to the range [start, end) of their keys they lie in; the equi part keeps it a sort-merge join."""
    r = ranges.select(*(F.col(k).alias(f"_{k}") for k in keys), *(c for c in ranges.columns if c not in keys))
    on = [F.col(k) == F.col(f"_{k}") for k in keys] + [F.col(at) >= F.col(start), F.col(at) < F.col(end)]
    return points.join(r, on).drop(*(f"_{k}" for k in keys))


def as_of(left: DataFrame, right: DataFrame, key: str, order: list[str], value: str) -> DataFrame:
    """Left rows with the last ``value`` of the right rows of the same key at or before them, by a window over the union."""
    both = left.select(key, *order, F.lit(1).alias("side"), F.lit(None).cast(right.schema[value].dataType).alias(value)).unionByName(
        right.select(key, *order, F.lit(0).alias("side"), value))
    w = Window.partitionBy(key).orderBy(order[0], "side", *order[1:]).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("last", F.last(value, ignorenulls=True).over(w)).where("side = 1").select(key, *order, F.col("last").alias(value))


def top_per_row(df: DataFrame, k: int) -> DataFrame:
    """The k largest cells of each row, smaller columns first among equals."""
    w = Window.partitionBy("i").orderBy(F.desc("v"), "j")
    return df.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)


def row_blocks(rows: DataFrame, work: str, blocks: int) -> DataFrame:
    """(i, work, block): rows dealt to blocks of about equal work by its prefix sum."""
    from sparsetier.operators.blocks import prefix_sum

    tagged = rows.withColumn("rb", F.floor(F.col("i") / 4096))
    totals = prefix_sum(tagged.groupBy("rb").agg(F.sum(work).alias("t")).withColumn("one", F.lit(0)), ["one"], "rb", "t")
    whole = totals.agg(F.max("end").alias("whole"))
    placed = prefix_sum(tagged, ["rb"], "i", work).join(totals.select("rb", F.col("start").alias("base")), "rb").join(F.broadcast(whole))
    return placed.select("i", work, F.floor((F.col("start") + F.col("base")) * blocks / F.col("whole")).alias("block"))
