"""Connected components of an edge table by alternating large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.llm.common import Scratch


def _star(edges: DataFrame, large: bool) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))) if large else edges.select(
        F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("low"))
    moved = both.join(low, "u")
    if large:
        out = moved.where("v > u").select(F.col("v").alias("u"), F.col("low").alias("v"))
    else:
        out = moved.select(F.col("v").alias("u"), F.col("low").alias("v")).unionByName(low.select("u", F.col("low").alias("v")))
    return out.where("u <> v").distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, component) for every node of ``edges`` (u, v long) that is not its component's smallest node. Of the tables
    written on the way only the last stays."""
    scratch = Scratch(edges.sparkSession)
    edges = scratch.write(edges.where("u <> v").distinct(), "cc_edges")
    mark = None
    while True:
        edges = scratch.write(_star(_star(edges, True), False), "cc_edges")
        scratch.clear(but=1)
        now = edges.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))")).first()
        if now == mark:
            return edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
        mark = now
