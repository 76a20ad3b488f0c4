"""Streams over files of events and orders. Every function takes and returns streaming DataFrames; ``drained`` runs one to the end of
its input and returns what it wrote."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from sparsetier.sources.matrices import SparseMatrix, instant
from sparsetier.store import Scratch


def source(spark: SparkSession, sf_dir: str, table: str, files_per_trigger: int = 8) -> DataFrame:
    """A stream over the Parquet files of a table."""
    schema = spark.read.parquet(f"{sf_dir}/{table}.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{sf_dir}/{table}.parquet*")


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return source(spark, sf_dir, "events").withColumn("ts", instant(F.col("ts")))


def drained(stream: DataFrame, mode: str, checkpoint: str | None = None, out: str | None = None) -> DataFrame:
    """Run a stream over all that is there, then stop. Each batch is a folder of its own, so that a batch that is run again
    overwrites itself; in complete mode the last one is the result, in update mode ``batch`` tells which row is newest."""
    spark, scratch = stream.sparkSession, Scratch(stream.sparkSession)
    out, checkpoint = out or scratch.path("stream_out"), checkpoint or scratch.path("stream_state")
    last = [-1]

    def keep(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{out}/batch={batch}")
        last[0] = batch

    stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    if mode == "complete" and last[0] >= 0:
        return spark.read.schema(stream.schema).parquet(f"{out}/batch={last[0]}")
    if last[0] < 0:
        return spark.createDataFrame([], stream.schema)
    found = spark.read.option("basePath", out).parquet(f"{out}/batch=*")
    return found if mode == "update" else found.select(*stream.columns)


def newest(drawn: DataFrame, keys: list[str]) -> DataFrame:
    """The last row written for each key in update mode."""
    rest = [c for c in drawn.columns if c not in (*keys, "batch")]
    return drawn.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("row")).select(*keys, "row.*")


def incremental_product(stream_a: DataFrame, b: SparseMatrix) -> DataFrame:
    """C = A·B is linear in A, so each batch of entries (i, j, v) of A adds its own products to the state."""
    left = stream_a.select("i", F.col("j").alias("k"), F.col("v").alias("va"))
    right = b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("vb"))
    return left.join(right, "k").groupBy("i", "j").agg(F.sum(F.col("va") * F.col("vb")).alias("v"))


def daily_squares(stream: DataFrame, product: Callable[[SparseMatrix, SparseMatrix], SparseMatrix], n: int, out: str, checkpoint: str) -> None:
    """For every batch of whole hours: the matrix of consecutive users, and its square, written by batch."""
    from pyspark.sql import Window

    def batch(df: DataFrame, number: int) -> None:
        after = F.lead("user_id").over(Window.partitionBy(F.date_trunc("hour", "ts")).orderBy("ts", "event_id"))
        pairs = df.select(F.col("user_id").alias("a"), after.alias("b"))
        a = SparseMatrix.from_table(pairs, "a", "b", F.lit(1), n, n)
        product(a, a).df.write.mode("overwrite").parquet(f"{out}/batch={number}")

    stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def tumbling(stream: DataFrame) -> DataFrame:
    return stream.groupBy(F.window("ts", "1 day").alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.unix_seconds("w.start").alias("day"), "user_id", "n")


def sliding(stream: DataFrame) -> DataFrame:
    return stream.groupBy(F.window("ts", "2 hours", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.unix_seconds("w.start").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return stream.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.unix_micros("w.start").alias("start"), "n")


def closed_days(stream: DataFrame, late: str = "1 day") -> DataFrame:
    """Days are given once the watermark has passed them; rows older than the watermark are dropped."""
    counted = stream.withWatermark("ts", late).groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return counted.select(F.unix_seconds("w.start").alias("day"), "n", "total")


def without_repeats(stream: DataFrame, late: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def click_then_purchase(clicks: DataFrame, purchases: DataFrame, within: str = "1 hour") -> DataFrame:
    """Purchases of a user up to an hour after a click; watermarks bound the state of both sides."""
    left = clicks.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("at")).withWatermark("at", "2 hours")
    right = purchases.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", "ts").withWatermark("ts", "2 hours")
    return left.join(right, F.expr(f"u = user_id and ts >= at and ts <= at + interval {within}")).select("click", "purchase", "user_id")


def running_histogram(stream: DataFrame, shift: int = 4) -> DataFrame:
    """(chunk, n): counts of user chunks held in state of our own."""

    def update(key, frames, state: GroupState):
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"chunk": [key[0]], "n": [n]})

    keyed = stream.where("user_id is not null").select(F.shiftright("user_id", shift).alias("chunk"))
    return keyed.groupBy("chunk").applyInPandasWithState(update, "chunk long, n long", "n long", "update", GroupStateTimeout.NoTimeout)


def run_twice(stream: DataFrame) -> DataFrame:
    """(run, n): rows written by a bounded run, and by a second one from the same checkpoint, which finds nothing new."""
    spark, scratch = stream.sparkSession, Scratch(stream.sparkSession)
    state, rows = scratch.path("stream_state"), []
    for run in (1, 2):
        rows.append((run, drained(stream, "append", state, scratch.path(f"run{run}")).count()))
    return spark.createDataFrame(rows, "run long, n long")
