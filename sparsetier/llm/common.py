"""Helpers shared by the training-data operators: reading, written intermediate tables, Arrow maps."""

from __future__ import annotations

import ctypes
import sys
import types
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsetier.store import Scratch


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def held_by_process(key, make: Callable):
    """What ``make`` gives, once per Python worker, which Spark uses for many tasks. Functions reach workers as copies, so their own
    globals do not last; a module entry does."""
    holder = sys.modules.setdefault("sparsetier_held", types.ModuleType("sparsetier_held"))
    if key not in holder.__dict__:
        holder.__dict__[key] = make()
    return holder.__dict__[key]


def give_back() -> None:
    """Return freed memory to the system at the end of a task: Spark keeps idle Python workers, and what they hold counts."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Write a table to the shared folder and read it again."""
    return Scratch(df.sparkSession).write(df, tag)


def texts_of(docs: DataFrame, *extra: str) -> DataFrame:
    """doc_id and text (null: empty) of a documents table, whatever other columns it has."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"), *extra)


def arrow_rows(df: DataFrame, schema: str, start: Callable[[], Callable[[dict], Iterator[tuple]]], flush: int = 2048) -> DataFrame:
    """Row generator over Arrow batches. ``start()`` runs once per task and returns a function from a column dict
    of one slice (at most 256 rows) to output tuples; output batches hold at most ``flush`` rows or about 8 MB."""
    target = df.sparkSession.createDataFrame([], schema).schema
    names = target.fieldNames()

    def run(batches):
        from pyspark.sql.pandas.types import to_arrow_schema

        arrow = to_arrow_schema(target)
        work = start()
        out: list[tuple] = []
        weight = 0

        def pack():
            cols = list(zip(*out)) if out else [()] * len(names)
            return pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(cols, arrow)], schema=arrow)

        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                for row in work(batch.slice(at, 256).to_pydict()):
                    out.append(row)
                    weight += sum(len(v) for v in row if isinstance(v, (bytes, str, list)))
                    if len(out) >= flush or weight > 8_000_000:
                        yield pack()
                        out, weight = [], 0
        if out:
            yield pack()
        give_back()

    return df.mapInArrow(run, schema)
