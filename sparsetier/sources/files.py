"""Readers and writers of matrices: coordinate text, partitioned and bucketed sinks, other formats."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from sparsetier.sources.matrices import SparseMatrix

CELLS = "i long, j long, v long"


def write_coordinate_text(m: SparseMatrix, path: str) -> None:
    """Part files of "row column value" lines, numbered from 1, after one part with the line "rows columns non-zeros"."""
    lines = m.df.select(F.concat_ws(" ", F.col("i") + 1, F.col("j") + 1, "v").alias("value"))
    head = m.df.agg(F.concat_ws(" ", F.lit(m.n_rows), F.lit(m.n_cols), F.count("*")).alias("value"))
    head.coalesce(1).write.text(f"{path}/part=0")
    lines.write.text(f"{path}/part=1")


def read_coordinate_text(spark: SparkSession, path: str) -> SparseMatrix:
    """What ``write_coordinate_text`` wrote, or any file of the format (comments start with %), read by Spark's text reader from any store.
    The head is the first line that is no comment: in the part with the smallest name, at the smallest place."""
    lines = spark.read.text(path, recursiveFileLookup=True).select("value", F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("at"), F.monotonically_increasing_id().alias("n"))
    lines = lines.where(~F.col("value").startswith("%") & (F.trim("value") != ""))
    head = lines.agg(F.min(F.struct("file", "at", "n", "value")).alias("first")).first().first
    rows, cols, _ = map(int, head.value.split())
    parts = F.split(F.trim("value"), r"\s+")
    cells = lines.where(~((F.col("file") == head.file) & (F.col("at") == head["at"]) & (F.col("n") == head.n))).select(
        (parts[0].cast("long") - 1).alias("i"), (parts[1].cast("long") - 1).alias("j"), parts[2].cast("long").alias("v"))
    return SparseMatrix(cells, rows, cols)


class CoordinateTextSource(DataSource):
    """``spark.read.format("coordinate_text").load(path)``: one file in a folder that every executor can open, cut at line ends into
    pieces of ``piece_bytes``."""

    @classmethod
    def name(cls):
        return "coordinate_text"

    def schema(self):
        return CELLS

    def reader(self, schema):
        return _TextReader(self.options["path"], int(self.options.get("piece_bytes", 64 << 20)))


class _TextReader(DataSourceReader):
    def __init__(self, path: str, piece_bytes: int):
        self.path, self.piece_bytes = path.removeprefix("file:"), piece_bytes

    def partitions(self):
        with open(self.path, "rb") as file:
            while (line := file.readline()).startswith(b"%"):
                pass
            start = file.tell()
        return [InputPartition((at, min(at + self.piece_bytes, size))) for size in [os.path.getsize(self.path)] for at in range(start, size, self.piece_bytes)]

    def read(self, partition):
        start, stop = partition.value
        with open(self.path, "rb") as file:
            file.seek(start - 1)
            file.readline()  # a line belongs to the piece it starts in
            while file.tell() < stop and (line := file.readline()):
                if line.strip():
                    i, j, v = line.split()
                    yield int(i) - 1, int(j) - 1, int(v)


#: Folders of blocks along the rows, and along the columns.
FOLDERS = 16


def _folder_shift(size: int, block: int) -> int:
    """Bits of a block's number inside its folder."""
    return max(0, (max(0, size - 1) >> block).bit_length() - (FOLDERS.bit_length() - 1))


def write_blocks(m: SparseMatrix, path: str, row_block: int = 12, col_block: int = 12) -> None:
    """Parquet folders by neighbouring row blocks and column blocks, inside them files ordered by block (rb, cb), so that a block is
    read without the others: by its folder, and by the bounds of a file's row groups and pages. The number of folders does not grow with the
    matrix, as a folder and a file for every block costs more than the cells in it."""
    blocks = m.df.withColumns({"rb": F.shiftright("i", row_block), "cb": F.shiftright("j", col_block)})
    folders = blocks.withColumns({"rf": F.shiftright("rb", _folder_shift(m.n_rows, row_block)), "cf": F.shiftright("cb", _folder_shift(m.n_cols, col_block))})
    folders.repartition("rf", "cf").sortWithinPartitions("rf", "cf", "cb", "rb", "i", "j").write.partitionBy("rf", "cf").parquet(path)


def read_blocks(spark: SparkSession, m: SparseMatrix, path: str, row_block: int = 12, col_block: int = 12, first_row=None, last_row=None, first_column=None, last_column=None) -> DataFrame:
    """(i, j, v, rb, cb) of the blocks between the given ones, both included, from what ``write_blocks`` wrote of ``m``."""
    rows = spark.read.schema(CELLS + ", rb long, cb long, rf long, cf long").parquet(path)
    for block, folder, shift, low, high in (("rb", "rf", _folder_shift(m.n_rows, row_block), first_row, last_row), ("cb", "cf", _folder_shift(m.n_cols, col_block), first_column, last_column)):
        if low is not None:
            rows = rows.where((F.col(block) >= low) & (F.col(folder) >= low >> shift))
        if high is not None:
            rows = rows.where((F.col(block) <= high) & (F.col(folder) <= high >> shift))
    return rows.drop("rf", "cf")


def write_bucketed(m: SparseMatrix, name: str, key: str, buckets: int = 8) -> DataFrame:
    """A table bucketed and sorted by ``key``: a join with another one bucketed alike needs no exchange."""
    m.df.write.bucketBy(buckets, key).sortBy(key).format("parquet").mode("overwrite").saveAsTable(name)
    return m.df.sparkSession.table(name)


def round_trip(m: SparseMatrix, path: str, format: str) -> DataFrame:
    m.df.write.format(format).save(path)
    return m.df.sparkSession.read.format(format).schema(CELLS).load(path)
