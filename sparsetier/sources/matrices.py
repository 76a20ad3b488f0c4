"""Coordinate matrices (i, j, v): from tables, and generated on the executors."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

PRIME = 2147483647


@dataclass(frozen=True)
class SparseMatrix:
    df: DataFrame
    n_rows: int
    n_cols: int

    @staticmethod
    def from_table(df: DataFrame, row: str, col: str, value: Column, n_rows: int, n_cols: int, by_row: bool = False) -> SparseMatrix:
        """Sums by row and column; ``by_row`` deals whole rows to tasks, so that what works on rows needs no exchange of its own."""
        df = df.where(F.col(row).isNotNull() & F.col(col).isNotNull())
        return SparseMatrix((df.repartition(row) if by_row else df).groupBy(F.col(row).alias("i"), F.col(col).alias("j")).agg(F.sum(value).cast("long").alias("v")), n_rows, n_cols)

    def transpose(self) -> SparseMatrix:
        return SparseMatrix(self.df.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), self.n_cols, self.n_rows)


def _size(spark, sf_dir, table, key) -> int:
    return (spark.read.parquet(f"{sf_dir}/{table}.parquet").agg(F.max(key)).first()[0] or 0) + 1


def order_part(spark: SparkSession, sf_dir: str) -> SparseMatrix:
    rows = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    return SparseMatrix.from_table(rows, "l_orderkey", "l_partkey", F.col("l_quantity"), _size(spark, sf_dir, "orders", "o_orderkey"), _size(spark, sf_dir, "part", "p_partkey"))


def part_supplier(spark: SparkSession, sf_dir: str, by_row: bool = False) -> SparseMatrix:
    rows = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    if by_row:
        rows = rows.select("l_partkey", "l_suppkey", "l_quantity")
    return SparseMatrix.from_table(rows, "l_partkey", "l_suppkey", F.col("l_quantity"), _size(spark, sf_dir, "part", "p_partkey"), _size(spark, sf_dir, "supplier", "s_suppkey"), by_row)


def customer_order(spark: SparkSession, sf_dir: str) -> SparseMatrix:
    rows = spark.read.parquet(f"{sf_dir}/orders.parquet")
    return SparseMatrix.from_table(rows, "o_custkey", "o_orderkey", F.lit(1), _size(spark, sf_dir, "customer", "c_custkey"), _size(spark, sf_dir, "orders", "o_orderkey"))


def next_part(spark: SparkSession, sf_dir: str) -> SparseMatrix:
    from pyspark.sql import Window

    after = F.lead("l_partkey").over(Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey"))
    rows = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select(F.col("l_partkey").alias("a"), after.alias("b"))
    n = _size(spark, sf_dir, "part", "p_partkey")
    return SparseMatrix.from_table(rows, "a", "b", F.lit(1), n, n)


def instant(ts: Column) -> Column:
    """A time without zone read as UTC, whatever the session's zone."""
    return F.concat(ts.cast("timestamp_ntz").cast("string"), F.lit("+00:00")).cast("timestamp")


def next_user(spark: SparkSession, sf_dir: str) -> SparseMatrix:
    """Counts of consecutive users inside an hour."""
    from pyspark.sql import Window

    after = F.lead("user_id").over(Window.partitionBy(F.date_trunc("hour", "ts")).orderBy("ts", "event_id"))
    rows = spark.read.parquet(f"{sf_dir}/events.parquet").select(F.col("user_id").alias("a"), after.alias("b"))
    n = _size(spark, sf_dir, "events", "user_id")
    return SparseMatrix.from_table(rows, "a", "b", F.lit(1), n, n)


def user_hour(spark: SparkSession, sf_dir: str) -> SparseMatrix:
    rows = spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id", F.floor(F.unix_seconds(instant(F.col("ts"))) / 3600).alias("hour"))
    first = rows.agg(F.min("hour")).first()[0] or 0
    rows = rows.withColumn("hour", F.col("hour") - first)
    return SparseMatrix.from_table(rows, "user_id", "hour", F.lit(1), _size(spark, sf_dir, "events", "user_id"), (rows.agg(F.max("hour")).first()[0] or 0) + 1)


def document_terms(spark: SparkSession, sf_dir: str, least: int = 2, most: int = 50) -> SparseMatrix:
    """Counts of words of a to z, for words that stand in ``least`` to ``most`` documents; columns number these words in their order."""
    from sparsetier.operators.blocks import index_keys

    words = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"))).alias("term"))
    counts = words.groupBy("doc_id", "term").agg(F.count("*").alias("c"))
    chosen = counts.groupBy("term").agg(F.count("*").alias("df")).where(F.col("df").between(least, most)).select("term")
    ids = index_keys(chosen, "term")
    cells = counts.join(ids, F.col("term") == F.col("key")).select("doc_id", "id", "c")
    return SparseMatrix.from_table(cells, "doc_id", "id", F.col("c"), _size(spark, sf_dir, "documents", "doc_id"), (ids.agg(F.max("id")).first()[0] or 0) + 1)


def page_links(spark: SparkSession, sf_dir: str) -> SparseMatrix:
    """Counts of href targets by page; columns number the targets in their order."""
    from sparsetier.operators.blocks import index_keys

    links = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'))).alias("target"))
    ids = index_keys(links, "target")
    cells = links.join(ids, F.col("target") == F.col("key")).select("page_id", "id")
    return SparseMatrix.from_table(cells, "page_id", "id", F.lit(1), _size(spark, sf_dir, "pages", "page_id"), (ids.agg(F.max("id")).first()[0] or 0) + 1)


def embedding_matrix(spark: SparkSession, sf_dir: str, scale: int = 1000, width: int = 64) -> SparseMatrix:
    """Vectors as scaled whole numbers; every entry is stored, zeros too."""
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", F.posexplode("embedding").alias("j", "x"))
    value = F.floor(F.col("x").cast("double") * scale + 0.5)
    return SparseMatrix.from_table(rows.withColumn("j", F.col("j").cast("long")), "vec_id", "j", value, _size(spark, sf_dir, "embeddings", "vec_id"), width)


def portable_hash(x: Column, seed: int) -> Column:
    """Integer congruential hash below 2**31; every intermediate value is below 2**63."""
    a = ((x % PRIME) * 48271 + seed) % PRIME
    b = (a * a + x) % PRIME
    c = (b * 69621 + 7) % PRIME
    return (c * c + x) % PRIME


def keys(spark: SparkSession, sf_dir: str, table: str, key: str) -> DataFrame:
    """(id): a key of a given table, as numbers for the generators below to work on in place of a range."""
    return spark.read.parquet(f"{sf_dir}/{table}.parquet").where(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("id"))


def banded_matrix(spark: SparkSession, n: int, half: int, rows: DataFrame | None = None) -> SparseMatrix:
    df = (spark.range(n) if rows is None else rows.distinct()).select(F.col("id").alias("i"), F.explode(F.sequence(F.col("id") - half, F.col("id") + half)).alias("j")).where((F.col("j") >= 0) & (F.col("j") < n))
    return SparseMatrix(df.withColumn("v", F.lit(1).cast("long")), n, n)


def mixed_matrix(spark: SparkSession, n: int = 2048, seed: int = 42, rows: DataFrame | None = None) -> SparseMatrix:
    """A third of the rows a narrow band, a third a wide band, the rest uniform: rows for sorting, dense buffers and chunks."""
    third, rest = n // 3, 2 * n // 3
    rows = spark.range(n) if rows is None else rows.distinct()
    half = F.when(F.col("id") < third, 2).otherwise(20)
    band = rows.where(F.col("id") < rest).select(F.col("id").alias("i"), F.explode(F.sequence(F.col("id") - half, F.col("id") + half)).alias("j")).where((F.col("j") >= 0) & (F.col("j") < n))
    loose = rows.where(F.col("id") >= rest).select(F.col("id").alias("i"), F.explode(F.sequence(F.lit(0), F.lit(19))).alias("t"))
    loose = loose.select("i", (portable_hash(F.col("i") * 20 + F.col("t"), seed) % n).alias("j")).distinct()
    return SparseMatrix(band.unionByName(loose).withColumn("v", F.lit(1).cast("long")), n, n)


def index_stream(spark: SparkSession, size: int, length: int, seed: int = 42, ids: DataFrame | None = None) -> DataFrame:
    """(pos, idx, val): indices spread evenly over the stream's length."""
    return (spark.range(size) if ids is None else ids).select(F.col("id").alias("pos"), (portable_hash(F.col("id"), seed) % length).alias("idx"), (F.col("id") % 7 + 1).alias("val"))


def uniform_matrix(spark: SparkSession, n: int, m: int, per_row: int, seed: int, ids: DataFrame | None = None) -> SparseMatrix:
    df = (spark.range(n * per_row) if ids is None else ids).select(F.floor(F.col("id") / per_row).cast("long").alias("i"), (portable_hash(F.col("id"), seed) % m).alias("j")).distinct()
    return SparseMatrix(df.withColumn("v", F.lit(1).cast("long")), n, m)


def power_law_matrix(spark: SparkSession, scale: int, per_row: int = 16, seed: int = 7, percents=(57, 19, 19), ids: DataFrame | None = None) -> SparseMatrix:
    """Recursive quadrant draws; equal draws are summed."""
    a, b, c = percents[0], percents[0] + percents[1], sum(percents)
    edges = spark.range((1 << scale) * per_row) if ids is None else ids
    row, col = F.lit(0).cast("long"), F.lit(0).cast("long")
    for level in range(scale):
        u = portable_hash(F.col("id") * 64 + level, seed) % 100
        row = row * 2 + F.when(u >= b, 1).otherwise(0)
        col = col * 2 + F.when((u >= a) & (u < b) | (u >= c), 1).otherwise(0)
    df = edges.select(row.alias("i"), col.alias("j")).groupBy("i", "j").agg(F.count("*").alias("v"))
    return SparseMatrix(df, 1 << scale, 1 << scale)
