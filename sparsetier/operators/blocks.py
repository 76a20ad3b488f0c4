"""Storage forms, per-row measures, categories and the histogram, prefix-sum and reorder blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sparsetier.functions.params import ChunkPlan, SystemSpec, TypeSizes, dense_slot_bytes
from sparsetier.sources.matrices import SparseMatrix


def row_packed(m: SparseMatrix) -> DataFrame:
    cells = m.df.groupBy("i").agg(F.sort_array(F.collect_list(F.struct("j", "v"))).alias("cells"))
    return cells.select("i", F.transform("cells", lambda c: c["j"]).alias("cols"), F.transform("cells", lambda c: c["v"]).alias("vals"))


def unpack_rows(packed: DataFrame) -> DataFrame:
    return packed.select("i", F.posexplode(F.arrays_zip("cols", "vals")).alias("pos", "cell")).select("i", "pos", F.col("cell.cols").alias("j"), F.col("cell.vals").alias("v"))


def prefix_sum(df: DataFrame, keys: list[str], order: str, count: str) -> DataFrame:
    """Add start and end offsets of ``count`` within ``keys``."""
    w = Window.partitionBy(*keys).orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    first = F.coalesce(F.sum(count).over(w), F.lit(0))
    return df.withColumn("start", first).withColumn("end", first + F.col(count))


def row_pointers(m: SparseMatrix) -> DataFrame:
    return pointers_from_counts(m.df.groupBy("i").agg(F.count("*").alias("c")), m.n_rows)


def pointers_from_counts(counts: DataFrame, n_rows: int, block: int = 1 << 12) -> DataFrame:
    """(i, start, end) for all rows, empty ones too: a scan inside row blocks plus a scan over block totals, so that no
    task orders all rows."""
    rows = counts.sparkSession.range(n_rows).select(F.col("id").alias("i")).join(counts, "i", "left").select("i", F.coalesce("c", F.lit(0)).alias("c"), F.floor(F.col("i") / block).alias("rb"))
    totals = prefix_sum(rows.groupBy("rb").agg(F.sum("c").alias("t")).withColumn("g", F.floor(F.col("rb") / block)), ["g"], "rb", "t")
    groups = prefix_sum(totals.groupBy("g").agg(F.sum("t").alias("gt")).withColumn("one", F.lit(0)), ["one"], "g", "gt")
    base = totals.join(groups.select("g", F.col("start").alias("gs")), "g").select("rb", (F.col("start") + F.col("gs")).alias("base"))
    inner = prefix_sum(rows, ["rb"], "i", "c").join(base, "rb")
    return inner.select("i", (F.col("start") + F.col("base")).alias("start"), (F.col("end") + F.col("base")).alias("end"))


def offsets_across(counts: DataFrame, chunk: str, row: str, count: str, block: int = 1 << 12) -> DataFrame:
    """Exclusive prefix sum of ``count`` in the order (chunk, row): inside blocks of rows of a chunk, over these blocks, over
    chunks; the last scan orders one row per chunk."""
    tagged = counts.withColumn("rb", F.floor(F.col(row) / block))
    blocks = prefix_sum(tagged.groupBy(chunk, "rb").agg(F.sum(count).alias("t")), [chunk], "rb", "t")
    chunks = prefix_sum(blocks.groupBy(chunk).agg(F.sum("t").alias("ct")).withColumn("one", F.lit(0)), ["one"], chunk, "ct")
    base = blocks.join(chunks.select(chunk, F.col("start").alias("cs")), chunk).select(chunk, "rb", (F.col("start") + F.col("cs")).alias("base"))
    inner = prefix_sum(tagged, [chunk, "rb"], row, count).join(base, [chunk, "rb"])
    return inner.select(chunk, row, count, (F.col("start") + F.col("base")).alias("start"))


def row_slices(m: SparseMatrix, width: int = 1 << 12) -> DataFrame:
    """(k, part, cols, vals): rows packed in slices of at most ``width`` columns, so that a full row is several packs."""
    packed = m.df.groupBy(F.col("i").alias("k"), F.floor(F.col("j") / width).alias("part")).agg(F.sort_array(F.collect_list(F.struct("j", "v"))).alias("cells"))
    return packed.select("k", "part", F.col("cells.j").alias("cols"), F.col("cells.v").alias("vals"))


def column_packed(m: SparseMatrix, rows: DataFrame | None = None, width: int = 1 << 12) -> DataFrame:
    """(k, part, rows, vals): the columns of all rows, or of the given (i), packed in slices of at most ``width`` rows."""
    chosen = m if rows is None else select_rows(m, rows)
    return row_slices(chosen.transpose(), width).withColumnRenamed("cols", "rows")


def column_pointers(m: SparseMatrix, rows: DataFrame | None = None) -> DataFrame:
    """(i, start, end) per column of the row subset."""
    return row_pointers((m if rows is None else select_rows(m, rows)).transpose())


def select_rows(m: SparseMatrix, rows: DataFrame) -> SparseMatrix:
    return SparseMatrix(m.df.join(rows.select("i").distinct(), "i", "left_semi"), m.n_rows, m.n_cols)


def needed_rows(a: SparseMatrix) -> DataFrame:
    """(i): the rows of B that A's columns ask for."""
    return a.df.select(F.col("j").alias("i")).distinct()


def needed_bitmap(a: SparseMatrix) -> DataFrame:
    """(word, bits): the same as 64-bit words."""
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("j").bitwiseAND(63).cast("int"))
    return a.df.groupBy(F.shiftright("j", 6).alias("word")).agg(F.bit_or(bit).alias("bits"))


def prune(b: SparseMatrix, needed: DataFrame) -> SparseMatrix:
    return SparseMatrix(b.df.join(needed, "i", "left_semi"), b.n_rows, b.n_cols)


def index_keys(df: DataFrame, col: str) -> DataFrame:
    """(key, id): numbers 0, 1, … of the distinct non-null string keys in their order: places inside the keys of one first pair of
    characters, plus offsets of these pairs, so that no task orders all keys."""
    keys = df.select(F.col(col).alias("key")).where("key is not null").distinct().withColumn("head", F.substring("key", 1, 2))
    heads = prefix_sum(keys.groupBy("head").agg(F.count("*").alias("c")).withColumn("one", F.lit(0)), ["one"], "head", "c").select("head", "start")
    placed = keys.withColumn("place", F.row_number().over(Window.partitionBy("head").orderBy("key")) - 1)
    return placed.join(heads, "head").select("key", (F.col("start") + F.col("place")).alias("id"))


def describe(m: SparseMatrix) -> DataFrame:
    return m.df.agg(F.count("*").alias("nnz"), F.count_distinct("i").alias("used_rows"), F.count_distinct("j").alias("used_cols"))


def intermediate_rows(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """(i, n_inter, jmin, jmax) without forming the product: one small row per row of B is joined."""
    rows = b.df.groupBy(F.col("i").alias("k")).agg(F.count("*").alias("c"), F.min("j").alias("lo"), F.max("j").alias("hi"))
    return a.df.select("i", F.col("j").alias("k")).join(rows, "k").groupBy("i").agg(F.sum("c").alias("n_inter"), F.min("lo").alias("jmin"), F.max("hi").alias("jmax"))


def categorize(a: SparseMatrix, b: SparseMatrix, plan: ChunkPlan, spec: SystemSpec, types: TypeSizes, threshold: int = 256, phase: str = "numeric") -> DataFrame:
    slot = dense_slot_bytes(phase, types)
    return intermediate_rows(a, b).withColumn("category", F.when(F.col("n_inter") < threshold, "sort").when(
        (F.col("jmax") - F.col("jmin") + 1) * slot <= spec.l2_bytes, "dense").otherwise(plan.level))


def census(rows: DataFrame) -> DataFrame:
    return rows.groupBy("category").agg(F.count("*").alias("n_rows"), F.sum("n_inter").alias("products"))


def batches(rows: DataFrame, limit_products: int, block: int = 1 << 12) -> DataFrame:
    """Batch numbers by exclusive prefix of products over a limit; a batch exceeds the limit by less than one row."""
    tagged = rows.withColumn("rb", F.floor(F.col("i") / block))
    totals = prefix_sum(tagged.groupBy("rb").agg(F.sum("n_inter").alias("t")).withColumn("one", F.lit(0)), ["one"], "rb", "t").select("rb", F.col("start").alias("base"))
    return prefix_sum(tagged, ["rb"], "i", "n_inter").join(totals, "rb").select("i", "n_inter", F.floor((F.col("start") + F.col("base")) / limit_products).cast("long").alias("batch_id"))


def coarse_volume(rows: DataFrame, pair_bytes: int = 16) -> DataFrame:
    """Products and bytes of the given rows' intermediate product."""
    return rows.agg(F.coalesce(F.sum("n_inter"), F.lit(0)).alias("products"), (F.coalesce(F.sum("n_inter"), F.lit(0)) * pair_bytes).alias("bytes"))


def coarse_batches(rows: DataFrame, types: TypeSizes, live_bytes: int, cache_bytes: int, row_bytes: int, block: int = 1 << 12) -> DataFrame:
    """(i, n_inter, batch_id) under two limits: the bytes of live pairs, and the rows' counters within the cache. A row takes the
    larger of its two shares of a batch (in millionths); a batch exceeds a limit by less than one row."""
    share = F.greatest(F.ceil(F.col("n_inter") * (types.value + types.column) * 1_000_000 / live_bytes), F.lit(-(-row_bytes * 1_000_000 // cache_bytes)))
    tagged = rows.select("i", "n_inter", share.cast("long").alias("share"), F.floor(F.col("i") / block).alias("rb"))
    totals = prefix_sum(tagged.groupBy("rb").agg(F.sum("share").alias("t")).withColumn("one", F.lit(0)), ["one"], "rb", "t").select("rb", F.col("start").alias("base"))
    return prefix_sum(tagged, ["rb"], "i", "share").join(totals, "rb").select("i", "n_inter", F.floor((F.col("start") + F.col("base")) / 1_000_000).cast("long").alias("batch_id"))


def greedy_batches(rows: list[tuple[int, int]], live_limit: int, rows_limit: int) -> list[int]:
    """The sequential form on a list of (i, bytes): a batch is closed before a row that would break a limit."""
    out, batch, live, n = [], 0, 0, 0
    for _, size in rows:
        if n and (live + size > live_limit or n + 1 > rows_limit):
            batch, live, n = batch + 1, 0, 0
        live, n = live + size, n + 1
        out.append(batch)
    return out


def salted_join(left: DataFrame, right: DataFrame, key: str, hub_products: int, salts: int = 16) -> DataFrame:
    """Equi-join whose hub keys, those with more than ``hub_products`` matches, are spread: left rows get one salt, right rows all."""
    c = left.groupBy(key).agg(F.count("*").alias("ca")).join(right.groupBy(key).agg(F.count("*").alias("cb")), key)
    hubs = c.where(F.col("ca") * F.col("cb") > hub_products).select(key, F.lit(True).alias("hub"))
    one = F.pmod(F.xxhash64(*(c for c in left.columns if c != key)), F.lit(salts)).cast("int")
    spread = left.join(hubs, key, "left").withColumn("salt", F.when(F.col("hub"), one).otherwise(0)).drop("hub")
    copies = right.join(hubs, key, "left").withColumn("salt", F.explode(F.when(F.col("hub"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))))).drop("hub")
    return spread.join(copies, [key, "salt"]).drop("salt")


def expand(a: SparseMatrix, b: SparseMatrix, hint: str | None = None) -> DataFrame:
    """The intermediate product (i, k, j, p), one row per elementary product."""
    left = a.df.select("i", F.col("j").alias("k"), F.col("v").alias("va"))
    right = b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("vb"))
    return left.join(right.hint(hint) if hint else right, "k").select("i", "k", "j", (F.col("va") * F.col("vb")).alias("p"))


def histogram(pairs: DataFrame, shift: int) -> DataFrame:
    return pairs.groupBy("i", F.shiftright("j", shift).alias("chunk")).agg(F.count("*").alias("cnt"))


def histogram_by_length(pairs: DataFrame, length: int) -> DataFrame:
    """The histogram for chunk lengths that are no power of two."""
    return pairs.groupBy("i", F.floor(F.col("j") / length).alias("chunk")).agg(F.count("*").alias("cnt"))


def to_global(chunk, local, shift: int):
    return F.shiftleft(chunk, shift) + local


def reorder(pairs: DataFrame, shift: int) -> DataFrame:
    """Place of every pair in its chunk, with the chunk-local column."""
    w = Window.partitionBy("i", "chunk").orderBy("j", "k")
    tagged = pairs.withColumn("chunk", F.shiftright("j", shift))
    return tagged.select("i", "chunk", (F.row_number().over(w) - 1).cast("long").alias("pos"), (F.col("j") - F.shiftleft("chunk", shift)).alias("local_j"), "p")
