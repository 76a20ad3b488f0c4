"""The two-level product: setup, symbolic phase and numeric phase as one plan, its coarse level, and its ablations.

Setup finds each row's category from its number of products and column span (a small join, the product is not formed). The category rides
on the entries of A, so that A and B are joined once for all categories. One exchange deals the pairs by (piece, row):
a coarse chunk is a piece of the row's columns, and a fine row with many products is dealt into several groups of fine chunks, so
that no row of a power-law matrix stays in one task. Inside a task the chunk kernel streams over sorted pairs.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.functions.params import SPR, ChunkPlan, SystemSpec, TypeSizes, coarse_counter_bytes, plan_chunks
from sparsetier.operators import blocks as B
from sparsetier.plans import kernel as K
from sparsetier.sources.matrices import SparseMatrix

TYPES = TypeSizes(value=8, column=8)
#: Products of a fine row from which on its chunks are dealt to several tasks.
SPLIT = 1 << 20


@dataclass(frozen=True)
class Options:
    coarse: bool = True
    categorize: bool = True
    accumulator: str = "hybrid"
    pack: bool = True
    n_fine: int | None = None  # a fixed chunk count in place of the model's
    threshold: int = 256
    batch_bytes: int = 1 << 30  # limit on the live pairs of a batch of coarse rows
    hub_products: int | None = None  # salt the join for columns of A with more products


def value_type(*matrices: SparseMatrix) -> str:
    return "double" if any(dict(m.df.dtypes)["v"] == "double" for m in matrices) else "long"


def chunk_plan(n_cols: int, spec: SystemSpec, phase: str, options: Options) -> ChunkPlan:
    plan = plan_chunks(n_cols, spec, TYPES, phase, options.coarse)
    if options.n_fine is None:
        return plan
    inner = plan.width >> (plan.n_coarse.bit_length() - 1)
    n_fine = min(options.n_fine, inner)
    return ChunkPlan(plan.level, plan.width, plan.n_coarse, plan.shift_coarse, n_fine, (inner // n_fine).bit_length() - 1)


def setup(a: SparseMatrix, b: SparseMatrix, spec: SystemSpec, phase: str = "numeric", options: Options = Options()) -> tuple[ChunkPlan, DataFrame]:
    """The chunk plan and (i, n_inter, category)."""
    plan = chunk_plan(b.n_cols, spec, phase, options)
    rows = B.categorize(a, b, plan, spec, TYPES, options.threshold, phase).select("i", "n_inter", "category")
    return plan, rows if options.categorize else rows.withColumn("category", F.lit(plan.level))


def pieces(a: SparseMatrix, b: SparseMatrix, plan: ChunkPlan, rows: DataFrame, options: Options) -> DataFrame:
    """(key, j, p): the intermediate product, formed once; the key has its row, its category and the piece of the row it belongs to."""
    kind = F.when(F.col("category") == "sort", K.SORT).when(F.col("category") == "dense", K.DENSE).otherwise(K.FINE)
    ways = F.when(F.col("category") == "fine", F.least(F.lit(plan.n_fine), F.ceil(F.col("n_inter") / SPLIT))).otherwise(1)
    tags = rows.select("i", kind.cast("long").alias("kind"), ways.cast("long").alias("ways"), (F.col("category") == "coarse").alias("split"))
    left = a.df.join(tags, "i").select("i", F.col("j").alias("k"), F.col("v").alias("va"), "kind", "ways", "split")
    # small inputs make many products: a stated number of partitions keeps adaptive execution from putting them into one
    left = left.repartition(int(left.sparkSession.conf.get("spark.sql.shuffle.partitions")), "k")
    right = b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("vb"))
    joined = left.join(right, "k") if options.hub_products is None else B.salted_join(left, right, "k", options.hub_products)
    chunk = F.shiftright("j", plan.shift_fine)
    sub = F.when(F.col("split"), F.shiftright("j", plan.shift_coarse)).otherwise(F.pmod(chunk, F.col("ways")))
    key = K.piece_key(sub.cast("long"), F.col("kind"), F.col("i"), a.n_rows, max(plan.n_coarse, plan.n_fine))
    return joined.select(key, "j", (F.col("va") * F.col("vb")).alias("p"))


def _kernel(plan: ChunkPlan, options: Options, symbolic: bool = False) -> K.KernelPlan:
    return K.KernelPlan(plan.shift_fine, options.accumulator, options.threshold, options.pack, symbolic)


def two_level(a: SparseMatrix, b: SparseMatrix, spec: SystemSpec = SPR, options: Options = Options()) -> SparseMatrix:
    """Numeric phase: C = A·B."""
    plan, rows = setup(a, b, spec, "numeric", options)
    return SparseMatrix(K.chunked_merge(pieces(a, b, plan, rows, options), a.n_rows, _kernel(plan, options), value_type(a, b)), a.n_rows, b.n_cols)


def symbolic_phase(a: SparseMatrix, b: SparseMatrix, spec: SystemSpec = SPR, options: Options = Options()) -> DataFrame:
    """Exact (i, nnz) by the same chunks with bit maps; no multiplication."""
    ones = lambda m: SparseMatrix(m.df.select("i", "j", F.lit(1).cast("long").alias("v")), m.n_rows, m.n_cols)
    plan, rows = setup(a, b, spec, "symbolic", options)
    found = K.chunked_merge(pieces(ones(a), ones(b), plan, rows, options), a.n_rows, _kernel(plan, options, True))
    return found.groupBy("i").agg(F.sum("nnz").alias("nnz"))  # rows dealt in pieces


def result_pointers(a: SparseMatrix, b: SparseMatrix, spec: SystemSpec = SPR) -> DataFrame:
    """(i, start, end) of C from the symbolic phase, empty rows included."""
    return B.pointers_from_counts(symbolic_phase(a, b, spec).withColumnRenamed("nnz", "c"), a.n_rows)


def report(a: SparseMatrix, b: SparseMatrix, spec: SystemSpec = SPR, options: Options = Options()) -> DataFrame:
    """(category, n_rows, products, level, n_coarse, n_fine): what the setup decides."""
    plan, rows = setup(a, b, spec, "numeric", options)
    return B.census(rows).withColumns({"level": F.lit(plan.level), "n_coarse": F.lit(plan.n_coarse).cast("long"), "n_fine": F.lit(plan.n_fine).cast("long")})


# ---- the levels on their own

def fine_level(a, b, spec=SPR, options=Options()) -> SparseMatrix:
    """Every row through the fine level."""
    return two_level(a, b, spec, Options(coarse=False, categorize=False, accumulator=options.accumulator, pack=options.pack, n_fine=options.n_fine, hub_products=options.hub_products))


def coarse_pairs(a: SparseMatrix, b: SparseMatrix, plan: ChunkPlan) -> DataFrame:
    """(i, j, p, coarse) in outer-product order: the columns of A, packed by column, meet the needed rows of B, packed by row; each
    meeting of two packs gives its products at once."""
    needed = B.needed_rows(a)
    left = B.column_packed(a).select("k", "rows", F.col("vals").alias("avals"))
    right = B.row_slices(B.prune(b, needed)).select("k", "cols", F.col("vals").alias("bvals"))
    outer = left.join(right, "k").select(F.explode(F.arrays_zip("rows", "avals")).alias("x"), "cols", "bvals")
    outer = outer.select(F.col("x.rows").alias("i"), F.col("x.avals").alias("va"), F.explode(F.arrays_zip("cols", "bvals")).alias("y"))
    return outer.select("i", F.col("y.cols").alias("j"), (F.col("va") * F.col("y.bvals")).alias("p")).withColumn("coarse", F.shiftright("j", plan.shift_coarse))


def coarse_level(a: SparseMatrix, b: SparseMatrix, spec: SystemSpec = SPR) -> DataFrame:
    """(coarse, i, n, start): pairs of every coarse chunk of every row and where they start, the offsets carrying on from row to
    row inside a chunk and from chunk to chunk."""
    plan = plan_chunks(b.n_cols, spec, TYPES)
    # what is exchanged is a list of chunk numbers for every entry of A, not a row for every pair
    chunk = F.shiftright("j", plan.shift_coarse).cast("int" if plan.n_coarse < 1 << 31 else "long")
    rows = b.df.groupBy(F.col("i").alias("k")).agg(F.sort_array(F.collect_list(chunk)).alias("chunks"))
    met = a.df.select("i", F.col("j").alias("k")).join(rows, "k").select("i", "chunks")
    met = met.repartition(int(met.sparkSession.conf.get("spark.sql.shuffle.partitions")), "i")
    counts = met.select("i", F.explode("chunks").alias("c")).select(F.col("c").cast("long").alias("coarse"), "i").groupBy("coarse", "i").agg(F.count("*").alias("n"))
    return B.offsets_across(counts, "coarse", "i", "n")


def coarse_fine(a: SparseMatrix, b: SparseMatrix, spec: SystemSpec = SPR, options: Options = Options()) -> SparseMatrix:
    """All rows through both levels, in batches under two limits: live pairs, and counters within the private cache."""
    plan = chunk_plan(b.n_cols, spec, "numeric", options)
    value = value_type(a, b)
    batches = B.coarse_batches(B.intermediate_rows(a, b), TYPES, options.batch_bytes, spec.l2_bytes, coarse_counter_bytes(plan.n_coarse, spec, TYPES))
    pairs = coarse_pairs(a, b, plan).join(batches.select("i", "batch_id"), "i")
    key = K.piece_key(F.pmod("batch_id", F.lit(1024)) * plan.n_coarse + F.col("coarse"), K.FINE, F.col("i"), a.n_rows, plan.n_coarse << 10)
    return SparseMatrix(K.chunked_merge(pairs.select(key, "j", "p"), a.n_rows, _kernel(plan, options), value), a.n_rows, b.n_cols)
