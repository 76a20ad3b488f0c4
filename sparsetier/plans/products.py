"""The products the two-level method is measured against. All return a coordinate matrix and agree exactly; they differ in how
the intermediate product is dealt and merged."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.functions.params import SPR, dense_slot_bytes
from sparsetier.operators import blocks as B
from sparsetier.operators.blocks import expand
from sparsetier.plans import kernel as K
from sparsetier.plans import tiles as X
from sparsetier.plans import two_level as T
from sparsetier.sources.matrices import SparseMatrix
from sparsetier.store import Scratch


def _c(df, a, b):
    return SparseMatrix(df, a.n_rows, b.n_cols)


def relational(a, b, hint=None):
    """Join, partial and final hash aggregation; the row-wise product as SQL would do it."""
    return _c(expand(a, b, hint).groupBy("i", "j").agg(F.sum("p").alias("v")), a, b)


def rowwise_dense(a, b, budget: int = 1 << 30):
    """Row-wise product with one dense accumulator of the full width. A width over ``budget`` bytes, where the method breaks down
    for want of memory, goes through the fine level, whose chunks are the same accumulator cut to a width that fits."""
    if b.n_cols * dense_slot_bytes("numeric", T.TYPES) > budget:
        return T.fine_level(a, b, SPR, T.Options(accumulator="dense"))
    return T.two_level(a, b, SPR, T.Options(coarse=False, categorize=False, accumulator="dense", n_fine=1))


def expand_sort_compress(a, b):
    """The intermediate product of a row goes to one task, is sorted by column, and equal neighbours are merged."""
    pairs = expand(a, b, "merge").select("i", "j", "p").repartition("i").sortWithinPartitions("i", "j")
    return _c(K.compress_sorted(pairs, T.value_type(a, b)), a, b)


def symbolic(a, b) -> DataFrame:
    """Exact (i, nnz) of the product, relational; no multiplication."""
    return expand(a, b).select("i", "j").distinct().groupBy("i").agg(F.count("*").alias("nnz"))


def symbolic_estimate(a, b, error: float = 0.05) -> DataFrame:
    """(i, upper, estimate): the number of products bounds the non-zeros, a sketch estimates them."""
    return expand(a, b).groupBy("i").agg(F.count("*").alias("upper"), F.approx_count_distinct("j", error).alias("estimate"))


def fine_level_sql(a, b, spec=SPR, row_block=6):
    plan = T.chunk_plan(b.n_cols, spec, "numeric", T.Options(coarse=False))
    pairs = expand(a, b).withColumns({"rb": F.shiftright("i", row_block), "chunk": F.shiftright("j", plan.shift_fine)}).repartition("rb", "chunk")
    return _c(pairs.groupBy("rb", "chunk", "i", "j").agg(F.sum("p").alias("v")).select("i", "j", "v"), a, b)


def segment_length(b, segments: int) -> int:
    return -(-b.n_cols // segments)


def segment_summary(b, segments=8) -> DataFrame:
    """(i, seg, cnt, first_j): where each row's segments start, and how long they are."""
    return b.df.groupBy("i", F.floor(F.col("j") / segment_length(b, segments)).alias("seg")).agg(F.count("*").alias("cnt"), F.min("j").alias("first_j"))


def segmented_b(a, b, segments=8):
    """Competitor: B in column segments, one narrow accumulator alive at a time. The summary says which segments an entry of A has
    to visit; a segment of a row of B is read for these only, and each (segment, row) is accumulated densely by itself."""
    length = segment_length(b, segments)
    visits = a.df.select("i", F.col("j").alias("k"), F.col("v").alias("va")).join(segment_summary(b, segments).select(F.col("i").alias("k"), "seg"), "k")
    cut = b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("vb"), F.floor(F.col("j") / length).alias("seg"))
    key = K.piece_key(F.col("seg"), K.DENSE, F.col("i"), a.n_rows, segments)
    pairs = visits.join(cut, ["k", "seg"]).select(key, "j", (F.col("va") * F.col("vb")).alias("p"))
    return _c(K.chunked_merge(pairs, a.n_rows, K.KernelPlan(0), T.value_type(a, b)), a, b)


def hash_product(a, b):
    """Competitor: shuffled hash join; each row's products meet in one task and are merged in a hash table there, without partial
    aggregation before."""
    return _c(expand(a, b, "shuffle_hash").repartition("i").groupBy("i", "j").agg(F.sum("p").alias("v")), a, b)


def heap_product(a, b):
    """Competitor: per row, a heap merges the scaled rows of B."""
    pairs = expand(a, b, "merge").repartition("i").sortWithinPartitions("i", "k", "j")
    return _c(K.heap_rows(pairs), a, b)


def library_product(a, b, block: int = 512, inner: int = 8192, most: int = 4096, limit: int | None = None):
    """Competitor, a black box: the block matrices of Spark's own library. Their sparse blocks are packed once, and once for both factors where one
    is the other's transpose. The library keeps all block products of a task at once, and makes them and the right factors dense: narrow blocks
    along the result, long ones along the sum, as many tasks as keep a task's block products within a seventh of a core's heap, counted over the blocks that there are,
    up to ``most`` tasks, and parts of the sum of their own where one block's products are more. Cells are those with a sum other than 0, exact below 2**53.
    Over ``limit`` cells of a dense result the call is refused; the measure of failures asks for that."""
    from pyspark.mllib.common import callMLlibFunc
    from pyspark.mllib.linalg import MatrixUDT
    from pyspark.sql.types import LongType, StructType

    if limit is not None and a.n_rows * b.n_cols > limit:
        raise ValueError("the library's result blocks are dense: rows x columns is too large for it")
    spark, value, scratch = a.df.sparkSession, T.value_type(a, b), Scratch(a.df.sparkSession)
    same = _same_rows(a.df, b.transpose().df)
    left = scratch.write(X.packed_blocks(a, "i", "j", block, value, inner), "library_left")
    right = left if same else scratch.write(X.packed_blocks(b, "j", "i", block, value, inner), "library_right")
    per_task, split = _library_tasks(left, right, block, _library_bytes(spark.sparkContext))
    count = lambda n, size: max(1, -(-n // size))
    parts = min(most, count(count(max(a.n_rows, b.n_cols), block), per_task) ** 2)  # the library cuts both ways by the root of it
    schema = StructType().add("_1", StructType().add("_1", LongType()).add("_2", LongType())).add("_2", MatrixUDT())

    def blocks(packed, m):
        rows = X.compressed_blocks(packed, m.n_rows, m.n_cols, block, inner, value, parts)
        jschema = spark._jsparkSession.parseDataType(schema.json())
        typed = DataFrame(spark._jsparkSession.internalCreateDataFrame(rows._jdf.queryExecution().toRdd(), jschema, False), spark)
        return callMLlibFunc("createBlockMatrix", typed, block, inner, m.n_rows, m.n_cols)

    x = blocks(left, a)
    y = (x if same else blocks(right, b.transpose())).transpose()
    found = callMLlibFunc("getMatrixEntries", x.multiply(y, split).toCoordinateMatrix())
    return _c(found.where("value <> 0").select("i", "j", F.col("value").cast(value).alias("v")), a, b)


def _library_bytes(context) -> int:
    """Block products that a task may hold: a seventh of the heap of a core."""
    executors = context._jsc.sc().getExecutorMemoryStatus().size() - 1
    one = context._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(context.getConf().get("spark.executor.memory", "1g"))
    heap = executors * one if executors else context._jvm.java.lang.Runtime.getRuntime().maxMemory()
    return heap // (7 * context.defaultParallelism)


def _library_tasks(left, right, block: int, held: int):
    """(blocks of the result each way of a task, parts of its sum) with which no task holds more block products than fit, nor more than its share."""
    pairs = left.select("b", "bk").distinct().join(right.select(F.col("b").alias("c"), "bk").distinct(), "bk").groupBy("b", "c").agg(F.count("*").alias("n"))
    sizes = [1 << n for n in range(8)]
    corner = lambda n: [F.floor(F.col(c) / n) for c in ("b", "c")]
    found = pairs.select("n", F.explode(F.array(*(F.struct(F.lit(n).alias("size"), *(e.alias(f"c{k}") for k, e in enumerate(corner(n)))) for n in sizes))).alias("at"))
    tasks = {r.size: r for r in found.groupBy("at").agg(F.sum("n").alias("n")).groupBy("at.size").agg(F.max("n").alias("most"), F.sum("n").alias("every")).collect()}
    if not tasks:
        return 1, 1
    fit = max(1, held // (block * block * 8))
    share = max(1, tasks[1].every // left.sparkSession.sparkContext.defaultParallelism)
    return max([n for n in sizes if tasks[n].most <= min(fit, share)], default=1), max(1, -(-tasks[1].most // fit))


def _same_rows(x: DataFrame, y: DataFrame) -> bool:
    """The plans of both are the same, so that one stands for the other."""
    plan = lambda df: df._jdf.queryExecution().optimizedPlan()
    return plan(x).sameResult(plan(y))


def portable_sql(a, b):
    """Competitor: the same product as SQL text, without functions, hints or settings of ours."""
    spark, names = a.df.sparkSession, [f"m_{uuid.uuid4().hex}" for _ in range(2)]
    for name, m in zip(names, (a, b)):
        m.df.createOrReplaceTempView(name)
    return _c(spark.sql(f"select x.i, y.j, sum(x.v * y.v) as v from {names[0]} x join {names[1]} y on x.j = y.i group by x.i, y.j"), a, b)


SEMIRINGS = {"plus_times": ("sum", "times"), "min_plus": ("min", "plus"), "max_min": ("max", "min"), "or_and": ("or", "and"), "plus_pair": ("sum", "pair")}


def semiring(a, b, name: str = "plus_times"):
    """Competitor: any of the five semirings. or-and takes non-zero for true and gives 1 or 0."""
    add, mul = SEMIRINGS[name]
    left = a.df.select("i", F.col("j").alias("k"), F.col("v").alias("va"))
    right = b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("vb"))
    x, y = F.col("va"), F.col("vb")
    p = {"times": x * y, "plus": x + y, "min": F.least(x, y), "pair": F.lit(1).cast("long"), "and": (x != 0) & (y != 0)}[mul]
    merge = {"sum": F.sum, "min": F.min, "max": F.max, "or": lambda c: F.bool_or(c).cast("long")}[add]
    return _c(left.join(right, "k").groupBy("i", "j").agg(merge(p).alias("v")), a, b)


def outer_product(a, b):
    """Columns of A against rows of B, both packed, merged by one aggregation."""
    plan = T.chunk_plan(b.n_cols, SPR, "numeric", T.Options())
    return _c(T.coarse_pairs(a, b, plan).groupBy("i", "j").agg(F.sum("p").alias("v")), a, b)


def blocked_outer(a, b, n_blocks: int = 16):
    """Outer product with one level of blocking: its pairs are dealt by column block first and merged inside the block."""
    plan = T.chunk_plan(b.n_cols, SPR, "numeric", T.Options())
    pairs = T.coarse_pairs(a, b, plan).withColumn("block", F.floor(F.col("j") * n_blocks / b.n_cols))
    dealt = pairs.repartition("block", F.shiftright("i", 6))
    return _c(dealt.groupBy("block", F.shiftright("i", 6).alias("rb"), "i", "j").agg(F.sum("p").alias("v")).select("i", "j", "v"), a, b)


def masked(a, b, mask):
    pairs = expand(a, b).join(mask.df.select("i", "j"), ["i", "j"], "left_semi")
    return _c(pairs.groupBy("i", "j").agg(F.sum("p").alias("v")), a, b)


def broadcast_product(a, b, limit_bytes: int = 32 << 20):
    """B is broadcast if its entries, 24 bytes each, are counted to be within the limit; else the relational product."""
    return relational(a, b, "broadcast" if b.df.count() * 24 <= limit_bytes else None)


def grid(a, b, p=4, q=4):
    """Result-stationary grid: A is copied to q column blocks, B to p row blocks."""
    left = a.df.select("i", F.col("j").alias("k"), F.col("v").alias("va"), (F.col("i") % p).alias("gi"), F.explode(F.sequence(F.lit(0), F.lit(q - 1))).alias("gj"))
    right = b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("vb"), (F.col("j") % q).alias("gj"), F.explode(F.sequence(F.lit(0), F.lit(p - 1))).alias("gi"))
    joined = left.join(right.withColumnRenamed("gi", "gi2").withColumnRenamed("gj", "gj2"), [F.col("gi") == F.col("gi2"), F.col("gj") == F.col("gj2"), left.k == right.k])
    return _c(joined.groupBy("i", "j").agg(F.sum(F.col("va") * F.col("vb")).alias("v")), a, b)


def total_products(a, b) -> int:
    """n_inter from row and column counts alone."""
    left = a.df.groupBy(F.col("j").alias("k")).agg(F.count("*").alias("ca"))
    right = b.df.groupBy(F.col("i").alias("k")).agg(F.count("*").alias("cb"))
    return left.join(right, "k").agg(F.coalesce(F.sum(F.col("ca") * F.col("cb")), F.lit(0))).first()[0]


def square(a, spec=SPR):
    return T.two_level(a, a, spec)


def gram(a, spec=SPR):
    """Aᵀ·A."""
    return T.two_level(a.transpose(), a, spec)


def triple(r, a, p):
    """R·A·P, associated so that the first product has fewer elementary products; that product is not written. Rows of P and columns of R are
    made and stored once, and only once for both where one is the other's transpose."""
    scratch, value = Scratch(a.df.sparkSession), T.value_type(r, a, p)
    a = SparseMatrix(scratch.write(a.df, "triple"), a.n_rows, a.n_cols)
    right = scratch.write(X.rows_of(p), "triple_rows")
    left = right if _same_rows(r.transpose().df, p.df) else scratch.write(X.rows_of(r.transpose()), "triple_columns")

    def products(lists, key):
        return lists.select("k", F.size("y").alias("n")).join(a.df.groupBy(F.col(key).alias("k")).agg(F.count("*").alias("c")), "k").agg(F.coalesce(F.sum(F.col("n") * F.col("c")), F.lit(0))).first()[0]

    if products(left, "i") <= products(right, "j"):
        return X.triple(right, a.transpose(), left, p.n_cols, r.n_rows, value).transpose()
    return X.triple(left, a, right, r.n_rows, p.n_cols, value)


def choose(a, b, spec=SPR, small_bytes: int = 32 << 20) -> str:
    """Name of the method by size: broadcast for a small B, the relational product where partial aggregation shrinks the products
    (several a result cell could hold) or all rows are short, else the two-level method."""
    if b.df.count() * 24 <= small_bytes:
        return "broadcast"
    n = total_products(a, b)
    if n >= 4 * a.n_rows * b.n_cols or n < 256 * max(1, a.n_rows):
        return "relational"
    return "two_level"


def product(a, b, method: str = "auto", spec=SPR):
    method = choose(a, b, spec) if method == "auto" else method
    return {"broadcast": broadcast_product, "relational": relational, "two_level": lambda x, y: T.two_level(x, y, spec)}[method](a, b)
