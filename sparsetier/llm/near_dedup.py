"""MinHash near-dedup with min-max hashing.

Each permutation gives two signature values, the minimum and the maximum of the permuted shingle hashes; bands of
``ROWS`` values are candidate keys. Equal word sequences are one node with a number of its own, whatever doc_ids its rows have. Links are
confirmed on the shingles themselves, not on hashes.

First step: in a bucket every member is compared with one other only, the one whose buckets hold most members (the likely original of
a group of copies). Second step: nodes of buckets that still hold several components meet by an exact prefix filter: shingles are
ordered by rising number of nodes that hold them, and two sets of size x >= y can only be similar enough if a shingle at place
i of the larger and j of the smaller has 3 (x + y) <= 7 min(x - i, y - j) (the overlap that 75 % asks for), which also binds i to x / 4,
j to y / 7 and y to a range that narrows with i. Sizes are dealt into classes that are part of the join key. Members of a group
that are alike but not linked hold shingles of their own first, so they do not meet; no pair that could be linked is passed over.

At Jaccard 0.75 a pair misses all 30 bands of 4 with chance 1.1e-5. Null or empty texts (no words): n_shingles 0, own component.
Rows without doc_id are measured, kept and linked with nothing. Rows that repeat a doc_id share its component, and
links of any of their texts count. Repeated rows are one node. Whole texts are read, however long; memory is some 80 bytes per word of
the longest text. Other input columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.llm.common import Scratch, arrow_rows
from sparsetier.llm.graph import components

SHINGLE, SIMILAR, PERMUTATIONS, ROWS, SALTS = 5, 75, 60, 4, 8
HELD_SHINGLES = 1 << 19
BLANK = r"[\x20\x09-\x0D]+"


def words_of(text: str) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").lower().split()


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return h ^ (h >> np.uint64(29))


def shingle_hashes(words: list[bytes], cache: dict[bytes, int]) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles of a word list."""
    import xxhash

    if not words:
        return np.zeros(0, dtype=np.uint64)
    if len(words) < SHINGLE:
        return np.array([xxhash.xxh3_64_intdigest(b"short " + b" ".join(words))], dtype=np.uint64)
    if len(cache) > 500_000:
        cache.clear()
    for w in set(words):
        if w not in cache:
            cache[w] = xxhash.xxh3_64_intdigest(w)
    h = np.array([cache[w] for w in words], dtype=np.uint64)
    total = np.zeros(len(words) - SHINGLE + 1, dtype=np.uint64)
    for n in range(SHINGLE):
        total = _mix(total + np.uint64(n + 1)) + h[n:n + len(total)]
    return np.unique(_mix(total))


def shingles(words: list[bytes]) -> set[bytes]:
    """The shingles themselves; words hold no blanks, so joining them loses nothing."""
    if len(words) < SHINGLE:
        return {b" ".join(words)} if words else set()
    return {b" ".join(words[n:n + SHINGLE]) for n in range(len(words) - SHINGLE + 1)}


def minmax_bands(h: np.ndarray, permutations: int = PERMUTATIONS, rows: int = ROWS) -> list[int]:
    """Band keys from both the minimum and the maximum under each permutation."""
    rng = np.random.default_rng(20)
    a = rng.integers(1, 1 << 63, permutations, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    x = rng.integers(0, 1 << 63, permutations, dtype=np.uint64)
    low, high = np.full(permutations, ~np.uint64(0)), np.zeros(permutations, dtype=np.uint64)
    for at in range(0, len(h), 1024):
        p = (h[None, at:at + 1024] ^ x[:, None]) * a[:, None]
        p ^= p >> np.uint64(32)
        p *= np.uint64(0xD6E8FEB86659FD93)
        low, high = np.minimum(low, p.min(1)), np.maximum(high, p.max(1))
    values = np.concatenate([low, high]).reshape(-1, rows)
    out = np.arange(1, len(values) + 1, dtype=np.uint64)
    for r in range(rows):
        out = _mix(out * np.uint64(0x9E3779B97F4A7C15) + values[:, r])
    return out.view(np.int64).tolist()


def normalized(docs: DataFrame) -> DataFrame:
    """(doc_id, words, key): the words with A-Z in lower case and one blank between them; key is 16 bytes of their SHA-256, null
    for rows without words or without doc_id."""
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    words = F.trim(F.regexp_replace(F.translate(F.coalesce(F.col("text"), F.lit("")), upper, lower), BLANK, " "))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), words.alias("words"))
    key = F.unhex(F.substring(F.sha2(F.col("words").cast("binary"), 256), 1, 32))
    return rows.withColumn("key", F.when((F.col("words") != "") & F.col("doc_id").isNotNull(), key))


def signatures(rows: DataFrame) -> DataFrame:
    def start():
        cache: dict[bytes, int] = {}

        def work(cols):
            for doc_id, words, key in zip(cols["doc_id"], cols["words"], cols["key"]):
                h = shingle_hashes(words_of(words), cache)
                yield doc_id, key, len(h), minmax_bands(h) if key else None

        return work

    return arrow_rows(rows, "doc_id long, key binary, n_shingles long, bands array<long>", start)


def confirm(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """Edges (u, v) among the pairs whose whole shingle sets are similar enough."""

    def start():
        known: dict[int, set[bytes]] = {}
        held = [0]

        def of(node, words):
            if node not in known:
                own = shingles(words_of(words))
                if held[0] + len(own) > HELD_SHINGLES:
                    known.clear()
                    held[0] = 0
                known[node] = own
                held[0] += len(own)
            return known[node]

        def work(cols):
            for u, v, a, b in zip(cols["u"], cols["v"], cols["a"], cols["b"]):
                y = of(v, b)
                x = known[u] if u in known else shingles(words_of(a))
                both = len(x & y)
                if 100 * both >= SIMILAR * (len(x) + len(y) - both):
                    yield u, v

        return work

    rows = pairs.join(texts.select(F.col("node").alias("u"), F.col("words").alias("a")), "u").join(
        texts.select(F.col("node").alias("v"), F.col("words").alias("b")), "v")
    return arrow_rows(rows, "u long, v long", start)


def _fits(a: str, b: str):
    return 100 * F.least(a, b) >= SIMILAR * F.greatest(a, b)


def _spread(rows: DataFrame) -> DataFrame:
    """Each row once per salt, so that a large bucket meets it in several tasks."""
    return rows.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))


def _tokens(nodes: DataFrame) -> DataFrame:
    """(node, n, c, tokens) from (node, n, c, words)."""

    def run(batches):
        cache: dict[bytes, int] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                piece = batch.slice(at, 256)
                found = [shingle_hashes(words_of(w), cache).view(np.int64) for w in piece.column("words").to_pylist()]
                offsets = pa.array(np.concatenate([[0], np.cumsum([len(f) for f in found])]).astype(np.int32))
                lists = pa.ListArray.from_arrays(offsets, pa.array(np.concatenate(found)))
                yield pa.RecordBatch.from_arrays([piece.column("node"), piece.column("n"), piece.column("c"), lists], names=["node", "n", "c", "tokens"])

    return nodes.select("node", "n", "c", "words").mapInArrow(run, "node long, n long, c long, tokens array<long>")


def _size_class(n):
    return F.floor(16 * F.log2(n)).cast("int")


def prefix_pairs(tokens: DataFrame) -> DataFrame:
    """(u, v) of nodes of different components ``c`` that pass the prefix, size and position filters."""
    flat = tokens.select("node", F.explode("tokens").alias("token"))
    several = flat.groupBy("token").agg(F.count("*").alias("df")).where("df > 1")
    held = flat.join(several, "token").groupBy("node").agg(F.sort_array(F.collect_list(F.struct("df", "token"))).alias("held"))
    placed = held.join(tokens.select("node", "n", "c"), "node").withColumn("alone", F.col("n") - F.size("held"))
    first = F.greatest(F.floor(F.col("n") / 4) + 1 - F.col("alone"), F.lit(0)).cast("int")
    prefix = placed.select("node", "n", "c", "alone", F.posexplode(F.slice("held", F.lit(1), first)).alias("pos", "t")).select(
        "node", "n", "c", (F.col("alone") + F.col("pos")).alias("at"), F.col("t.token").alias("token"))
    most = F.least(F.col("n"), F.floor(7 * (F.col("n") - F.col("at")) / 3) - F.col("n"))
    least = F.ceil(3 * F.col("n") / 4)
    large = prefix.where((4 * F.col("at") <= F.col("n")) & (most >= least)).select(
        "token", F.col("node").alias("x"), F.col("n").alias("xn"), F.col("c").alias("xc"), F.col("at").alias("i"),
        F.explode(F.sequence(_size_class(least), _size_class(most))).alias("size"))
    small = prefix.where(7 * F.col("at") <= F.col("n")).select(
        "token", F.col("node").alias("y"), F.col("n").alias("yn"), F.col("c").alias("yc"), F.col("at").alias("j"), _size_class(F.col("n")).alias("size"))
    met = large.join(small, ["token", "size"]).where("xc <> yc and yn <= xn and 4 * yn >= 3 * xn and 3 * (xn + yn) <= 7 * least(xn - i, yn - j)")
    return met.select(F.least("x", "y").alias("u"), F.greatest("x", "y").alias("v")).distinct()


def near_components(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept), one row per row of ``docs``."""
    scratch = Scratch(docs.sparkSession)
    rows = normalized(docs)
    sig = scratch.write(signatures(rows), "minmax")
    nodes = sig.where("key is not null").groupBy("key").agg(F.min("doc_id").alias("first_id"), F.first("n_shingles").alias("n"), F.first("bands").alias("bands"), F.count("*").alias("copies"))
    nodes = scratch.write(nodes.withColumn("node", F.monotonically_increasing_id()), "nodes")

    work = Scratch(docs.sparkSession)
    members = nodes.select("node", "n", F.posexplode("bands").alias("band", "value")).select(F.xxhash64("band", "value").alias("bucket"), "node", "n").distinct()
    members = members.withColumn("salt", F.pmod(F.col("node"), F.lit(SALTS)).cast("int"))
    sizes = members.groupBy("bucket").agg(F.count("*").alias("size")).where("size > 1")
    shared = work.write(members.join(_spread(sizes), ["bucket", "salt"]), "shared_buckets")
    ranked = shared.join(shared.groupBy("node").agg(F.sum("size").alias("pull")), "node")
    heads = ranked.groupBy("bucket").agg(F.max_by(F.struct("node", "n"), F.struct("pull", -F.col("node"))).alias("head"))
    members = work.write(shared.join(_spread(heads), ["bucket", "salt"]).select(
        "bucket", "node", "n", F.col("head.node").alias("head"), F.col("head.n").alias("head_n")), "buckets")

    star = work.write(members.where("node <> head").where(_fits("n", "head_n")).select(F.col("node").alias("u"), F.col("head").alias("v")).distinct(), "star_pairs")
    needed = nodes.join(members.select("node").distinct(), "node", "left_semi").select("key", "node")
    texts = rows.where("key is not null").groupBy("key").agg(F.first("words").alias("words"))
    texts = work.write(texts.join(needed, "key").select("node", "words"), "texts")
    placed = sig.where("key is not null").select("key", "doc_id").distinct().join(nodes.select("key", "node"), "key")
    several = placed.groupBy("doc_id").agg(F.min("node").alias("v"), F.max("node").alias("top")).where("v < top").select("doc_id", "v")
    same_id = placed.join(several, "doc_id").where("node <> v").select(F.col("node").alias("u"), "v")
    edges = scratch.write(confirm(star, texts).unionByName(same_id), "edges")
    found = components(edges)

    where = members.join(found, "node", "left").select("bucket", "node", "n", F.coalesce("component", "node").alias("c"))
    mixed = where.groupBy("bucket").agg(F.min("c").alias("low"), F.max("c").alias("high")).where("low < high").select("bucket")
    rest = where.join(mixed, "bucket", "left_semi").select("node", "n", "c").distinct()
    tokens = work.write(_tokens(rest.join(texts, "node")), "tokens")
    more = work.write(prefix_pairs(tokens), "rest_pairs")
    more = scratch.write(confirm(more, texts), "edges")
    work.clear()
    if not more.isEmpty():
        found = components(found.select(F.col("node").alias("u"), F.col("component").alias("v")).unionByName(more))

    owner = nodes.join(found, "node", "left").select("key", "first_id", "copies", F.coalesce("component", "node").alias("c"))
    names = owner.groupBy("c").agg(F.min("first_id").alias("component_id"), F.sum("copies").alias("n_rows")).where("n_rows > 1")
    moved = owner.join(names, "c").select("key", "component_id", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    out = sig.select("doc_id", "key", "n_shingles", F.pmod(F.coalesce("doc_id", F.lit(0)), F.lit(SALTS)).cast("int").alias("salt"))
    out = out.join(moved, ["key", "salt"], "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("component_id") == F.col("doc_id"), F.lit(True)))
