"""Products of dense or nearly dense results by tiles: packed blocks of the factors meet in a task, which multiplies them at once. What is
exchanged are the factors and merged tiles, never the elementary products."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.plans import two_level as T
from sparsetier.sources.matrices import SparseMatrix
from sparsetier.store import Scratch

#: Rows and columns of a tile, positions along the sum multiplied at a time, and rows of A of a triple product in one group.
TILE, INNER, GROUP = 1 << 10, 1 << 10, 1 << 13
#: Positions along the sum of a packed block: places in it are two bytes.
WIDE = 1 << 13
#: Tiles a task of a triple product holds before it passes their sums on, and how many dense products take as long as a sparse one.
HELD, DEAR = 24, 200


def exact_matmul(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Product of matrices of whole numbers: in floating point only where no sum can reach 2**53."""
    if x.dtype != np.int64:
        return x @ y
    most = int(max(x.max(initial=0), -x.min(initial=0))) * int(max(y.max(initial=0), -y.min(initial=0))) * x.shape[1]
    return (x.astype(np.float64) @ y.astype(np.float64)).astype(np.int64) if most < 1 << 53 else x @ y


class Cells:
    """Cells (x, y, v) of a block; ``known`` says where a value is not null."""

    def __init__(self, x, y, v, known):
        self.x, self.y, self.v, self.known = x, y, v, known

    def plain(self) -> bool:
        """Every product of such cells is a value above zero, so that sums tell which cells there are."""
        return bool(self.known.all()) and bool((self.v > 0).all())

    def take(self, pick):
        return Cells(self.x[pick], self.y[pick], self.v[pick], self.known[pick])


def _dense(rows, cols, v, shape, dtype):
    out = np.zeros(shape, dtype=dtype)
    np.add.at(out, (rows, cols), v)
    return out


def multiply(a: Cells, b: Cells):
    """(rows, columns, sum, there, known) of the product of the cells (row, k) and (k, column): row and column numbers, and over them
    the sums, which cells have a product at all, and which of them have one that is not null. Dense over TILE x TILE at the callers'."""
    rows, r = np.unique(a.x, return_inverse=True)
    cols, c = np.unique(b.y, return_inverse=True)
    shared = np.intersect1d(a.y, b.x)
    total = np.zeros((len(rows), len(cols)), dtype=a.v.dtype)
    plain = a.plain() and b.plain()
    there, known = (None, None) if plain else (np.zeros(total.shape), np.zeros(total.shape))
    for at in range(0, len(shared), INNER):
        part = shared[at:at + INNER]
        ka, kb = np.searchsorted(part, a.y), np.searchsorted(part, b.x)
        own, other = np.flatnonzero(part[np.minimum(ka, len(part) - 1)] == a.y), np.flatnonzero(part[np.minimum(kb, len(part) - 1)] == b.x)
        left = lambda v, t: _dense(r[own], ka[own], v[own], (len(rows), len(part)), t)
        right = lambda v, t: _dense(kb[other], c[other], v[other], (len(part), len(cols)), t)
        total += exact_matmul(left(a.v, a.v.dtype), right(b.v, b.v.dtype))
        if not plain:
            there += left(np.ones(len(a.v)), float) @ right(np.ones(len(b.v)), float)
            known += left(a.known, float) @ right(b.known, float)
    if plain:
        there = known = total > 0
    return rows, cols, total, there > 0, known > 0


def _batch(i, j, v, known, arrow):
    return pa.RecordBatch.from_arrays([pa.array(i, pa.int64()), pa.array(j, pa.int64()), pa.array(v, arrow, mask=~known)], names=["i", "j", "v"])


def _columns(value: str):
    return {"long": (np.int64, pa.int64()), "double": (np.float64, pa.float64())}[value]


def _read(batch, first: str, second: str, dtype) -> Cells:
    """The packed cells of a batch's rows, list by list one behind the other."""
    flat = lambda name: batch.column(name).flatten()
    v = flat("v")
    known = np.asarray(v.is_valid().to_numpy(zero_copy_only=False), dtype=bool)
    return Cells(flat(first).to_numpy(zero_copy_only=False).astype(np.int64), flat(second).to_numpy(zero_copy_only=False).astype(np.int64), v.fill_null(0).to_numpy(zero_copy_only=False).astype(dtype), known)


def packed_blocks(m: SparseMatrix, outer: str, inner: str, side: int, value: str, wide: int = WIDE) -> DataFrame:
    """(b, bk, cells): the cells of each block of ``side`` rows (or columns) and ``wide`` positions along the sum, packed, many cells at a time."""
    dtype = _columns(value)[0]

    def run(batches):
        held, n = [], 0
        for batch in batches:
            flat = lambda c: batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64)
            v = batch.column("v")
            held.append(Cells(flat("x"), flat("y"), v.fill_null(0).to_numpy(zero_copy_only=False).astype(dtype), np.asarray(v.is_valid().to_numpy(zero_copy_only=False), dtype=bool)))
            n += batch.num_rows
            if n >= 1 << 20:
                yield emit(_joined(held))
                held, n = [], 0
        if n:
            yield emit(_joined(held))

    def emit(cells):
        codec = pa.Codec("zstd", compression_level=1)
        b, bk = cells.x // side, cells.y // wide
        order = np.lexsort((cells.y, cells.x, bk, b))
        cells, b, bk = cells.take(order), b[order], bk[order]
        cuts = np.flatnonzero(np.append(True, (np.diff(b) != 0) | (np.diff(bk) != 0)))
        blobs = [_blob(cells.take(slice(at, end)), b[at] * side, bk[at] * wide, codec) for at, end in zip(cuts.tolist(), [*cuts[1:].tolist(), len(b)])]
        return pa.RecordBatch.from_arrays([pa.array(b[cuts], pa.int64()), pa.array(bk[cuts], pa.int64()), pa.array(blobs, pa.binary())], names=["b", "bk", "cells"])

    return m.df.select(F.col(outer).alias("x"), F.col(inner).alias("y"), "v").mapInArrow(run, "b long, bk long, cells binary")


def _narrow(v: np.ndarray) -> np.ndarray:
    """Whole numbers in as few bytes as they need."""
    if v.dtype == np.int64 and len(v):
        low, high = v.min(), v.max()
        return v.astype(next(kind for kind in (np.int8, np.int16, np.int32, np.int64) if np.iinfo(kind).min <= low and high <= np.iinfo(kind).max))
    return v


def _blob(cells: Cells, x: int, y: int, codec) -> bytes:
    """Number of cells and kind of their values, and the cells from (x, y) on: steps along the rows, columns, values, and which are null."""
    v = _narrow(cells.v)
    steps = np.diff(cells.x - x, prepend=0).astype(np.uint32)
    plain = b"".join(part.tobytes() for part in (_planes(steps), _planes((cells.y - y).astype(np.uint16)), _planes(v), np.packbits(cells.known)))
    return len(v).to_bytes(8, "little") + v.dtype.str.encode().ljust(4) + codec.compress(plain, asbytes=True)


def _planes(v: np.ndarray) -> np.ndarray:
    """Bytes of equal weight one behind the other, which packs well."""
    return np.ascontiguousarray(v.view(np.uint8).reshape(len(v), -1).T)


def _cells(blob: bytes, x: int, y: int, dtype, codec) -> Cells:
    n, kind = int.from_bytes(blob[:8], "little"), np.dtype(blob[8:12].decode().strip())
    plain = np.frombuffer(codec.decompress(blob[12:], decompressed_size=n * (6 + kind.itemsize) + -(-n // 8), asbytes=True), np.uint8)
    at, out = 0, []
    for form in (np.dtype(np.uint32), np.dtype(np.uint16), kind):
        size = n * form.itemsize
        out.append(np.ascontiguousarray(plain[at:at + size].reshape(form.itemsize, n).T).view(form).ravel())
        at += size
    return Cells(np.cumsum(out[0].astype(np.int64)) + x, out[1].astype(np.int64) + y, out[2].astype(dtype), np.unpackbits(plain[at:], count=n).astype(bool))


def _side(rows: int, inner: int, parts: int) -> int:
    """Rows of the square of tiles that a task makes at a time: a few squares for each task, of at most 2^20 places of a factor. A sum longer
    than WIDE takes single tiles, whose sums are carried on."""
    if inner > WIDE:
        return TILE
    shared = -(-rows // max(1, math.isqrt(4 * parts)))
    return TILE * max(1, min(-(-shared // TILE), (1 << 20) // (inner * TILE)))


def compressed_blocks(packed: DataFrame, n_rows: int, n_cols: int, side: int, wide: int, value: str, parts: int) -> DataFrame:
    """(_1, _2): number and rows of each block with a value that is not null, as the library stores a sparse matrix, ``parts`` partitions of them."""
    dtype = _columns(value)[0]

    def run(batches):
        codec, now, found = pa.Codec("zstd"), None, []
        for batch in batches:
            keys, blobs = list(zip(batch.column("b").to_pylist(), batch.column("bk").to_pylist())), batch.column("cells")
            for n, own in enumerate(keys):
                if own != now:
                    if found:
                        yield from block(now, _joined(found))
                    now, found = own, []
                found.append(_cells(blobs[n].as_py(), own[0] * side, own[1] * wide, dtype, codec))
        if found:
            yield from block(now, _joined(found))

    def block(own, cells):
        cells = cells.take(cells.known)
        if not len(cells.x):
            return
        cells = cells.take(np.lexsort((cells.y, cells.x)))
        rows, cols = min(side, n_rows - own[0] * side), min(wide, n_cols - own[1] * wide)
        starts = np.searchsorted(cells.x, np.arange(rows + 1) + own[0] * side).astype(np.int32)
        one = lambda v, kind: pa.array([v], kind)
        listed = lambda v: pa.ListArray.from_arrays(pa.array([0, len(v)], pa.int32()), pa.array(v))
        parts = [one(0, pa.int8()), one(rows, pa.int32()), one(cols, pa.int32()), listed(starts), listed((cells.y - own[1] * wide).astype(np.int32)), listed(cells.v.astype(np.float64)), one(True, pa.bool_())]
        number = pa.StructArray.from_arrays([one(n, pa.int64()) for n in own], names=["_1", "_2"])
        yield pa.RecordBatch.from_arrays([number, pa.StructArray.from_arrays(parts, names=["type", "numRows", "numCols", "colPtrs", "rowIndices", "values", "isTransposed"])], names=["_1", "_2"])

    dealt = packed.repartition(parts, "b", "bk").sortWithinPartitions("b", "bk")
    return dealt.mapInArrow(run, "_1 struct<_1 long, _2 long>, _2 struct<type byte, numRows int, numCols int, colPtrs array<int>, rowIndices array<int>, values array<double>, isTransposed boolean>")


def tiled(a: SparseMatrix, b: SparseMatrix) -> SparseMatrix:
    """C = A·B by squares of tiles of C that have a meeting block of both: blocks of rows of A and of columns of B, packed once and stored,
    are copied to the squares of their row and column. A task multiplies them tile by tile; no tile leaves it but as cells."""
    value = T.value_type(a, b)
    dtype, arrow = _columns(value)
    spark = a.df.sparkSession
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    side = _side(max(a.n_rows, b.n_cols), a.n_cols, parts)
    scratch = Scratch(spark)
    left = scratch.write(packed_blocks(a, "i", "j", side, value), "left_blocks").withColumnRenamed("b", "bi")
    right = scratch.write(packed_blocks(b, "j", "i", side, value), "right_blocks").withColumnRenamed("b", "bj")
    copied = lambda m, kind, others: m.join(F.broadcast(others.distinct()), "bk").select("bi", "bj", "bk", F.lit(kind).alias("kind"), "cells")
    met = copied(left, 0, right.select("bj", "bk")).unionByName(copied(right, 1, left.select("bi", "bk")))

    def blocks(batches):
        """((bi, bj, bk), left, right) where both are there."""
        codec, now, found = pa.Codec("zstd"), None, None
        for batch in batches:
            keys, kinds, blobs = list(zip(*(batch.column(c).to_pylist() for c in ("bi", "bj", "bk")))), batch.column("kind").to_pylist(), batch.column("cells")
            for n, (own, kind) in enumerate(zip(keys, kinds)):
                if own != now:
                    if now is not None and all(found):
                        yield now, *map(_joined, found)
                    now, found = own, ([], [])
                found[kind].append(_cells(blobs[n].as_py(), own[kind] * side, own[2] * WIDE, dtype, codec))
        if now is not None and all(found):
            yield now, *map(_joined, found)

    def run(batches):
        tile = None
        for (bi, bj, _), x, y in blocks(batches):
            by_row, by_column = _by_tile(x), _by_tile(y)
            for ti, some in by_row:
                for tj, others in by_column:
                    if tile is not None and tile[0] != (ti, tj):
                        yield from _emit(*tile, arrow)
                        tile = None
                    rows, cols, total, there, known = multiply(some, Cells(others.y, others.x, others.v, others.known))
                    if tile is None:
                        tile = ((ti, tj), np.zeros((TILE, TILE), dtype), np.zeros((TILE, TILE), bool), np.zeros((TILE, TILE), bool))
                    at = np.ix_(rows - ti * TILE, cols - tj * TILE)
                    for held, new in zip(tile[1:], (total, there, known)):
                        held[at] += new
        if tile is not None:
            yield from _emit(*tile, arrow)

    squares = -(-b.n_cols // side)
    dealt = met.repartitionById(parts, F.pmod(F.col("bi") * squares + F.col("bj"), F.lit(parts)).cast("int")).sortWithinPartitions("bi", "bj", "bk", "kind")
    return SparseMatrix(dealt.mapInArrow(run, f"i long, j long, v {value}"), a.n_rows, b.n_cols)


def _by_tile(cells: Cells):
    """(number, cells) of the tiles along x."""
    order = np.argsort(cells.x // TILE, kind="stable")
    cells = cells.take(order)
    tile = cells.x // TILE
    cuts = np.flatnonzero(np.append(True, np.diff(tile) != 0)).tolist()
    return [(int(tile[at]), cells.take(slice(at, end))) for at, end in zip(cuts, [*cuts[1:], len(tile)])]


def _emit(own, total, there, known, arrow):
    """The cells of a tile, some rows at a time."""
    for at in range(0, TILE, 64):
        r, c = np.nonzero(there[at:at + 64])
        if len(r):
            yield _batch(r + at + own[0] * TILE, c + own[1] * TILE, total[at:at + 64][r, c], known[at:at + 64][r, c], arrow)


def rows_of(m: SparseMatrix) -> DataFrame:
    """(k, y, v): the columns and values of each row of a matrix as lists of equal order. One exchange at most, none where the cells are dealt by row."""
    number = "int" if m.n_cols < 1 << 31 else "long"
    cells = m.df.groupBy(F.col("i").alias("k")).agg(F.collect_list(F.struct(F.col("j").cast(number).alias("j"), "v")).alias("c"))
    return cells.select("k", F.col("c.j").alias("y"), F.col("c.v").alias("v"))


def _dealt(df: DataFrame, pick, value: str, number: str) -> DataFrame:
    """(g, x, y, v): the cells that ``pick`` reads of a batch, those of each group of rows or columns in lists, many batches at a time."""
    arrow = _columns(value)[1]
    kept = pa.int32() if number == "int" else pa.int64()

    def run(batches):
        held, n = [], 0
        for batch in batches:
            held.append(pick(batch))
            n += len(held[-1][0].x)
            if n >= 1 << 20:
                yield from emit(held)
                held, n = [], 0
        if n:
            yield from emit(held)

    def emit(held):
        cells, g = _joined([c for c, _ in held]), np.concatenate([g for _, g in held])
        order = np.argsort(g, kind="stable")
        cells, g = cells.take(order), g[order]
        cuts = np.append(0, np.flatnonzero(np.diff(g)) + 1)
        at = pa.array(np.append(cuts, len(g)), pa.int32())
        lists = lambda flat: pa.ListArray.from_arrays(at, flat)
        yield pa.RecordBatch.from_arrays([pa.array(g[cuts], pa.int64()), lists(pa.array(cells.x, kept)), lists(pa.array(cells.y, kept)), lists(pa.array(cells.v, arrow, mask=~cells.known))], names=["g", "x", "y", "v"])

    return df.mapInArrow(run, f"g long, x array<{number}>, y array<{number}>, v array<{value}>")


def _joined(cells) -> Cells:
    return Cells(*(np.concatenate([getattr(c, f) for c in cells]) for f in ("x", "y", "v", "known")))


def _listed(batch, dtype) -> Cells:
    """The cells (k, y, v) of rows with lists."""
    y = batch.column("y")
    sizes = np.diff(y.offsets.to_numpy())
    v = batch.column("v").flatten()
    known = np.asarray(v.is_valid().to_numpy(zero_copy_only=False), dtype=bool)
    return Cells(np.repeat(batch.column("k").to_numpy(zero_copy_only=False).astype(np.int64), sizes), y.flatten().to_numpy(zero_copy_only=False).astype(np.int64), v.fill_null(0).to_numpy(zero_copy_only=False).astype(dtype), known)


def triple(left: DataFrame, a: SparseMatrix, right: DataFrame, n_rows: int, n_cols: int, value: str, most: int = HELD, dear: int = DEAR) -> SparseMatrix:
    """R·(A·P), both products in one pass over groups of rows of A, with ``left`` the columns of R and ``right`` the rows of P as lists:
    a group gets its cells of A, the columns of R that meet it, and each row of P that it names once, however many of its rows name it.
    A·P is held a tile at a time and never written. Neighbouring groups are dealt to one task; sums of tiles pass on packed, when a
    task holds ``most`` of them, and are merged strip by strip."""
    dtype, arrow = _columns(value)
    spark = a.df.sparkSession
    n_groups = -(-a.n_rows // GROUP)
    parts = max(1, min(n_groups, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    number = "int" if max(a.n_rows, a.n_cols, n_rows, n_cols) < 1 << 31 else "long"
    kind = lambda df, n: df.select("g", F.lit(n).alias("kind"), "x", F.col("y").cast(f"array<{number}>").alias("y"), "v")

    def columns(batch):
        c = _listed(batch, dtype)
        return Cells(c.y, c.x, c.v, c.known), c.x // GROUP

    def cells(batch):
        flat = lambda c: batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64)
        v = batch.column("v")
        c = Cells(flat("i"), flat("j"), v.fill_null(0).to_numpy(zero_copy_only=False).astype(dtype), np.asarray(v.is_valid().to_numpy(zero_copy_only=False), dtype=bool))
        return c, c.x // GROUP

    named = a.df.select(F.floor(F.col("i") / GROUP).alias("g"), F.col("j").alias("k")).distinct()
    met = named.join(right, "k").select("g", F.array(F.col("k").cast(number)).alias("x"), "y", "v")
    every = kind(_dealt(left, columns, value, number), 0).unionByName(kind(_dealt(a.df.select("i", "j", "v"), cells, value, number), 1)).unionByName(kind(met, 2))
    place = F.floor(F.least(F.greatest(F.col("g"), F.lit(0)), F.lit(n_groups - 1)) * parts / n_groups)
    dealt = every.repartitionById(parts, place.cast("int")).sortWithinPartitions("g", "kind")
    strips = dealt.mapInArrow(lambda batches: _triple_tiles(batches, dtype, most, dear), "bi long, bj long, strip int, at binary, sums binary, kind string, unknown binary")
    merged = strips.repartition("bi", "bj", "strip").sortWithinPartitions("bi", "bj", "strip")
    return SparseMatrix(merged.mapInArrow(lambda batches: _merged_strips(batches, dtype, arrow), f"i long, j long, v {value}"), n_rows, n_cols)


def _groups(batches, dtype):
    """(R's, A's, P's) cells of each group of which all three are there."""
    now, found = None, None
    for batch in batches:
        g, kind = batch.column("g").to_numpy(), batch.column("kind").to_numpy()
        cuts = [0, *(np.flatnonzero((np.diff(g) != 0) | (np.diff(kind) != 0)) + 1).tolist(), len(g)]
        for at, end in zip(cuts, cuts[1:]):
            if at == end:
                continue
            if now != g[at]:
                if now is not None and all(found):
                    yield [_joined(c) for c in found]
                now, found = g[at], ([], [], [])
            piece = batch.slice(at, end - at)
            if kind[at] == 2:
                piece = pa.RecordBatch.from_arrays([piece.column("x").flatten(), piece.column("y"), piece.column("v")], names=["k", "y", "v"])
                found[2].append(_listed(piece, dtype))
            else:
                found[kind[at]].append(_read(piece, "x", "y", dtype))
    if now is not None and all(found):
        yield [_joined(c) for c in found]


def _added(place, v, size, dtype):
    """Sums of values by place: in floating point only where no sum can reach 2**53."""
    if dtype != np.int64 or (len(v) and int(max(v.max(), -v.min())) * len(v) < 1 << 53):
        return np.bincount(place, weights=v, minlength=size).astype(dtype)
    out = np.zeros(size, dtype)
    np.add.at(out, place, v)
    return out


def _steps(mid: Cells, cols: Cells, low, high, base: int, y, width: int):
    """Rows of A·P from ``base`` on over the columns of one tile, dense: sums, cells that have a product, those with one not null."""
    n = high - low
    of = np.repeat(np.arange(len(n)), n)
    at = np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(low, n)
    place = (mid.x[of] - base) * width + y[at]
    size = INNER * width
    total = _added(place, mid.v[of] * cols.v[at], size, mid.v.dtype).reshape(INNER, width)
    if mid.plain() and cols.plain():
        return total, None, None
    there, known = np.zeros(size, bool), np.zeros(size, bool)
    there[place] = True
    known[place[mid.known[of] & cols.known[at]]] = True
    return total, there.reshape(INNER, width), known.reshape(INNER, width)


def _triple_tiles(batches, dtype, most, dear):
    tiles = {}
    for left, mid, right in _groups(batches, dtype):
        left, mid = left.take(np.argsort(left.y, kind="stable")), mid.take(np.argsort(mid.x, kind="stable"))
        right = right.take(np.lexsort((right.x, right.y // TILE)))
        tile_of = right.y // TILE
        edges = np.append(np.flatnonzero(np.append(True, np.diff(tile_of) != 0)), len(tile_of))
        bases = [(base * INNER, slice(*np.searchsorted(mid.x, [base * INNER, (base + 1) * INNER])), slice(*np.searchsorted(left.y, [base * INNER, (base + 1) * INNER]))) for base in np.unique(mid.x // INNER).tolist()]
        factors = {}
        for start, end in zip(edges.tolist(), edges[1:].tolist()):
            cols, bj = right.take(slice(start, end)), int(tile_of[start])
            columns, y = np.unique(cols.y, return_inverse=True)
            low, high = np.searchsorted(cols.x, mid.y, "left"), np.searchsorted(cols.x, mid.y, "right")
            for base, some, own in bases:
                if own.start == own.stop or not (high[some] > low[some]).any():
                    continue
                if base not in factors:
                    mine = left.take(own)
                    bi = mine.x // TILE
                    factors[base] = [(n, _Factor(mine.take(bi == n), base)) for n in np.unique(bi).tolist()]
                step = _steps(mid.take(some), cols, low[some], high[some], base, y, len(columns))
                for bi, factor in factors[base]:
                    if (bi, bj) not in tiles:
                        if len(tiles) >= most:
                            for at, tile in tiles.items():
                                yield from _packed_strips(at, *tile)
                            tiles.clear()
                        tiles[bi, bj] = (np.zeros((TILE, TILE), dtype), np.zeros((TILE, TILE), bool), np.zeros((TILE, TILE), bool))
                    factor.add(step, tiles[bi, bj], factor.rows - bi * TILE, columns - bj * TILE, dear)
    for at, tile in tiles.items():
        yield from _packed_strips(at, *tile)


class _Factor:
    """The cells of R over one tile of its rows and INNER of its columns."""

    def __init__(self, cells: Cells, base: int):
        self.cells, self.k = cells, cells.y - base
        self.rows, self.r = np.unique(cells.x, return_inverse=True)
        self._forms = {}

    def _form(self, name: str):
        if name not in self._forms:
            v = {"v": self.cells.v, "there": np.ones(len(self.k)), "known": self.cells.known.astype(float)}[name]
            self._forms[name] = _dense(self.r, self.k, v, (len(self.rows), INNER), v.dtype)
        return self._forms[name]

    def add(self, step, tile, rows, columns, dear):
        """Add the product with rows of A·P to a tile, over its cells where these are few."""
        total, there, known = step
        full = total != 0 if there is None else there
        least = int(full.sum(axis=1)[self.k].sum())
        if not least:
            return
        if least * dear < len(self.rows) * INNER * len(columns):
            k, c = np.nonzero(full)
            middle = Cells(k, c, total[k, c], np.ones(len(k), bool) if known is None else known[k, c])
            i, j, sums, _, good = expanded(Cells(self.r, self.k, self.cells.v, self.cells.known), middle)
            at = (rows[i], columns[j])
            tile[0][at] += sums
            tile[1][at] = True
            tile[2][at] |= good
            return
        at = np.ix_(rows, columns)
        sums = exact_matmul(self._form("v"), total)
        if there is None and self.cells.plain():
            has = good = sums > 0
        else:
            has = self._form("there") @ full.astype(float) > 0
            good = self._form("known") @ (full if known is None else known).astype(float) > 0
        tile[0][at] += sums
        tile[1][at] |= has
        tile[2][at] |= good


#: Rows of a strip: places in it are two bytes.
STRIP = (1 << 16) // TILE


def _packed_strips(own, total, there, known):
    """The cells of a tile by strips of rows: places, sums in as few bytes as they need, and the places of those that are null."""
    rows = []
    codec = pa.Codec("zstd", compression_level=1)
    small = lambda x: codec.compress(np.ascontiguousarray(x).tobytes(), asbytes=True)
    for strip in range(TILE // STRIP):
        cut = slice(strip * STRIP, (strip + 1) * STRIP)
        at = np.flatnonzero(there[cut])
        if not len(at):
            continue
        sums = total[cut].ravel()[at]
        if sums.dtype == np.int64 and -(1 << 31) <= sums.min() and sums.max() < 1 << 31:
            sums = sums.astype(np.int32)
        steps = np.diff(at, prepend=0).astype(np.uint16)
        # bytes of equal weight stand together, which packs well
        planes = sums.view(np.uint8).reshape(len(sums), -1).T
        unknown = at[~known[cut].ravel()[at]].astype(np.uint16)
        rows.append((own[0], own[1], strip, small(steps), small(planes), sums.dtype.str, small(unknown), len(at), len(unknown)))
    if rows:
        cols = list(zip(*rows))
        head = lambda blobs, n: [int(c).to_bytes(4, "little") + blob for c, blob in zip(n, blobs)]
        yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int32()), pa.array(head(cols[3], cols[7]), pa.binary()), pa.array(cols[4], pa.binary()),
                                          pa.array(cols[5], pa.string()), pa.array(head(cols[6], cols[8]), pa.binary())], names=["bi", "bj", "strip", "at", "sums", "kind", "unknown"])


def _merged_strips(batches, dtype, arrow):
    """Cells of the sums of packed strips, rows of one strip one behind the other."""
    codec = pa.Codec("zstd")

    def places(blob):
        n = int.from_bytes(blob[:4], "little")
        return np.frombuffer(codec.decompress(blob[4:], decompressed_size=2 * n, asbytes=True), np.uint16).astype(np.int64)

    def cells(own, total, there, known):
        at = np.flatnonzero(there)
        return _batch(at // TILE + own[0] * TILE + own[2] * STRIP, at % TILE + own[1] * TILE, total[at], known[at], arrow)

    now = None
    for batch in batches:
        cols = [batch.column(c) for c in ("bi", "bj", "strip", "at", "sums", "kind", "unknown")]
        for n in range(batch.num_rows):
            bi, bj, strip, at, sums, kind, unknown = (c[n].as_py() for c in cols)
            if now is None or now[0] != (bi, bj, strip):
                if now is not None:
                    yield cells(*now)
                now = ((bi, bj, strip), np.zeros(1 << 16, dtype), np.zeros(1 << 16, bool), np.zeros(1 << 16, bool))
            at = np.cumsum(places(at))
            kind = np.dtype(kind)
            planes = np.frombuffer(codec.decompress(sums, decompressed_size=len(at) * kind.itemsize, asbytes=True), np.uint8).reshape(kind.itemsize, len(at))
            null = places(unknown)
            good = np.zeros(1 << 16, bool)
            good[at] = True
            good[null] = False
            now[1][at] += np.ascontiguousarray(planes.T).view(kind).ravel()
            now[2][at] = True
            now[3][good] = True
    if now is not None:
        yield cells(*now)


def expanded(a: Cells, b: Cells):
    """(row, column, sum, there, known) of the cells of a sparse product over at most INNER rows and TILE columns: its elementary
    products one behind the other, added up in one dense buffer."""
    b = b.take(np.argsort(b.x, kind="stable"))
    low, high = np.searchsorted(b.x, a.y, "left"), np.searchsorted(b.x, a.y, "right")
    n = high - low
    if not n.sum():
        return (np.zeros(0, np.int64),) * 5
    of = np.repeat(np.arange(len(n)), n)
    at = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(low, n)
    base, first = a.x.min(), b.y.min()
    width = int(b.y.max() - first) + 1
    place = (a.x[of] - base) * width + b.y[at] - first
    size = (int(a.x.max() - base) + 1) * width
    total = np.zeros(size, dtype=a.v.dtype)
    np.add.at(total, place, a.v[of] * b.v[at])
    there, known = np.zeros(size, bool), np.zeros(size, bool)
    there[place] = True
    known[place[a.known[of] & b.known[at]]] = True
    pick = np.flatnonzero(there)
    return pick // width + base, pick % width + first, total[pick], there[pick], known[pick]
