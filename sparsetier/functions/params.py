"""Chunk counts from a storage cost, evaluated on the matrix shape and a system description. Driver-side, O(1)."""

from __future__ import annotations

import math
from dataclasses import dataclass


@dataclass(frozen=True)
class SystemSpec:
    name: str
    l2_bytes: int
    line_bytes: int = 64


@dataclass(frozen=True)
class TypeSizes:
    value: int = 4
    column: int = 4
    row_pointer: int = 8
    histogram: int = 4
    prefix: int = 4


@dataclass(frozen=True)
class StorageModel:
    """Storage of a chunked accumulation for any accumulator: slots(chunk width) * slot_bytes + chunks * chunk_bytes."""

    slot_bytes: float
    slots: object = staticmethod(lambda width: width)
    chunk_bytes: float = 136

    def bytes(self, width: int, n_chunks: int) -> float:
        return self.slots(-(-width // n_chunks)) * self.slot_bytes + n_chunks * self.chunk_bytes

    def argmin_pow2(self, width: int) -> int:
        return min((1 << n for n in range(ceil_pow2(width).bit_length())), key=lambda n: self.bytes(width, n))


#: Private cache of the three published machines.
SKX, SPR, EMR = SystemSpec("SKX", 1 << 20), SystemSpec("SPR", 2 << 20), SystemSpec("EMR", 2 << 20)
TOY = SystemSpec("toy", 2048)
TOY_FINE = SystemSpec("toy_fine", 4096)


def spec_from_spark(spark) -> SystemSpec:
    """One tier up: the memory of a task in place of the private cache, its shuffle write buffer in place of a cache line."""
    conf = spark.sparkContext.getConf()
    unit = {"k": 1 << 10, "m": 1 << 20, "g": 1 << 30, "t": 1 << 40}

    def size(text: str, default: str) -> int:
        text = text.lower().rstrip("b")
        return int(float(text[:-1]) * unit[text[-1]]) if text[-1] in unit else int(text) * unit[default]

    memory = size(conf.get("spark.executor.memory", "1g"), "m") * float(conf.get("spark.memory.fraction", "0.6"))
    cores = int(conf.get("spark.executor.cores", "0")) or max(1, spark.sparkContext.defaultParallelism)
    return SystemSpec("task", int(memory / cores), size(conf.get("spark.shuffle.file.buffer", "32k"), "k"))


def ceil_pow2(x: int) -> int:
    return 1 << max(0, int(x) - 1).bit_length()


def floor_pow2(x: float) -> int:
    return 1 << max(0, int(x).bit_length() - 1)


def nearest_pow2(x: float) -> int:
    """Nearest in log space: the argmin of the convex cost over powers of two."""
    return 1 << max(0, round(math.log2(x))) if x > 1 else 1


def dense_slot_bytes(phase: str, types: TypeSizes) -> int:
    return types.value + 1 if phase == "numeric" else 1


def fine_chunk_bytes(spec: SystemSpec, types: TypeSizes) -> int:
    return types.histogram + types.prefix + 2 * spec.line_bytes


def fine_storage(width: int, n_chunks: int, spec, types, phase="numeric") -> float:
    return width * dense_slot_bytes(phase, types) / n_chunks + n_chunks * fine_chunk_bytes(spec, types)


def optimal_fine_chunks(width: int, spec, types, phase="numeric") -> int:
    return min(nearest_pow2(math.sqrt(width * dense_slot_bytes(phase, types) / fine_chunk_bytes(spec, types))), ceil_pow2(width))


def min_fine_storage(width: int, spec, types, phase="numeric") -> float:
    return 2 * math.sqrt(width * dense_slot_bytes(phase, types) * fine_chunk_bytes(spec, types))


def max_fine_columns(spec, types, phase="numeric") -> int:
    return floor_pow2(spec.l2_bytes**2 / (4 * dense_slot_bytes(phase, types) * fine_chunk_bytes(spec, types)))


@dataclass(frozen=True)
class ChunkPlan:
    level: str
    width: int
    n_coarse: int
    shift_coarse: int
    n_fine: int
    shift_fine: int


def plan_chunks(n_cols: int, spec=SPR, types=TypeSizes(), phase="numeric", coarse=True) -> ChunkPlan:
    """Fine level alone while its storage is below the private cache, else coarse chunks of the widest fitting width."""
    width = ceil_pow2(n_cols)
    if not coarse or min_fine_storage(width, spec, types, phase) < spec.l2_bytes:
        n_coarse, inner = 1, width
    else:
        inner = min(width, max_fine_columns(spec, types, phase))
        n_coarse = width // inner
    n_fine = optimal_fine_chunks(inner, spec, types, phase)
    log = lambda x: x.bit_length() - 1
    return ChunkPlan("coarse" if n_coarse > 1 else "fine", width, n_coarse, log(inner), n_fine, log(max(1, inner // n_fine)))


def ideal_read_bytes(n_rows: int, nnz_a: int, n_inter: int, types=TypeSizes()) -> int:
    pair = 2 * types.column + types.value
    return 2 * (n_rows + 1) * types.row_pointer + nnz_a * (4 * types.row_pointer + pair) + n_inter * pair


def ideal_write_bytes(n_rows: int, nnz_c: int, types=TypeSizes()) -> int:
    return (n_rows + 1) * types.row_pointer + nnz_c * (types.column + types.value)


def ideal_seconds(n_bytes: float, bytes_per_second: float) -> float:
    return n_bytes / bytes_per_second


def breakpoints(width: int, spec, types, phase="numeric") -> tuple[int, int]:
    """First power-of-two chunk counts at which a dense chunk buffer fits the private cache, and at which the reorder arrays do not
    any more."""
    log = range(ceil_pow2(width).bit_length() + 1)
    fits = next((1 << n for n in log if width * dense_slot_bytes(phase, types) / (1 << n) <= spec.l2_bytes), 0)
    breaks = next((1 << n for n in range(64) if (1 << n) * fine_chunk_bytes(spec, types) > spec.l2_bytes), 0)
    return fits, breaks


def working_set_excess(width: int, n_chunks: int, spec, types, phase="numeric") -> float:
    """Bytes by which the fine level's storage exceeds the private cache: the model's stand-in for evictions."""
    return max(0.0, fine_storage(width, n_chunks, spec, types, phase) - spec.l2_bytes)


def coarse_counter_bytes(n_coarse: int, spec, types) -> int:
    """Bytes a coarse row holds while its products are dealt: a count, an offset and two lines of store buffer per chunk."""
    return n_coarse * fine_chunk_bytes(spec, types)
