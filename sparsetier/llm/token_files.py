"""Token-id files: one zstandard dictionary for all documents, each document compressed by itself.

The dictionary is trained on the ids of a bounded sample (``sample`` documents with the smallest hash of doc_id, at most
``sample_ids`` ids of each, from the first 8 * ``sample_ids`` characters); it only affects size, never content. The sample is chosen by
doc_id alone and its texts are fetched after.

The pre-tokenizers served here never join characters across white space, so a text's ids are those of its pieces between
ASCII white space, one after the other. Arrow cuts about ``SLICE_BYTES`` of texts at a time and tells their distinct pieces, and lays the ids of
these out again by place, so that only distinct pieces become Python strings. Each Python worker holds the ids of pieces it has met (at most
``HELD_PIECES``, from task to task) and asks the library for new ones only. Vocabularies that keep white space are given whole texts. Documents are ranged by (doc_id, hash of the
text) and written as shards of bounded size. A shard is bytes: magic, dictionary hash, number of documents, tokens before it in
its range, then the offset index (doc_id, null flag, offset, length, n_tokens) and the frames, so that one short
document can be read alone. Shards are stored as a binary column of Parquet, since only Spark's writers reach every
shared store. Null or empty text: the end id alone. A null doc_id sorts first; repeated doc_ids keep each row.
"""

from __future__ import annotations

import hashlib
import json
import os
import struct
import unicodedata
import zlib
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.llm.common import arrow_rows, held_by_process, materialize, texts_of

MAGIC = b"TIDS0001"
_HEAD = "<8s32sIQ"
HELD_PIECES, SLICE_BYTES = 1 << 20, 8 << 20
_ENTRY = np.dtype([("doc_id", "<i8"), ("null", "u1"), ("offset", "<u8"), ("length", "<u4"), ("n_tokens", "<u4")])


def _tokenizer(name):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path(name))
    tok.no_truncation()
    tok.no_padding()
    return tok


def drops_white_space(tok) -> bool:
    """Whether the pre-tokenizer's first step keeps only matches of a pattern without white space, so that pieces between white space
    are independent (lower-casing and composition of characters never reach across a blank)."""
    shape = json.loads(tok.to_str())
    first = (shape.get("pre_tokenizer") or {}).get("pretokenizers", [{}])[0]
    if not shape["model"].get("end_of_word_suffix") or not shape["added_tokens"]:
        return False
    steps = {n["type"] for n in (shape.get("normalizer") or {}).get("normalizers", [])}
    return first.get("type") == "Split" and first.get("behavior") == "Removed" and first.get("invert") is True and steps <= {"NFC", "Replace", "Lowercase"}


class PieceEncoder:
    """Ids (little-endian unsigned 32-bit) of texts, by pieces met before where that is exact.

    New pieces of letters alone are given to the library many at a time, parted by blanks: each is one pre-token, so its ids end where
    a token has the end-of-word mark. Other new pieces are cut by the pre-tokenizer's pattern after composition and lower-casing,
    and their parts are looked up in turn; parts that are no letters, pieces with characters whose lower case depends on their
    surroundings or is longer, and pieces with white space of any kind, are parted by a special token instead.
    """

    def __init__(self, name: str):
        self.tok, self.held = _tokenizer(name), {}
        self.by_piece = drops_white_space(self.tok)
        if self.by_piece:
            import regex

            shape = json.loads(self.tok.to_str())
            mark = shape["model"]["end_of_word_suffix"]
            size = max(shape["model"]["vocab"].values()) + 1
            self.ends = np.zeros(max([size, *(t["id"] + 1 for t in shape["added_tokens"])]), dtype=bool)
            self.ends[[n for t, n in shape["model"]["vocab"].items() if mark and t.endswith(mark)]] = True
            self.special = shape["added_tokens"][0]
            self.cut = regex.compile(shape["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]).findall

    def _ids(self, text: str) -> np.ndarray:
        return np.array(self.tok.encode_batch_fast([text], add_special_tokens=False)[0].ids, dtype="<u4")

    def _whole(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, dtype="<u4").tobytes() for e in self.tok.encode_batch_fast(texts, add_special_tokens=False)]

    def _parted(self, pieces: list[str]) -> list[bytes]:
        """Pieces that do not hold the special token, parted by it."""
        if any("<|" in p for p in pieces):
            return self._whole(pieces)
        ids = self._ids(self.special["content"].join(pieces))
        edges = np.flatnonzero(ids == self.special["id"]).tolist()
        return [ids[a + 1:b].tobytes() for a, b in zip([-1, *edges], [*edges, len(ids)])]

    def _letters(self, pieces: list[str]) -> list[bytes]:
        ids = self._ids(" ".join(pieces))
        edges = (np.flatnonzero(self.ends[ids]) + 1).tolist()
        if len(edges) != len(pieces):  # another opinion on what a letter is
            return self._parted(pieces)
        return [ids[a:b].tobytes() for a, b in zip([0, *edges], edges)]

    def _learn(self, pieces: list[str]):
        letters, others, cut = [], [], {}
        for p in pieces:
            if "\u0130" in p or "\u03a3" in p or "<|" in p:
                others.append(p)
            elif p.isalpha():
                letters.append(p)
            elif p and p.split() != [p]:  # not ASCII, or U+001C to U+001F, which the library does not count as white space
                others.append(p)
            else:
                cut[p] = self.cut(unicodedata.normalize("NFC", p).lower())
        parts = {x for own in cut.values() for x in own} - set(letters) - set(others)
        for x in parts:
            if x not in self.held:
                (letters if x.isalpha() else others).append(x)
        for own, ask in ((letters, self._letters), (others, self._parted)):
            for at in range(0, len(own), 1024):
                self.held.update(zip(own[at:at + 1024], ask(own[at:at + 1024])))
        for p, own in cut.items():
            self.held[p] = b"".join(map(self.held.__getitem__, own)) if own != [p] else self.held[p]

    def __call__(self, texts: list[str] | pa.Array) -> list[bytes]:
        if not self.by_piece:
            return self._whole(texts.to_pylist() if isinstance(texts, pa.Array) else texts)
        words = pc.ascii_split_whitespace(texts.cast(pa.string()) if isinstance(texts, pa.Array) else pa.array(texts, pa.string()))
        coded = words.flatten().dictionary_encode()
        # one string cut at blanks, which no piece holds, is faster than one string after the other
        pieces = pc.binary_join(pa.ListArray.from_arrays([0, len(coded.dictionary)], coded.dictionary), " ")[0].as_py().split(" ")
        if len(self.held) > HELD_PIECES:
            self.held.clear()
        own = list(map(self.held.get, pieces))
        new = [n for n, ids in enumerate(own) if ids is None]
        self._learn([pieces[n] for n in new])
        for n in new:
            own[n] = self.held[pieces[n]]
        placed = pa.array(own[:len(coded.dictionary)], pa.large_binary()).take(coded.indices)
        data = placed.buffers()[2]
        data = memoryview(b"" if data is None else data)
        ends = np.frombuffer(placed.buffers()[1], "<i8", len(placed) + 1, 8 * placed.offset) if len(placed) else np.zeros(1, dtype=np.int64)
        edges = ends[np.cumsum(np.concatenate([[0], words.value_lengths().to_numpy()]).astype(np.int64))].tolist()
        return [bytes(data[a:b]) for a, b in zip(edges, edges[1:])]


def slices(batch: pa.RecordBatch, column: str = "text") -> Iterator[pa.RecordBatch]:
    """The rows of a batch, about ``SLICE_BYTES`` of texts at a time, one row at least."""
    before = np.cumsum(np.concatenate([[0], pc.binary_length(batch.column(column)).to_numpy()]).astype(np.int64))
    at = 0
    while at < batch.num_rows:
        stop = max(at + 1, int(np.searchsorted(before, before[at] + SLICE_BYTES, "right")) - 1)
        yield batch.slice(at, stop - at)
        at = stop


def train_dictionary(texts: DataFrame, name: str, end_id: int, sample: int = 256, sample_ids: int = 1 << 14, size: int = 1 << 15) -> bytes:
    chosen = texts.select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    rows = texts.join(F.broadcast(chosen), "doc_id").select(F.substring("text", 1, 8 * sample_ids).alias("text")).limit(sample).collect()
    encode, end = PieceEncoder(name), np.array([end_id], dtype="<u4").tobytes()
    arrays = sorted(ids[:4 * sample_ids] + end for ids in encode([r.text for r in rows]))
    try:
        return zstandard.train_dictionary(size, arrays).as_bytes()
    except zstandard.ZstdError:  # too few samples to train on
        return b"".join(arrays)[:size] or b"\0" * 8


def write_shards(docs: DataFrame, name: str = "word_bpe_49k.json", end_id: int = 2, shard_bytes: int = 4 << 20) -> tuple[DataFrame, bytes]:
    """Shard rows (part, shard, tokens, blob) in the shared folder, and the dictionary."""
    texts = texts_of(docs)
    dictionary = train_dictionary(texts, name, end_id)
    key = hashlib.sha256(dictionary).digest()

    def run(batches):
        from pyspark import TaskContext

        encode, end = held_by_process(("pieces", name), lambda: PieceEncoder(name)), np.array([end_id], dtype="<u4").tobytes()
        press = zstandard.ZstdCompressor(level=3, dict_data=zstandard.ZstdCompressionDict(dictionary)).compress
        part, shard, before = TaskContext.get().partitionId(), 0, 0
        index, frames, size, tokens = [], [], 0, 0

        def pack():
            blob = struct.pack(_HEAD, MAGIC, key, len(index), before) + np.array(index, dtype=_ENTRY).tobytes() + b"".join(frames)
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([shard], pa.int32()), pa.array([tokens], pa.int64()), pa.array([blob], pa.binary())], names=["part", "shard", "tokens", "blob"])

        for batch in batches:
            for piece in slices(batch):
                for doc_id, ids in zip(piece.column("doc_id").to_pylist(), encode(piece.column("text"))):
                    frame = press(ids + end)
                    index.append((doc_id or 0, doc_id is None, size, len(frame), len(ids) // 4 + 1))
                    frames.append(frame)
                    size += len(frame)
                    tokens += len(ids) // 4 + 1
                    if size + len(index) * _ENTRY.itemsize >= shard_bytes:
                        yield pack()
                        before, shard = before + tokens, shard + 1
                        index, frames, size, tokens = [], [], 0, 0
        if index:
            yield pack()

    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = texts.withColumn("h", F.xxhash64("text")).repartitionByRange(parts, "doc_id", "h").sortWithinPartitions("doc_id", "h", "text")
    return materialize(ranged.select("doc_id", "text").mapInArrow(run, "part int, shard int, tokens long, blob binary"), "token_shards"), dictionary


def read_index(blob: bytes):
    magic, key, n, before = struct.unpack_from(_HEAD, blob)
    if magic != MAGIC:
        raise ValueError("not a token-id shard")
    return key, before, np.frombuffer(blob, dtype=_ENTRY, count=n, offset=struct.calcsize(_HEAD)), struct.calcsize(_HEAD) + n * _ENTRY.itemsize


def read_document(blob: bytes, place: int, dictionary: bytes) -> np.ndarray:
    """Ids of one document of a shard, without touching the others."""
    key, _, index, data = read_index(blob)
    if key != hashlib.sha256(dictionary).digest():
        raise ValueError("shard was written with another dictionary")
    entry = index[place]
    at = data + int(entry["offset"])
    plain = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(dictionary)).decompress(blob[at:at + int(entry["length"])])
    return np.frombuffer(plain, dtype="<u4")


def read_shards(shards: DataFrame, dictionary: bytes) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) read back from shards. Totals per range, one row per shuffle partition, give
    each range its first token number; inside a range the shard headers have it."""
    spark = shards.sparkSession
    totals = shards.groupBy("part").agg(F.sum("tokens").alias("n")).orderBy("part").collect()
    offsets, at = [], 0
    for r in totals:
        offsets.append((r.part, at))
        at += r.n
    first = spark.createDataFrame(offsets, "part int, first long")
    key = hashlib.sha256(dictionary).digest()

    def start():
        expand = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(dictionary)).decompress

        def work(cols):
            for part_first, blob in zip(cols["first"], cols["blob"]):
                found, before, index, data = read_index(blob)
                if found != key:
                    raise ValueError("shard was written with another dictionary")
                place = part_first + before
                for e in index:
                    at = data + int(e["offset"])
                    ids = expand(blob[at:at + int(e["length"])])
                    yield None if e["null"] else int(e["doc_id"]), place, len(ids) // 4, zlib.crc32(ids)
                    place += len(ids) // 4

        return work

    return arrow_rows(shards.join(F.broadcast(first), "part").select("first", "blob"), "doc_id long, start long, n_tokens long, ids_crc32 long", start)
