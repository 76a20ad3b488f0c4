"""Byte-level BPE encoding and decoding by a global shuffle of distinct words.

Documents are read in blocks of bounded size. In a block every distinct pre-token ("word") has a number; a document is the sequence of
its words' numbers, so position is kept by order. Words that are one token of the vocabulary have that token as their number. The other
distinct words of a block leave it once, dealt by their hash to word partitions, where each word is encoded once and held for
the blocks that follow; its ids go back to the blocks and documents are put together by position. Blocks, words and ids travel packed: one
row for many, no row per occurrence. The exchange of the blocks is used by both sides of the join and written once.

Decoding joins the distinct ids of each block, one row each, with the token-byte table (one row per rank: bounded by the vocabulary, so
broadcast) and lays the bytes out by position inside the same task. The rows of a block's ids stand before those of its documents.

Null or empty text: no tokens. Repeated rows and repeated or null doc_ids each give their own row. Very long texts are a
block of their own. Other input columns are ignored, whatever their names.
"""

from __future__ import annotations

import base64
import hashlib
import re

import numpy as np
import public_tokenizers
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.llm.common import arrow_rows, give_back, texts_of

BLOCK_CHARS, BLOCK_TOKENS, ROW_TOKENS, HELD_WORDS = 12 << 20, 1 << 21, 1 << 17, 1 << 20
#: White space of Unicode and of Python; a blank between two other characters always starts a pre-token.
_SPACES = "".join(c for c in map(chr, range(0x3001)) if c.isspace() and c != " ")
_GAP = re.compile(r"(?<=\S) (?=\S)")
_CODED = "block long, token int, doc_ids array<long>, lengths array<int>, ids binary"
_PACKED = "block long, doc_ids array<long>, lengths array<int>, seq binary, part int, words binary"


def load_ranks(name: str) -> dict[bytes, int]:
    with open(public_tokenizers.path(name), "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in lines if line.strip())}


def pieces_of(text: str) -> list[str]:
    """The text cut at single blanks between other characters (these blanks go)."""
    if "  " in text or text[:1] == " " or text[-1:] == " " or any(f"{c} " in text or f" {c}" in text for c in _SPACES if c in text):
        return _GAP.split(text)
    return text.split(" ")


def splitter():
    """The pre-token pattern with Unicode white space spelled out, as the tiktoken library reads it."""
    import regex

    spelled = public_tokenizers.PATTERN.replace(r"[^\s", r"[^\p{White_Space}").replace(r"\s", r"\p{White_Space}").replace(r"\S", r"\P{White_Space}")
    return regex.compile(spelled).findall


def pack_list(items: list[bytes], press) -> bytes:
    sizes = np.array([len(items), *map(len, items)], dtype="<u4")
    return press(sizes.tobytes() + b"".join(items))


def unpack_list(packed: bytes, expand) -> list[bytes]:
    plain = expand(packed)
    n = int.from_bytes(plain[:4], "little")
    ends = (np.cumsum(np.frombuffer(plain, "<u4", n, 4)) + 4 + 4 * n).tolist()
    return [plain[a:b] for a, b in zip([4 + 4 * n, *ends], ends)]


def _planes(numbers: np.ndarray) -> bytes:
    """The low halves of all numbers, then the high halves, which press to little."""
    return (numbers & 0xFFFF).astype("<u2").tobytes() + (numbers >> 16).astype("<u2").tobytes()


def _from_planes(data: bytes) -> np.ndarray:
    halves = np.frombuffer(data, "<u2").astype(np.uint32).reshape(2, -1)
    return halves[0] | halves[1] << np.uint32(16)


class _Words(dict):
    """Pieces of text as the bytes of their words' numbers: a token id, or ``base`` plus the place in ``found``."""

    def __init__(self, lead: str, split, ranks: dict[bytes, int], numbers: dict[bytes, int], base: int):
        self.lead, self.split, self.ranks, self.numbers, self.base = lead, split, ranks, numbers, base

    def __missing__(self, piece: str) -> bytes:
        out = []
        for word in [self.lead + piece] if piece.isalpha() else self.split(self.lead + piece):  # letters are one pre-token
            raw = word.encode()
            n = self.ranks.get(raw)
            out.append(self.base + self.numbers.setdefault(raw, len(self.numbers)) if n is None else n)
        self[piece] = packed = b"".join([n.to_bytes(4, "little") for n in out])
        return packed


def _blocks(texts: DataFrame, ranks_name: str, parts: int, block_chars: int) -> DataFrame:
    """Rows of documents (doc_ids, lengths, seq) and rows of words (part, words) of each block. Words are numbered in the order of
    (part, word), from the size of the vocabulary on."""

    def run(batches):
        import xxhash
        from pyspark import TaskContext

        split, ranks = splitter(), load_ranks(ranks_name)
        base = max(ranks.values()) + 1
        press = zstandard.ZstdCompressor(level=3).compress
        number = TaskContext.get().partitionId() << 32
        names = ["block", "doc_ids", "lengths", "seq", "part", "words"]
        kinds = [pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.binary(), pa.int32(), pa.binary()]

        def fresh():
            numbers: dict[bytes, int] = {}
            return numbers, _Words("", split, ranks, numbers, base), _Words(" ", split, ranks, numbers, base), [], 0

        def pack(columns):
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds)], names=names)

        def finish():
            dealt = sorted((xxhash.xxh3_64_intdigest(w) % parts, w, n) for w, n in numbers.items())
            place = np.zeros(base + len(dealt), dtype=np.uint32)
            place[:base] = np.arange(base)
            place[base + np.array([n for _, _, n in dealt], dtype=np.int64)] = base + np.arange(len(dealt))
            own: dict[int, list[bytes]] = {}
            for part, word, _ in dealt:
                own.setdefault(part, []).append(word)
            n = len(own)
            yield pack([[number] * n, [None] * n, [None] * n, [None] * n, list(own), [pack_list(ws, press) for ws in own.values()]])
            at = 0
            while at < len(docs):
                held, stop = 0, at
                while stop < len(docs) and (stop == at or held < ROW_TOKENS) and stop - at < 1024:
                    held += len(docs[stop][1]) // 4
                    stop += 1
                row = docs[at:stop]
                seq = place[np.frombuffer(b"".join(s for _, s in row), "<u4")]
                yield pack([[number], [[d for d, _ in row]], [[len(s) // 4 for _, s in row]], [press(_planes(seq))], [None], [None]])
                at = stop

        numbers, first, rest, docs, size = fresh()
        for batch in batches:
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), batch.column("text")):
                text = text.as_py()
                pieces = pieces_of(text)
                docs.append((doc_id, first[pieces[0]] + b"".join(map(rest.__getitem__, pieces[1:]))))
                size += len(text) + 64
                if size >= block_chars:
                    yield from finish()
                    number += 1
                    numbers, first, rest, docs, size = fresh()
        if docs:
            yield from finish()
        give_back()

    return texts.mapInArrow(run, _PACKED)


def _encode_words(words: DataFrame, ranks_name: str) -> DataFrame:
    """(block, part, ids): the ids of each row's words, every distinct word of a part encoded once and held (the table of held
    words starts anew at ``HELD_WORDS``)."""

    def start():
        import tiktoken

        coder = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=load_ranks(ranks_name), special_tokens={})
        press, expand = zstandard.ZstdCompressor(level=3).compress, zstandard.ZstdDecompressor().decompress

        class Held(dict):
            def __missing__(self, word):
                self[word] = ids = np.array(coder._encode_single_piece(word), dtype="<u4").tobytes()
                return ids

        held = Held()

        def work(cols):
            for block, part, packed in zip(cols["block"], cols["part"], cols["words"]):
                if len(held) > HELD_WORDS:
                    held.clear()
                ids = list(map(held.__getitem__, unpack_list(packed, expand)))
                counts = np.array([len(x) // 4 for x in ids], dtype="<u4")
                yield block, part, press(counts.size.to_bytes(4, "little") + _planes(counts) + _planes(np.frombuffer(b"".join(ids), "<u4")))

        return work

    return arrow_rows(words, "block long, part int, ids binary", start)


def _word_rows(blocks: DataFrame) -> DataFrame:
    def run(batches):
        for batch in batches:
            yield batch.filter(batch.column("part").is_valid()).select(["block", "part", "words"])

    return blocks.mapInArrow(run, "block long, part int, words binary")


def _blockwise(docs: DataFrame, ranks_name: str, block_chars: int, finish, schema: str) -> DataFrame:
    """What ``finish`` makes of every block, given its number and (doc_ids, lengths, ids) of each of its rows of documents."""
    parts = 4 * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    blocks = _blocks(texts_of(docs), ranks_name, parts, block_chars).repartition("block")
    lexicon = _encode_words(_word_rows(blocks).repartition("part"), ranks_name)
    base = max(load_ranks(ranks_name).values()) + 1

    def assemble(left: pa.Table, right: pa.Table) -> pa.Table:
        expand = zstandard.ZstdDecompressor().decompress
        counts, ids = [], []
        for _, packed in sorted(zip(right.column("part").to_pylist(), right.column("ids").to_pylist())):
            plain = expand(packed)
            n = int.from_bytes(plain[:4], "little")
            counts.append(_from_planes(plain[4:4 + 4 * n]))
            ids.append(_from_planes(plain[4 + 4 * n:]))
        counts = np.concatenate([np.ones(base, dtype=np.int64), *counts]).astype(np.int64)
        ids = np.concatenate([np.arange(base, dtype=np.uint32), *ids])
        begin = np.cumsum(counts) - counts
        out = []
        for own, lengths, seq in zip(left.column("doc_ids").to_pylist(), left.column("lengths").to_pylist(), left.column("seq").to_pylist()):
            if own is None:
                continue
            words = _from_planes(expand(seq))
            n = counts[words]
            ends = np.cumsum(n)
            places = np.repeat(begin[words] - (ends - n), n) + np.arange(ends[-1] if len(ends) else 0)
            last = np.cumsum(lengths)
            edges = np.concatenate([[0], ends])[np.concatenate([[0], last])]
            out.append((own, np.diff(edges), ids[places]))
        return finish(left.column("block")[0].as_py() if left.num_rows else None, out)

    return blocks.groupBy("block").cogroup(lexicon.groupBy("block")).applyInArrow(assemble, schema)


def encode(docs: DataFrame, ranks_name: str = "byte_bpe_50k.tiktoken", block_chars: int = BLOCK_CHARS) -> DataFrame:
    """(doc_id, ids array<int>)."""

    def finish(_, rows):
        flat = np.concatenate([np.zeros(0, np.uint32), *(ids for _, _, ids in rows)])
        offsets = np.cumsum(np.concatenate([[0], *(lengths for _, lengths, _ in rows)]))
        lists = pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(flat.astype(np.int32)))
        return pa.table({"doc_id": pa.array([d for own, _, _ in rows for d in own], pa.int64()), "ids": lists})

    return _blockwise(docs, ranks_name, block_chars, finish, "doc_id long, ids array<int>")


def _coded(block: int | None, rows: list[tuple]) -> pa.Table:
    """Rows of the distinct ids of a block (token), then rows of its documents (doc_ids, lengths, ids)."""
    seen = np.zeros(1 + max((int(ids.max()) for _, _, ids in rows if len(ids)), default=0), dtype=bool)
    for _, _, ids in rows:
        seen[ids] = True
    tokens = np.flatnonzero(seen).astype(np.int32)
    n, m = len(tokens), len(rows)

    def after(first, values, kind):
        return pa.concat_arrays([first, pa.array(values, kind)])

    longs, ints = pa.list_(pa.int64()), pa.list_(pa.int32())
    return pa.table({
        "block": pa.array([block] * (n + m), pa.int64()), "token": after(pa.array(tokens, pa.int32()), [None] * m, pa.int32()),
        "doc_ids": after(pa.nulls(n, longs), [own for own, _, _ in rows], longs),
        "lengths": after(pa.nulls(n, ints), [lengths for _, lengths, _ in rows], ints),
        "ids": after(pa.nulls(n, pa.binary()), [ids.astype("<u4").tobytes() for _, _, ids in rows], pa.binary())})


def encode_blocks(docs: DataFrame, ranks_name: str = "byte_bpe_50k.tiktoken", block_chars: int = BLOCK_CHARS) -> DataFrame:
    """What ``encode`` gives, by blocks: rows of the distinct ids of each block, then rows of its documents."""
    return _blockwise(docs, ranks_name, block_chars, _coded, _CODED)


def _in_blocks(encoded: DataFrame) -> DataFrame:
    """The rows of ``encode_blocks`` for rows (doc_id, ids), a block for every ``BLOCK_TOKENS`` ids."""

    def run(batches):
        from pyspark import TaskContext

        number = TaskContext.get().partitionId() << 32
        rows, size = [], 0
        for batch in batches:
            ids = batch.column("ids")
            lengths = ids.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
            rows.append((batch.column("doc_id").to_pylist(), lengths, ids.flatten().to_numpy(zero_copy_only=False).astype(np.uint32)))
            size += int(lengths.sum()) + 16 * len(lengths)
            if size >= BLOCK_TOKENS:
                yield from _coded(number, rows).to_batches()
                rows, size, number = [], 0, number + 1
        if rows:
            yield from _coded(number, rows).to_batches()

    return encoded.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("ids").cast("array<int>").alias("ids")).mapInArrow(run, _CODED)


def token_table(spark, ranks_name: str) -> DataFrame:
    """(token, piece): the bytes of every rank."""
    return spark.createDataFrame([(rank, bytearray(token)) for token, rank in load_ranks(ranks_name).items()], "token int, piece binary")


def _joined(coded: DataFrame, ranks_name: str) -> DataFrame:
    """The rows of blocks, those of distinct ids with their bytes; order and partition do not change."""
    return coded.join(F.broadcast(token_table(coded.sparkSession, ranks_name)), "token", "left").select("block", "token", "piece", "doc_ids", "lengths", "ids")


def _laid_out(items: pa.Array, places: pa.Array, edges: np.ndarray) -> tuple[memoryview, list[int]]:
    """The items at ``places``, one after the other, and where in them each of the ``edges`` comes to stand."""
    taken = items.take(places)
    data = taken.buffers()[2]
    return memoryview(b"" if data is None else data), np.frombuffer(taken.buffers()[1], "<i8", len(taken) + 1, 8 * taken.offset)[edges].tolist()


def _reassembled(encoded: DataFrame, ranks_name: str, start, schema: str) -> DataFrame:
    """Rows of ``schema`` from rows of ``encode`` or ``encode_blocks``. ``start(tokens)`` runs once per block and returns a function of
    (doc_ids, ids, places, edges, data, cuts): the documents' ids, their places among the tokens, where each document begins in them, their
    bytes from the join with the token-byte table, and where each document begins in these."""
    coded = encoded if "token" in encoded.columns else _in_blocks(encoded)
    target = encoded.sparkSession.createDataFrame([], schema).schema

    def run(batches):
        from pyspark.sql.pandas.types import to_arrow_schema

        arrow = to_arrow_schema(target)
        block, held, work = None, [], None  # (tokens, pieces) of the block at hand; set up at its first row of documents
        for batch in batches:
            numbers, tokens, pieces = batch.column("block").to_pylist(), batch.column("token"), batch.column("piece")
            at = 0
            for i in np.flatnonzero(tokens.is_null().to_numpy(zero_copy_only=False)).tolist() + [batch.num_rows]:
                if at < batch.num_rows and numbers[at] != block:
                    block, held, work = numbers[at], [], None
                if at < i:
                    held.append((tokens.slice(at, i - at).to_numpy(), pieces.slice(at, i - at)))
                at = i + 1
                if i == batch.num_rows:
                    break
                if work is None:
                    own = np.concatenate([np.zeros(0, np.int32), *(t for t, _ in held)])
                    place = np.zeros(1 + max(own.tolist(), default=0), dtype=np.int64)
                    place[own] = np.arange(len(own))
                    data = pa.concat_arrays([pa.array([], pa.large_binary()), *(p.fill_null(b"").cast(pa.large_binary()) for _, p in held)])
                    work = start(own.tolist())
                ids = np.frombuffer(batch.column("ids")[i].as_buffer(), "<u4")
                places = pa.array(place[ids])
                edges = np.concatenate([[0], np.cumsum(np.array(batch.column("lengths")[i].as_py(), dtype=np.int64))]).astype(np.int64)
                found = work(batch.column("doc_ids")[i].as_py(), ids, places, edges, *_laid_out(data, places, edges))
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(found, arrow)], schema=arrow)
        give_back()

    return _joined(coded, ranks_name).mapInArrow(run, schema)


def decode(encoded: DataFrame, ranks_name: str = "byte_bpe_50k.tiktoken") -> DataFrame:
    """(doc_id, ids, data): rows with ``ids`` and their decoded bytes."""

    def start(_):
        def work(doc_ids, ids, places, edges, data, cuts):
            return doc_ids, [ids[a:b].tolist() for a, b in zip(edges, edges[1:])], [bytes(data[a:b]) for a, b in zip(cuts, cuts[1:])]

        return work

    return _reassembled(encoded, ranks_name, start, "doc_id long, ids array<int>, data binary")


def digests(encoded: DataFrame, ranks_name: str = "byte_bpe_50k.tiktoken") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of encoded documents, which are decoded for it."""

    def start(tokens):
        spelled = pa.array([b"%d " % t for t in tokens], pa.large_binary())

        def work(doc_ids, ids, places, edges, data, cuts):
            text, ends = _laid_out(spelled, places, edges)
            return (doc_ids, np.diff(edges), [hashlib.sha256(text[a:max(a, b - 1)]).hexdigest() for a, b in zip(ends, ends[1:])],
                    [hashlib.sha256(data[a:b]).hexdigest() for a, b in zip(cuts, cuts[1:])])

        return work

    return _reassembled(encoded, ranks_name, start, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
