"""Removal of strings that occur twice, in a document or across documents.

A window is ``width`` units long: bytes, or words (runs without ASCII white space; which white space parts them does not count).

1. Every text is cut into runs: neighbouring window starts with one smallest gram hash (``low``). Equal windows have equal smallest
   gram hashes, so equal windows always meet in one bucket, the runs with one ``low``. Only buckets of several runs, or of one that
   holds its gram twice, go on.
2. Runs of equal content (128-bit digest of the bytes) are one kind; every window of a kind that occurs twice stands elsewhere too.
3. The kinds of a bucket are compared as suffixes. Prefix polynomial hashes modulo 2**61 - 1 give the hash of any substring;
   window hashes that occur once in the bucket are passed over; of the others the first start of each stretch, and partners with its
   hash, are ordered by a mergesort network whose comparisons find the common extension by binary search over hashes.
   Neighbours with a common extension of ``width`` units or more are verified byte by byte; the verified extension covers the
   windows from there on, and starts that are not covered yet make the next round.
4. A bucket too large for one task (``HOT_BYTES`` of content) is refined instead. Windows are dealt by their distance to the gram into
   parts of ``sizes_of`` windows, which shrink eightfold from step to step. Digests of the bytes are counted with partial
   aggregation, no group is gathered: a part whose whole content occurs twice is found, one whose core (the bytes that all windows at
   its place hold) occurs once is done, and only one part of each kind of the rest goes on, down to single windows.

With ``words`` set, passages of that many equal words are cut as well as strings of ``width`` bytes; both kinds are judged on the
whole input text. Null or empty text: nothing removed, n_spans 0. Rows are judged one by one, so repeated rows remove each other whole
(from ``width`` bytes or ``words`` words on). Texts shorter than both stay. Very long texts are hashed in blocks of ``BLOCK``
units. Other input columns stay as they are, whatever their names.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.llm.common import Scratch, arrow_rows, give_back

WIDTH, GRAM, WORD_GRAM = 400, 64, 8
#: Words of the shortest passage that counts as repeated.
PASSAGE = 51
BLOCK, BATCH_BYTES, HOT_BYTES = 1 << 20, 1 << 19, 1 << 19
_P = np.uint64((1 << 61) - 1)
_U = np.uint64
_BLANK = np.zeros(256, dtype=bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True


# ---- the filter hash: gram hashes modulo 2**64, only ever used to bring equal windows together

_ODD = _U(0x9E3779B97F4A7C15)
_BYTES = np.random.default_rng(7).integers(0, 1 << 63, 256, dtype=np.uint64)
_TABLES: dict[str, np.ndarray] = {}


def _mix(h):
    h = (h ^ (h >> _U(32))) * _U(0xD6E8FEB86659FD93)
    return h ^ (h >> _U(29))


def _powers(n: int):
    """Powers of the base and of its inverse; at most of a block's length."""
    if len(_TABLES.get("up", ())) < n:
        for name, base in (("up", int(_ODD)), ("down", pow(int(_ODD), -1, 1 << 64))):
            step = np.full(2 * n, base, dtype=np.uint64)
            step[0] = 1
            _TABLES[name] = np.cumprod(step, dtype=np.uint64)
    return _TABLES["up"], _TABLES["down"]


def _prefix(values: np.ndarray) -> np.ndarray:
    out = np.zeros(len(values) + 1, dtype=np.uint64)
    np.cumsum(values * _powers(len(values) + 1)[0][:len(values)], out=out[1:])
    return out


def _grams(values: np.ndarray, gram: int) -> np.ndarray:
    prefix = _prefix(values)
    n = len(prefix) - gram
    return _mix((prefix[gram:] - prefix[:n]) * _powers(n)[1][:n])


def sliding_min(x: np.ndarray, k: int) -> np.ndarray:
    n = len(x)
    padded = np.concatenate([x, np.full(-n % k + k, ~_U(0))]).reshape(-1, k)
    left = np.minimum.accumulate(padded, 1).ravel()
    right = np.minimum.accumulate(padded[:, ::-1], 1)[:, ::-1].ravel()
    return np.minimum(right[:n - k + 1], left[k - 1:n])


def word_units(raw: bytes):
    """(hash, first byte, end byte) of the words of a text, found block by block."""
    values, firsts, lasts = [], [], []
    at = 0
    while at < len(raw):
        stop = min(len(raw), at + BLOCK)
        while stop < len(raw) and not _BLANK[raw[stop]]:
            stop += 1
        data = np.frombuffer(raw, dtype=np.uint8, count=stop - at, offset=at)
        full = np.concatenate([[False], ~_BLANK[data], [False]])
        edge = np.flatnonzero(full[1:] != full[:-1])
        first, last = edge[::2], edge[1::2]
        prefix = _prefix(_BYTES[data])
        values.append(_mix((prefix[last] - prefix[first]) * _powers(len(prefix))[1][first] + (last - first).astype(np.uint64)))
        firsts.append(first + at)
        lasts.append(last + at)
        at = stop
    empty = np.zeros(0, dtype=np.int64)
    return (np.concatenate(values) if values else empty.view(np.uint64), np.concatenate([empty, *firsts]), np.concatenate([empty, *lasts]))


def runs_of(raw: bytes, width: int, by_word: bool):
    """(low, at, n, twice, content) of a text: the windows at at … at + n - 1 have the smallest gram hash ``low``, which stands there
    at two places or more if ``twice``. Words in the content are parted by one blank."""
    gram = min(WORD_GRAM if by_word else GRAM, width)
    units, first, last = word_units(raw) if by_word else (np.frombuffer(raw, dtype=np.uint8), None, None)
    for a in range(0, max(0, len(units) - width + 1), BLOCK):
        part = units[a:a + BLOCK + width - 1]
        g = _grams(part if by_word else _BYTES[part], gram)
        low = sliding_min(g, width - gram + 1)
        cut = np.flatnonzero(np.concatenate([[True], low[1:] != low[:-1]]))
        size = np.diff(np.append(cut, len(low)))
        for at, n, value in zip(cut.tolist(), size.tolist(), low[cut]):
            twice = np.count_nonzero(g[at:at + n + width - gram] == value) > 1
            yield int(value.view(np.int64)), a + at, n, twice, _content(raw, first, last, a + at, n + width - 1)


def _content(raw: bytes, first, last, at: int, n: int) -> bytes:
    return raw[at:at + n] if first is None else b" ".join(raw[first[at]:last[at + n - 1]].split())


def _digest(data: bytes) -> bytes:
    return hashlib.blake2b(data, digest_size=16).digest()


# ---- suffixes compared by hashes modulo 2**61 - 1

def _fold(x):
    x = (x & _P) + (x >> _U(61))
    return x - _P * (x >= _P)


def _times(a, b):
    """a * b modulo 2**61 - 1 in 64-bit arithmetic."""
    a1, a0, b1, b0 = a >> _U(32), a & _U(0xFFFFFFFF), b >> _U(32), b & _U(0xFFFFFFFF)
    middle, lowest = a1 * b0 + a0 * b1, a0 * b0
    return _fold(_U(8) * a1 * b1 + (middle >> _U(29)) + ((middle & _U((1 << 29) - 1)) << _U(32)) + (lowest & _P) + (lowest >> _U(61)))


class Suffixes:
    """The units of several pieces one after the other; suffixes end with their piece."""

    base = _U(0x1B873593CC9E2D51 % ((1 << 61) - 1))

    def __init__(self, pieces: list[bytes], by_word: bool):
        if by_word:
            words = [p.split(b" ") for p in pieces]
            flat = [w for ws in words for w in ws]
            lengths = np.array([len(ws) for ws in words], dtype=np.int64)
            self.raw = b" ".join(flat)
            size = np.array([len(w) for w in flat], dtype=np.int64)
            self.last = np.cumsum(size + 1) - 1
            self.first = self.last - size
            values = word_units(self.raw)[0] >> _U(4)
        else:
            self.raw = b"".join(pieces)
            lengths = np.array([len(p) for p in pieces], dtype=np.int64)
            self.first = self.last = None
            values = np.frombuffer(self.raw, dtype=np.uint8).astype(np.uint64)
        self.ends = np.cumsum(lengths)
        self.begins = self.ends - lengths
        self.units = values + _U(1)
        self.end_of = np.repeat(self.ends, lengths)
        n = len(values)
        self.power = np.ones(1, dtype=np.uint64)
        step = self.base
        while len(self.power) <= n:
            self.power = np.concatenate([self.power, _times(self.power, step)])
            step = _times(step, step)
        terms = _times(self.units, self.power[:n])
        high, lower = np.cumsum(terms >> _U(32)), np.cumsum(terms & _U(0xFFFFFFFF))
        self.prefix = np.zeros(n + 1, dtype=np.uint64)
        self.prefix[1:] = _fold(_fold((high >> _U(29)) + ((high & _U((1 << 29) - 1)) << _U(32))) + _fold(lower))

    def of(self, start, stop):
        """Hash of the units from start to stop, brought to one power."""
        return _times(_fold(self.prefix[stop] + (_P - self.prefix[start])), self.power[len(self.units) - start])

    def common(self, a, b):
        """Length of the common extension of the suffixes at a and b, by binary search over hashes."""
        low, high = np.zeros(len(a), dtype=np.int64), np.minimum(self.end_of[a] - a, self.end_of[b] - b)
        while (low < high).any():
            middle = (low + high + 1) // 2
            same = self.of(a, a + middle) == self.of(b, b + middle)
            low, high = np.where(same, middle, low), np.where(same, high, middle - 1)
        return low

    def after(self, a, b):
        k = self.common(a, b)
        n = len(self.units) - 1
        left = np.where(a + k < self.end_of[a], self.units[np.minimum(a + k, n)], _U(0))
        right = np.where(b + k < self.end_of[b], self.units[np.minimum(b + k, n)], _U(0))
        return left > right

    def sort(self, starts: np.ndarray, group: np.ndarray) -> np.ndarray:
        """Suffixes ordered inside each group (``group`` does not fall): an odd-even mergesort network whose layers compare all of
        their pairs, in all groups, at once."""
        s = starts.astype(np.int64).copy()
        if not len(s):
            return s
        begin = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
        size = np.diff(np.append(begin, len(s)))
        place, size = np.arange(len(s)) - np.repeat(begin, size), np.repeat(size, size)
        p = 1
        while p < size.max():
            k = p
            while k >= 1:
                r = place - k % p
                left = np.flatnonzero((r >= 0) & (r // k % 2 == 0) & (place + k < size) & (place // (2 * p) == (place + k) // (2 * p)))
                swap = left[self.after(s[left], s[left + k])] if len(left) else left
                s[swap], s[swap + k] = s[swap + k], s[swap]
                k //= 2
            p *= 2
        return s

    def equal(self, a: int, b: int, n: int) -> bool:
        if self.first is None:
            return self.raw[a:a + n] == self.raw[b:b + n]
        return self.raw[self.first[a]:self.last[a + n - 1]] == self.raw[self.first[b]:self.last[b + n - 1]]


def repeated_windows(pieces: list[bytes], bucket: list[int], known: list[bool], width: int, by_word: bool):
    """(piece, first window, windows) of windows that stand elsewhere in their bucket too; pieces in order of their buckets.
    Windows of ``known`` pieces are only compared with."""
    text = Suffixes(pieces, by_word)
    size = np.maximum(0, text.ends - text.begins - width + 1)
    owner = np.repeat(np.arange(len(pieces)), size)
    start = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size) + text.begins[owner]
    if not len(start):
        return
    bucket, wanted = np.array(bucket, dtype=np.int64), ~np.array(known, dtype=bool)[owner]
    key = _mix(text.of(start, start + width) + _ODD * bucket[owner].astype(np.uint64))
    order = np.argsort(key, kind="stable")
    edge = np.flatnonzero(np.concatenate([[True], key[order][1:] != key[order][:-1]]))
    class_size = np.diff(np.append(edge, len(order)))
    class_of = np.empty(len(order), dtype=np.int64)
    class_of[order] = np.repeat(np.arange(len(edge)), class_size)
    open_ = wanted & (class_size[class_of] > 1)
    while open_.any():
        lead = np.flatnonzero(open_ & ~np.concatenate([[False], open_[:-1] & (owner[1:] == owner[:-1])]))
        mates = edge[np.unique(class_of[lead])]
        chosen = np.unique(np.concatenate([lead, order[mates], order[mates + 1]]))
        s = text.sort(start[chosen], bucket[owner[chosen]])
        group = bucket[np.searchsorted(text.ends, s, side="right")]
        near = text.common(s[:-1], s[1:]) * (group[:-1] == group[1:])
        for n in np.flatnonzero(near >= width).tolist():
            if not text.equal(int(s[n]), int(s[n + 1]), int(near[n])):
                near[n] = 0
        reach = dict(zip(s.tolist(), np.maximum(np.append(near, 0), np.append(0, near)).tolist()))
        for w in lead.tolist():
            n = min(reach[int(start[w])] - width + 1, int(size[owner[w]] - (start[w] - text.begins[owner[w]])))
            if n > 0:
                open_[w:w + n] = False
                yield int(owner[w]), int(start[w] - text.begins[owner[w]]), n
            open_[w] = False  # a hash that only collided


# ---- plans

_RUN = "by_word boolean, low long, tkey binary, at int, n int"


def keyed(docs: DataFrame) -> DataFrame:
    """(tkey, raw) of every row: 16 bytes of the text's SHA-256, and the text (null: empty)."""
    raw = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.unhex(F.substring(F.sha2(raw.cast("binary"), 256), 1, 32)).alias("tkey"), raw.alias("raw"))


def anchor_runs(texts: DataFrame, modes) -> DataFrame:
    def start():
        def work(cols):
            for tkey, text in zip(cols["tkey"], cols["raw"]):
                raw = text.encode("utf-8", "surrogatepass")
                for by_word, width in modes:
                    for low, at, n, twice, content in runs_of(raw, width, by_word):
                        yield by_word, low, tkey, at, n, twice, _digest(content)

        return work

    return arrow_rows(texts, _RUN + ", twice boolean, whole binary", start, flush=16384)


def _contents(texts: DataFrame, chosen: DataFrame, modes) -> DataFrame:
    """Content of the chosen runs."""
    widths = dict(modes)

    def start():
        def work(cols):
            for tkey, text, runs in zip(cols["tkey"], cols["raw"], cols["runs"]):
                raw, units = text.encode("utf-8", "surrogatepass"), None
                for r in runs:
                    by_word, at, n = r["by_word"], r["at"], r["n"]
                    if by_word and units is None:
                        units = word_units(raw)[1:]
                    first, last = units if by_word else (None, None)
                    yield by_word, r["low"], tkey, at, n, r["known"], r["hot"], _content(raw, first, last, at, n + widths[by_word] - 1)

        return work

    per_text = chosen.groupBy("tkey").agg(F.collect_list(F.struct("by_word", "low", "at", "n", "known", "hot")).alias("runs"))
    return arrow_rows(texts.join(per_text, "tkey"), _RUN + ", known boolean, hot boolean, content binary", start, flush=4096)


def sizes_of(width: int) -> list[int]:
    """Windows per part at each step of the refinement: powers of eight, the first at most half a window."""
    sizes = [1]
    while sizes[0] * 16 <= width:
        sizes.insert(0, sizes[0] * 8)
    return sizes


def parts_of(content: bytes, low: int, n: int, size: int, width: int, by_word: bool, spans=None):
    """(first window, windows, core, content) of the parts of a run: neighbouring windows whose distances to the next gram ``low`` have
    one quotient by ``size``; only those in ``spans`` if given."""
    if by_word:
        values, first, last = word_units(content)
    else:
        first, last = None, None
        values = _BYTES[np.frombuffer(content, dtype=np.uint8)]
    hits = np.flatnonzero(_grams(values, min(WORD_GRAM if by_word else GRAM, width)).view(np.int64) == low)
    for a, b in [(0, n)] if spans is None else [(s["lo"], s["lo"] + s["n"]) for s in spans]:
        start = np.arange(a, b)
        hit = hits[np.searchsorted(hits, start)]
        part = (hit - start) // size
        cut = np.flatnonzero(np.concatenate([[True], (hit[1:] != hit[:-1]) | (part[1:] != part[:-1])]))
        for lo, count, h, k in zip(start[cut].tolist(), np.diff(np.append(cut, len(start))).tolist(), hit[cut].tolist(), part[cut].tolist()):
            yield lo, count, _content(content, first, last, h - size * k, width - size + 1), _content(content, first, last, lo, count + width - 1)


def _refined(contents: DataFrame, modes, scratch: Scratch) -> list[DataFrame]:
    """[(by_word, tkey, at, n)]: windows of hot buckets that stand elsewhere too, step by step."""
    widths, sizes = dict(modes), {by_word: sizes_of(width) for by_word, width in modes}
    found, opened, run = [], None, ["by_word", "tkey", "run_at"]
    for step in range(max(map(len, sizes.values()))):

        def start(step=step, all_of_it=opened is None):
            def work(cols):
                for by_word, low, tkey, at, n, content, spans in zip(*(cols[c] for c in ("by_word", "low", "tkey", "at", "n", "content", "spans"))):
                    size = sizes[by_word][step]
                    for lo, count, core, whole in parts_of(content, low, n, size, widths[by_word], by_word, None if all_of_it else spans):
                        yield by_word, low, tkey, at, lo, count, _digest(core), _digest(whole)

            return work

        rows = contents.withColumn("spans", F.lit(None).cast("array<struct<lo:int,n:int>>")) if opened is None else contents.withColumn("run_at", F.col("at")).join(
            opened.groupBy(*run).agg(F.collect_list(F.struct("lo", "n")).alias("spans")), run)
        parts = scratch.write(arrow_rows(rows, "by_word boolean, low long, tkey binary, run_at int, lo int, n int, core binary, whole binary", start), "parts")
        bucket = ["by_word", "low", "core"]
        kinds = parts.groupBy(*bucket, "whole").agg(F.count("*").alias("c"), F.min(F.struct("tkey", "run_at", "lo", "n")).alias("one"))
        kinds = scratch.write(kinds, "part_kinds")
        twice = kinds.where("c > 1").select(*bucket, "whole")
        found.append(parts.join(twice, [*bucket, "whole"], "left_semi").select("by_word", "tkey", (F.col("run_at") + F.col("lo")).alias("at"), "n"))
        several = kinds.groupBy(*bucket).agg(F.count("*").alias("k"), F.min("c").alias("least")).where("k > 1 and least = 1").select(*bucket)
        opened = kinds.join(several, bucket, "left_semi").select("by_word", "one.tkey", "one.run_at", "one.lo", "one.n")
    return found


def _compare(contents: DataFrame, modes) -> DataFrame:
    """(by_word, tkey, at, n): windows that stand elsewhere in their bucket too."""
    widths = dict(modes)

    def run(batches):
        held, weight, last = [], 0, None

        def pack(rows):
            out = []
            for by_word in {r[0] for r in rows}:
                own, numbers = [r for r in rows if r[0] == by_word], {}
                bucket = [numbers.setdefault(r[1], len(numbers)) for r in own]
                for piece, at, n in repeated_windows([r[5] for r in own], bucket, [r[4] for r in own], widths[by_word], by_word):
                    out.append((by_word, own[piece][2], own[piece][3] + at, n))
            cols = list(zip(*out)) or [()] * 4
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.bool_(), pa.binary(), pa.int32(), pa.int32()))], names=["by_word", "tkey", "at", "n"])

        for batch in batches:
            for row in zip(*(batch.column(c).to_pylist() for c in ("by_word", "low", "tkey", "at", "known", "content"))):
                if last == row[:4]:  # copies of one text
                    continue
                if weight > BATCH_BYTES and row[:2] != last[:2]:
                    yield pack(held)
                    held, weight = [], 0
                held.append(row)
                weight += len(row[5])
                last = row[:4]
        if held:
            yield pack(held)
        give_back()

    dealt = contents.repartition("by_word", "low").sortWithinPartitions("by_word", "low", "tkey", "at")
    return dealt.mapInArrow(run, "by_word boolean, tkey binary, at int, n int")


def repeat_spans(docs: DataFrame, scratch: Scratch, width: int = WIDTH, words: int | None = None) -> DataFrame:
    """(by_word, tkey, at, n), written in the shared folder: the windows at at … at + n - 1 of the texts with this key stand
    elsewhere too."""
    modes = [(False, width)] + ([(True, words)] if words else [])
    enough = F.octet_length("raw") >= (min(width, 2 * words - 1) if words else width)
    texts = keyed(docs).where(enough)
    runs = scratch.write(anchor_runs(texts, modes), "runs")
    bucket = ["by_word", "low"]
    met = runs.groupBy(*bucket).agg(F.count("*").alias("c"), F.max("twice").alias("any_twice")).where("c > 1 or any_twice").select(*bucket)
    met = scratch.write(runs.join(met, bucket, "left_semi"), "met")
    kinds = scratch.write(met.groupBy(*bucket, "whole").agg(F.count("*").alias("c"), F.min(F.struct("tkey", "at", "n")).alias("one"), F.max("twice").alias("twice")), "kinds")
    several = kinds.groupBy(*bucket).agg(F.count("*").alias("k"), F.max("twice").alias("any_twice"), F.max(F.col("c") == 1).alias("any_new"),
                                         F.sum(F.col("one.n") + width).alias("size")).where("any_new and (k > 1 or any_twice)")
    chosen = kinds.join(several.select(*bucket, (F.col("size") > HOT_BYTES).alias("hot")), bucket).select(
        *bucket, "one.tkey", "one.at", "one.n", (F.col("c") > 1).alias("known"), "hot")
    contents = scratch.write(_contents(texts, chosen, modes), "contents")
    hot = contents.where("hot").dropDuplicates(["by_word", "tkey", "at"])
    out = met.join(kinds.where("c > 1").select(*bucket, "whole"), [*bucket, "whole"], "left_semi").select("by_word", "tkey", "at", "n").unionByName(
        _compare(contents.where("not hot"), modes))
    for more in _refined(hot, modes, scratch) if not contents.where("hot").isEmpty() else []:
        out = out.unionByName(more)
    spans = scratch.write(out.distinct(), "spans")
    scratch.clear(but=1)
    return spans


def _kept(raw: bytes, spans, width: int, words: int | None):
    """(bytes removed, maximal removed stretches, remaining bytes)."""
    if not spans:
        return 0, 0, raw
    units = word_units(raw)[1:] if any(s["by_word"] for s in spans) else None
    cuts = sorted((int(units[0][s["at"]]), int(units[1][s["at"] + s["n"] + words - 2])) if s["by_word"] else (s["at"], s["at"] + s["n"] + width - 1) for s in spans)
    out, done, gone, stretches = [], 0, 0, 0
    for a, b in cuts:
        if a > done or not stretches:
            out.append(raw[done:a])
            stretches += 1
        gone += max(0, b - max(a, done))
        done = max(done, b)
    return gone, stretches, b"".join(out) + raw[done:]


def _with_spans(rows: DataFrame, spans: DataFrame) -> DataFrame:
    per_text = spans.groupBy("tkey").agg(F.collect_list(F.struct("at", "n", "by_word")).alias("spans"))
    return rows.join(per_text, "tkey", "left")


def repeat_report(docs: DataFrame, width: int = WIDTH, words: int | None = None) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256), one row per row of ``docs``. With ``words`` also (passage_bytes, n_passages):
    bytes under passages of that many words that stand elsewhere too, and maximal stretches of them; the other columns stay those of
    the repeated strings of ``width`` bytes."""
    spans = repeat_spans(docs, Scratch(docs.sparkSession), width, words)
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", passage_bytes long, n_passages long" if words else "")

    def start():
        def work(cols):
            for doc_id, text, found in zip(cols["doc_id"], cols["raw"], cols["spans"]):
                raw = text.encode("utf-8", "surrogatepass")
                by_byte, by_word = ([s for s in found or () if s["by_word"] == kind] for kind in (False, True))
                gone, stretches, kept = _kept(raw, by_byte, width, None)
                passages = _kept(raw, by_word, width, words)[:2] if words else ()
                yield doc_id, len(raw), gone, stretches, hashlib.sha256(kept).hexdigest(), *passages

        return work

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("raw"))
    rows = rows.withColumn("tkey", F.unhex(F.substring(F.sha2(F.col("raw").cast("binary"), 256), 1, 32)))
    return arrow_rows(_with_spans(rows, spans), schema, start)


def remove_repeats(docs: DataFrame, width: int = WIDTH, words: int | None = None) -> DataFrame:
    """``docs`` with the repeated bytes cut out of ``text``; pieces of a character that a cut leaves are dropped."""
    spans = repeat_spans(docs, Scratch(docs.sparkSession), width, words)

    def run(batches):
        for batch in batches:
            kept = []
            for text, found in zip(batch.column("raw").to_pylist(), batch.column("spans").to_pylist()):
                kept.append(_kept(text.encode("utf-8", "surrogatepass"), found, width, words)[2].decode("utf-8", "ignore") if found else text)
            yield pa.RecordBatch.from_arrays([batch.column("whole_row"), pa.array(kept, pa.string())], names=["whole_row", "kept"])

    raw = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("whole_row"), F.col("text").alias("raw"), F.unhex(F.substring(F.sha2(raw.cast("binary"), 256), 1, 32)).alias("tkey"))
    joined = _with_spans(rows, spans).select("whole_row", "raw", "spans")
    schema = joined.select("whole_row", F.col("raw").alias("kept")).schema
    return joined.mapInArrow(run, schema).select(*(F.col("kept").alias(c) if c == "text" else F.col(f"whole_row.`{c}`").alias(c) for c in docs.columns))
