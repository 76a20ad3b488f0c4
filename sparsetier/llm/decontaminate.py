"""Benchmark decontamination by pigeonhole edit matching.

Texts and items are lower-cased and reduced to letters and digits with single blanks. An item may occur with as many edits k as 5 % of
its length, rounded; it is cut into k + 1 pieces, of which one must occur unchanged. Exact piece hits (Aho-Corasick) give windows that
Myers' bit-parallel distance verifies. An item too short for an edit (under 10 characters) has one piece and must stand there on word
boundaries. Items, a stated query set, are handled in blocks of bounded bytes, one pass over all rows per block; of several
blocks each is written before the next is read.

Null or empty items and texts match nothing. Repeated items and rows keep their own rows; a null doc_id is given as it is. Of an item's
places in a text the nearest match, then the first, counts. Whole texts are searched, however long. Other input columns are ignored.
"""

from __future__ import annotations

import re
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.llm.common import Scratch, arrow_rows, texts_of

_JUNK = re.compile(r"[\W_]+")
ITEM_SCHEMA = "doc_id long, item_id long, distance int, place long"


def reduce_text(text: str) -> str:
    return _JUNK.sub(" ", text.lower()).strip()


def budget(item: str, share: float = 0.05) -> int:
    return int(len(item) * share + 0.5)


def pieces(item: str, k: int) -> list[tuple[int, str]]:
    cuts = [len(item) * n // (k + 1) for n in range(k + 2)]
    return [(a, item[a:b]) for a, b in zip(cuts, cuts[1:]) if b > a]


def myers_best(pattern: str, text: str) -> tuple[int, int]:
    """(least edit distance of the pattern to a substring of the text, end of that substring), column by column in one
    machine-independent bit vector."""
    m = len(pattern)
    eq: dict[str, int] = {}
    for n, c in enumerate(pattern):
        eq[c] = eq.get(c, 0) | 1 << n
    mask, high = (1 << m) - 1, 1 << (m - 1)
    up, down, score = mask, 0, m
    best, end = m, 0
    for n, c in enumerate(text):
        e = eq.get(c, 0)
        v = e | down
        h = (((e & up) + up) ^ up) | e
        plus, minus = down | (mask & ~(h | up)), up & h
        if plus & high:
            score += 1
        elif minus & high:
            score -= 1
        plus, minus = (plus << 1) & mask, (minus << 1) & mask
        up, down = minus | (mask & ~(v | plus)), plus & v
        if score < best:
            best, end = score, n + 1
    return best, end


def _block_matches(texts: DataFrame, shared) -> DataFrame:
    """Matches of one broadcast block of items."""

    def start():
        import ahocorasick

        automaton, owners = ahocorasick.Automaton(), {}
        reduced = [(item_id, reduce_text(t)) for item_id, t in shared.value]
        for n, (_, item) in enumerate(reduced):
            k = budget(item)
            for offset, piece in pieces(item if k else f" {item} ", k):
                owners.setdefault(piece, []).append((n, offset))
        for piece, own in owners.items():
            automaton.add_word(piece, (len(piece), own))
        automaton.make_automaton()

        def work(cols):
            for doc_id, text in zip(cols["doc_id"], cols["text"]):
                flat = f" {reduce_text(text)} "
                found: dict[int, tuple[int, int]] = {}
                tried: dict[int, list] = {}
                for end, (length, own) in automaton.iter(flat):
                    for n, offset in own:
                        item = reduced[n][1]
                        k = budget(item)
                        at = end - length + 1 - offset
                        if k == 0:
                            found.setdefault(n, (0, at))
                            continue
                        if n in found and found[n][0] == 0:
                            continue
                        if any(lo <= at - k and at + k <= hi for lo, hi in tried.get(n, [])[-2:]):
                            continue
                        if flat.startswith(item, max(at, 0)) and at >= 0:
                            found[n] = (0, at)
                            continue
                        lo = max(0, at - 2 * k)
                        tried.setdefault(n, []).append((at - 2 * k, at + 2 * k))
                        distance, stop = myers_best(item, flat[lo:at + len(item) + 2 * k])
                        if distance <= k and (n not in found or distance < found[n][0]):
                            found[n] = (distance, max(0, lo + stop - len(item)))
                for n, (distance, place) in sorted(found.items()):
                    yield doc_id, reduced[n][0], distance, place

        return work

    return arrow_rows(texts, ITEM_SCHEMA, start)


def contaminated(docs: DataFrame, benchmark: DataFrame, block_bytes: int = 8 << 20) -> DataFrame:
    """(doc_id, item_id, distance, place): one row per document row and item that occurs in it within the budget."""
    texts, spark = texts_of(docs), docs.sparkSession
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), "text").where("text is not null").orderBy("item_id", "text")
    scratch, written = Scratch(spark), []

    def blocks():
        block, size = [], 0
        for r in items.toLocalIterator():  # the stated query set, block by block
            if not reduce_text(r.text):
                continue
            block.append((r.item_id, r.text))
            size += len(r.text)
            if size >= block_bytes:
                yield block
                block, size = [], 0
        if block:
            yield block

    ahead = blocks()
    block = next(ahead, None)
    while block is not None:
        after = next(ahead, None)
        shared = spark.sparkContext.broadcast(block)
        found = _block_matches(texts, shared)
        if after is None and not written:
            return found
        written.append(scratch.write(found, "matches"))
        shared.unpersist()
        block = after
    return reduce(DataFrame.unionByName, written) if written else spark.createDataFrame([], ITEM_SCHEMA)
