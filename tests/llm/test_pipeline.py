"""Pipeline stages against plain versions on small fixtures."""

import hashlib
import re
from collections import Counter

import numpy as np
import public_tokenizers
import pytest

import corpus_pipeline
from sparsetier.llm import byte_bpe, near_dedup, suffix_dedup

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"


def table_of(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t)) for i, t in rows], COLUMNS)


def filler(seed, n):
    return " ".join(f"f{seed}x{k}" for k in range(n))


def without_repeats(texts, width=400, words=51):
    """Plain version: every window of bytes or words is held in one table, and those seen twice are cut."""
    seen, spans = {}, []
    for at, text in enumerate(texts):
        raw, found = text.encode(), [m.span() for m in re.finditer(rb"[^\s]+", text.encode())]
        for n in range(len(raw) - width + 1):
            seen.setdefault(raw[n:n + width], []).append((at, n, n + width))
        for n in range(len(found) - words + 1):
            seen.setdefault(tuple(raw[a:b] for a, b in found[n:n + words]), []).append((at, found[n][0], found[n + words - 1][1]))
    gone = [np.zeros(len(t.encode()), bool) for t in texts]
    for places in seen.values():
        if len(places) > 1:
            for at, a, b in places:
                gone[at][a:b] = True
    return [np.frombuffer(t.encode(), np.uint8)[~g].tobytes().decode(errors="ignore") for t, g in zip(texts, gone)]


@pytest.mark.parametrize("hot", [False, True])
def test_repeated_passages(spark, hot, monkeypatch):
    if hot:
        monkeypatch.setattr(suffix_dedup, "HOT_BYTES", 0)
    passage = " ".join(f"w{k % 97:02d}é" if k % 9 == 0 else f"p{k:02d}" for k in range(51))
    short = " ".join(f"q{k:02d}" for k in range(50))
    again = " ".join(f"r{k:02d}" for k in range(51))
    assert len(passage.encode()) < 300
    rows = [(1, f"{filler(1, 80)} {passage} {filler(2, 30)}"), (2, f"{filler(3, 10)} {passage.replace(' ', chr(10), 5)} {filler(4, 70)}"),
            (3, f"{short} {filler(5, 9)}"), (4, f"{filler(6, 9)} {short}"), (5, None), (6, ""), (7, f"{again} {filler(7, 3)} {again}"),
            (8, "z" * 450 + " a"), (9, "b " + "z" * 450), (10, " ".join(f"s{k:02d}" for k in range(51))), (None, " ".join(f"s{k:02d}" for k in range(51)))]
    got = corpus_pipeline.repeated_passages(spark, table_of(spark, rows), None)
    assert got.columns == table_of(spark, rows).columns
    got = got.collect()
    assert sorted((r.doc_id or 0, r.text or "") for r in got) == sorted(zip([i or 0 for i, _ in rows], without_repeats([t or "" for _, t in rows])))
    text = {r.doc_id: r.text for r in got}
    assert "p01" not in text[1] and "p01" not in text[2] and short in text[3] and short in text[4]


def test_near_duplicates(spark):
    one, two = filler(20, 60), filler(21, 60)
    near = one.replace("f20x3 ", "changed ")
    rows = [(1, one), (2, near), (3, two), (3, one + " more"), (4, filler(22, 40)), (4, filler(23, 40)), (None, two), (None, filler(24, 40)), (None, filler(24, 40)),
            (5, None), (5, ""), (6, ""), (None, None)]
    got = corpus_pipeline.near_duplicates(spark, table_of(spark, rows), None).collect()
    ids = Counter((r.doc_id, r.text or "") for r in got)
    assert ids == Counter([(1, one), (3, two), (4, filler(22, 40)), (4, filler(23, 40)), (None, filler(24, 40)), (5, ""), (6, ""), (None, "")])


def test_benchmark_leaks(spark, tmp_path):
    item = filler(30, 12)
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    rows = [(1, f"{filler(31, 9)} {item} {filler(32, 9)}"), (1, filler(33, 20)), (2, filler(34, 20)), (None, f"x {item} y"), (None, filler(35, 20)), (3, None)]
    got = corpus_pipeline.benchmark_leaks(spark, table_of(spark, rows), str(tmp_path)).collect()
    assert Counter((r.doc_id, r.text) for r in got) == Counter((i, t) for i, t in rows if item not in (t or ""))


def test_near_dedup_repeated_id(spark):
    rows = [(1, filler(40, 60)), (1, filler(41, 60)), (2, filler(40, 60) + " tail"), (3, filler(41, 60) + " tail")]
    got = near_dedup.near_components(table_of(spark, rows)).collect()
    assert {(r.doc_id, r.component_id) for r in got} == {(1, 1), (2, 1), (3, 1)}


def test_tokens(spark):
    import tiktoken

    coder = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.load_ranks("byte_bpe_50k.tiktoken"), special_tokens={})
    rows = [(1, filler(50, 30)), (1, "Élan vital.\n\n 12345"), (2, ""), (3, None), (None, "same"), (None, "same")]
    want = Counter()
    for i, t in rows:
        ids = coder.encode_ordinary(t or "")
        want[i, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()] += 1
    assert Counter(map(tuple, corpus_pipeline.tokens(spark, table_of(spark, rows), None).collect())) == want
