"""The whole pipeline over sf0.001, stage by stage, against a plain version in Python."""

import re
from collections import Counter

import duckdb
import pytest
from test_pipeline import without_repeats

import corpus_pipeline
from sparsetier.llm import decontaminate, quality_rules

DATA = "/root/testdata/sf0.001"


def clean_lines(text):
    """Kept lines, or None for a rejected text."""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    fives = Counter(tuple(words[n:n + 5]) for n in range(len(words) - 4))
    covered = {n + k for n in range(len(words) - 4) if fives[tuple(words[n:n + 5])] > 1 for k in range(5)}
    good = [line for line in text.split("\n") if re.search(quality_rules.PUNCTUATED.replace(r"\z", r"\Z"), line) and not re.search(quality_rules.NAVIGATION, line)
            and not (len(line) <= quality_rules.SHORT and re.search(quality_rules.BOILERPLATE, line.lower()))]
    size = lambda t: len(re.sub(r"[\x20\x09-\x0D]", "", t))
    if len(words) < 10 or 100 * len(covered) > 20 * len(words) or size("\n".join(good)) < quality_rules.MIN_KEPT * size(text):
        return None
    return "\n".join(good)


def shingles(text):
    w = text.encode().lower().split()
    return {tuple(w[n:n + 5]) for n in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


@pytest.fixture(scope="module")
def stages(spark):
    """Rows (doc_id, text) that each stage gives, the last with its own columns."""
    docs, out = spark.read.parquet(f"{DATA}/documents.parquet"), {}
    out["documents"] = docs.select("doc_id", "text").collect()
    for name, stage in corpus_pipeline.STAGES:
        columns = docs.columns
        docs = corpus_pipeline.materialize(stage(spark, docs, DATA), "test")
        assert docs.columns == columns or name == "byte_bpe"
        out[name] = docs.select("doc_id", "text").collect() if name != "byte_bpe" else docs.collect()
    return out


def test_quality_rules(stages):
    want = [(r.doc_id, clean_lines(r.text or "")) for r in stages["documents"]]
    assert sorted(map(tuple, stages["quality_rules"])) == sorted((i, t) for i, t in want if t is not None)


def test_near_dedup(stages):
    rows = {r.doc_id: shingles(r.text) for r in stages["quality_rules"]}
    first = {i: i for i in rows}

    def root(i):
        while first[i] != i:
            i = first[i]
        return i

    for a in rows:
        for b in rows:
            if a < b and rows[a] & rows[b] and 100 * len(rows[a] & rows[b]) >= 75 * len(rows[a] | rows[b]):
                x, y = sorted((root(a), root(b)))
                first[y] = x
    assert sorted(r.doc_id for r in stages["near_dedup"]) == sorted(i for i in rows if root(i) == i)


def test_suffix_dedup(stages):
    before = sorted(stages["near_dedup"])
    assert [r.text for r in sorted(stages["suffix_dedup"])] == without_repeats([r.text for r in before])


def test_decontaminate(stages):
    items = [decontaminate.reduce_text(t) for (t,) in duckdb.sql(f"select text from '{DATA}/benchmark.parquet' where text is not null").fetchall()]

    def leaks(text):
        flat = f" {decontaminate.reduce_text(text)} "
        return any(decontaminate.myers_best(item, flat)[0] <= decontaminate.budget(item) for item in items)

    assert sorted(r.doc_id for r in stages["decontaminate"]) == sorted(r.doc_id for r in stages["suffix_dedup"] if not leaks(r.text))


def test_byte_bpe(stages):
    import hashlib

    assert {r.doc_id: r.decoded_sha256 for r in stages["byte_bpe"]} == {r.doc_id: hashlib.sha256(r.text.encode()).hexdigest() for r in stages["decontaminate"]}


def test_empty_table_and_extra_columns(spark):
    """Nulls in every column, columns named like those used inside, and no rows at all."""
    rows = [(None, None, None, None, "a", 1, "w"), (1, None, "en", None, None, None, None), (1, "Some words of a text that is long enough to stay, and it ends here.", None, "s", "b", 2, "w"),
            (None, "Some other words of a text that is long enough to stay, as it ends there.", None, "s", "b", 2, "w")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, kept string, key int, whole_row string")
    for table, n in ((docs, 2), (docs.where("false"), 0)):
        for name, stage in corpus_pipeline.STAGES:
            table = corpus_pipeline.materialize(stage(spark, table, DATA), "test")
            assert name == "byte_bpe" or table.columns == docs.columns
        assert table.count() == n
