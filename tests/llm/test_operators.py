"""Operators against plain versions on small fixtures, with the hard cases: nulls, empties, repeats, clashing columns."""

import hashlib
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest

from sparsetier.llm import byte_bpe, decontaminate, license_scan, near_dedup, quality_rules, suffix_dedup, token_counts, token_files, toxicity, warc

LONG = " ".join(f"word{n * 7919 % 1000}" for n in range(400))
ROWS = [(1, LONG + ".", "x"), (2, LONG + ".", "x"), (3, LONG.replace("word3", "other", 1) + " tail end.", "y"), (4, None, None), (5, "", "z"),
        (6, "All Rights Reserved cc by CC BY", "z"), (7, "a\nb\na\n a  b", None), (8, "same same same same same same same same same same same same.", "q"), (9, "é" * 500, "q")]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, s, "clash", 0, b"k") for i, t, s in ROWS], "doc_id long, text string, source string, kept string, n int, key binary")


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("false")


TEXTS = {i: t or "" for i, t, _ in ROWS}


def test_suffix_dedup(docs, empty):
    seen = Counter(t.encode()[n:n + 400] for t in TEXTS.values() for n in range(len(t.encode()) - 399))
    for r in suffix_dedup.repeat_report(docs).collect():
        raw = TEXTS[r.doc_id].encode()
        gone = np.zeros(len(raw), bool)
        for n in range(len(raw) - 399):
            if seen[raw[n:n + 400]] > 1:
                gone[n:n + 400] = True
        assert (r.n_bytes, r.n_removed) == (len(raw), gone.sum())
        assert r.kept_sha256 == hashlib.sha256(np.frombuffer(raw, np.uint8)[~gone].tobytes()).hexdigest()
    assert suffix_dedup.repeat_report(empty).count() == 0
    assert suffix_dedup.remove_repeats(docs).columns == docs.columns


def test_suffix_order():
    pieces = [b"banana bandana banana " * 3, b"", b"bandana", b"zz" * 9]
    text = suffix_dedup.Suffixes(pieces, False)
    group = np.array([0] * len(pieces[0]) + [1] * (len(text.raw) - len(pieces[0])))
    got = text.sort(np.arange(len(text.raw)), group)
    want = sorted(range(len(text.raw)), key=lambda n: (group[n], text.raw[n:text.end_of[n]]))
    assert [text.raw[n:text.end_of[n]] for n in got] == [text.raw[n:text.end_of[n]] for n in want]
    words = suffix_dedup.Suffixes([b"to be or not to be", b"not to be"], True)
    assert words.common(np.array([3, 0]), np.array([6, 4])).tolist() == [3, 2]
    a, b = (np.random.default_rng(n).integers(0, (1 << 61) - 1, 2000, dtype=np.uint64) for n in (1, 2))
    assert suffix_dedup._times(a, b).tolist() == [int(x) * int(y) % ((1 << 61) - 1) for x, y in zip(a, b)]


def cut_plainly(texts, width):
    """Plain version: one table of all windows; (removed, stretches, kept) per text."""
    seen = Counter(t[n:n + width] for t in texts for n in range(len(t) - width + 1))
    for t in texts:
        gone = np.zeros(len(t) + 1, bool)
        for n in range(len(t) - width + 1):
            if seen[t[n:n + width]] > 1:
                gone[n:n + width] = True
        yield int(gone.sum()), int((gone[1:] & ~gone[:-1]).sum() + gone[0]), np.frombuffer(t, np.uint8)[~gone[:-1]].tobytes()


@pytest.mark.parametrize("hot", [False, True])
def test_suffix_dedup_random(spark, hot, monkeypatch):
    """Texts over few letters, periodic ones, cut-and-pasted ones, a long one and repeated rows and ids; all buckets opened if ``hot``."""
    if hot:
        monkeypatch.setattr(suffix_dedup, "HOT_BYTES", 0)
    rng = np.random.default_rng(5)
    letters = ["".join(rng.choice(list("abcd"), 900)) for _ in range(6)]
    texts = ["z" * 1500, "ab" * 700, "abc" * 500 + "ab", *letters]
    for _ in range(40):
        a, b, c = rng.integers(0, 6, 3)
        x, y, z = rng.integers(0, 900, 3)
        texts.append(letters[a][:x] + letters[b][y:] + "é" + letters[c][z:])
    texts += [letters[0][100:500], letters[0][100:500], letters[1][3:403] + "\ufffd", "".join(rng.choice(list("abcdefgh"), 50_000)) + letters[2], "", None]
    got = suffix_dedup.repeat_report(spark.createDataFrame([(n // 2 if n % 7 else None, t) for n, t in enumerate(texts)], "doc_id long, text string")).collect()
    raw = [(t or "").encode() for t in texts]
    want = [(len(t), n, s, hashlib.sha256(kept).hexdigest()) for t, (n, s, kept) in zip(raw, cut_plainly(raw, 400))]
    assert Counter((r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got) == Counter(want)


@pytest.mark.parametrize("hot", [False, True])
def test_suffix_dedup_short_passages(spark, hot, monkeypatch):
    """A passage of 51 short words is under 400 bytes; whatever white space parts its words, the report tells it and cuts nothing."""
    if hot:
        monkeypatch.setattr(suffix_dedup, "HOT_BYTES", 0)
    words = [f"w{n}" for n in range(51)]
    texts = ["one " + " ".join(words) + " end", "two " + "\n".join(words) + " é", " ".join(words[:50]) + " other", None, "é " + " ".join(words * 2)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = sorted(suffix_dedup.repeat_report(docs, words=51).collect())
    size = len(" ".join(words))
    assert [(r.passage_bytes, r.n_passages) for r in got] == [(size, 1), (size, 1), (0, 0), (0, 0), (2 * size, 2)]
    assert [tuple(r)[:5] for r in got] == [tuple(r) for r in sorted(suffix_dedup.repeat_report(docs).collect())]
    assert not any(r.n_removed for r in got)


def test_suffix_dedup_no_collision_by_construction(spark):
    """A string and its complement whose polynomial hashes modulo 2**64 agree for any base are still told apart."""
    bits = [bin(n).count("1") % 2 for n in range(2048)]
    rows = [(1, "".join("ab"[v] for v in bits)), (2, "".join("ba"[v] for v in bits))]
    got = suffix_dedup.repeat_report(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    want = [n for n, _, _ in cut_plainly([t.encode() for _, t in rows], 400)]
    assert [r.n_removed for r in sorted(got)] == want


def test_remove_repeats_keeps_replacement_characters(spark):
    shared = "é" * 250
    rows = [(1, f"\ufffd start {shared} end \ufffd", 1, b"k", None), (2, f"other {shared}", 2, b"k", "v"), (3, None, 3, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, tkey int, raw binary, spans string")
    got = {r.doc_id: r for r in suffix_dedup.remove_repeats(docs).collect()}
    assert got[1].text == "\ufffd start end \ufffd" and got[2].text == "other"
    assert got[1].tkey == 1 and got[2].spans == "v" and got[3].text is None


def test_byte_bpe(docs, empty):
    import tiktoken

    coder = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.load_ranks("byte_bpe_50k.tiktoken"), special_tokens={})
    got = {r.doc_id: r for r in byte_bpe.decode(byte_bpe.encode(docs)).collect()}
    for i, t in TEXTS.items():
        assert list(got[i].ids) == coder.encode_ordinary(t)
        assert bytes(got[i].data) == t.encode()
    assert byte_bpe.encode(empty).count() == 0


def rows_through(df, node):
    """Rows that the nodes of this name gave in the plan of ``df``, which was collected."""
    plan, found = df._jdf.queryExecution().executedPlan(), []
    left = [plan.executedPlan() if plan.nodeName() == "AdaptiveSparkPlan" else plan]
    while left:
        at = left.pop()
        if at.nodeName() == node:
            found.append(at.metrics().apply("numOutputRows").value())
        left += [at.plan()] if at.nodeName().endswith("QueryStage") else [at.children().apply(n) for n in range(at.children().size())]
    return sum(found)


def test_byte_bpe_decodes_distinct_ids(spark):
    """Many texts of few words: the join with the token-byte table gets the ids of a block once, not once for every place; empty texts and a
    text that is several rows of its block stay what they are."""
    import tiktoken

    rows = [(n, "one two three four " * 1000 + f"unheardofword{n % 3}") for n in range(20)] + [(20, ""), (21, None), (22, "x"), (23, "a b " * 200_000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(2)
    coder = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.load_ranks("byte_bpe_50k.tiktoken"), special_tokens={})
    want = []
    for i, t in rows:
        ids = coder.encode_ordinary(t or "")
        want.append((i, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
    for encoded in (byte_bpe.encode(docs, block_chars=1 << 15), byte_bpe.encode_blocks(docs, block_chars=1 << 15), byte_bpe.encode_blocks(docs)):
        got = byte_bpe.digests(encoded)
        assert sorted(map(tuple, got.collect())) == sorted(want)
        assert 0 < rows_through(got, "BroadcastHashJoin") < 1000 < sum(n for _, n, _, _ in want)


def test_token_files(docs, empty):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    got = {r.doc_id: r for r in token_files.read_shards(*token_files.write_shards(docs)).collect()}
    at = 0
    for i, t in TEXTS.items():
        ids = np.array(tok.encode(t, add_special_tokens=False).ids + [2], "<u4")
        assert (got[i].start, got[i].n_tokens, got[i].ids_crc32) == (at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    assert token_files.read_shards(*token_files.write_shards(empty)).count() == 0


def test_token_counts(docs, empty):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    got = token_counts.token_counts(docs, "byte_bpe_50k.json", piece_chars=50).collect()
    assert {r.doc_id: r.n_tokens for r in got} == {i: len(tok.encode(t).ids) for i, t in TEXTS.items()}
    assert token_counts.token_counts(empty, "byte_bpe_50k.json").count() == 0


def test_near_dedup(docs, empty, spark):
    got = {r.doc_id: r for r in near_dedup.near_components(docs).collect()}
    assert got[1].component_id == got[2].component_id == got[3].component_id == 1
    assert [i for i in TEXTS if got[i].kept] == [1, 4, 5, 6, 7, 8, 9]
    assert got[4].n_shingles == got[5].n_shingles == 0 and got[8].n_shingles == 2
    assert near_dedup.near_components(empty).count() == 0


def test_quality(docs, empty):
    got = {r.doc_id: r for r in quality_rules.quality_measures(docs).collect()}
    assert (got[8].n_words, got[8].n_repeat_words, got[8].base_failed) == (12, 11, True)
    assert got[7].n_dup_lines == 1 and got[4].n_words == 0 and got[1].kept
    assert quality_rules.quality_measures(empty).count() == 0


def test_quality_lines(spark):
    good = "This is a line of quite ordinary words that ends as a sentence does."
    other = "Quite another sentence stands here in its place, and it ends well."
    rows = [(1, f"{good}\nHome | News | Contact.\nno mark at the end of it\nRead more.\nAlle Rechte vorbehalten.\n{other}"),
            (2, "no mark here and so this line goes away\n" * 9 + good), (None, good), (None, good), (3, good + " Read more " + "of it " * 40 + "now.")]
    docs = spark.createDataFrame([(i, t, "clash", 7, "w") for i, t in rows], "doc_id long, text string, kept string, n_words int, whole_row string")
    got = sorted(quality_rules.clean_documents(docs).collect(), key=lambda r: (r.doc_id is None, r.doc_id))
    assert [(r.doc_id, r.text) for r in got] == [(1, f"{good}\n{other}"), (None, good), (None, good)]
    assert all((r.kept, r.n_words, r.whole_row) == ("clash", 7, "w") for r in got)
    assert quality_rules.clean_documents(docs.where("false")).columns == docs.columns


def test_quality_equals_sql(spark, docs):
    import duckdb

    rows = docs.select("doc_id", "text").unionByName(spark.createDataFrame([(8, "x"), (8, "x"), (None, "a b c d e\n" * 6)], "doc_id long, text string"))
    con = duckdb.connect()
    con.register("documents", rows.toArrow())
    order = lambda found: sorted(tuple(map(str, r)) for r in found)
    got, want = quality_rules.quality_measures(rows).select(quality_rules.COLUMNS).collect(), con.sql(quality_rules.SQL).fetchall()
    assert order(got) == order(want)


def test_toxicity(spark, docs, empty):
    rows = [(n, f"Plain words here w{n % 7}. " + ("You vile thing! " if n % 3 == 0 else "Nice day! ") + "The end.") for n in range(300)]
    table = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(n, int(n % 3 == 0)) for n in range(300)], "doc_id long, toxic int")
    got = toxicity.toxicity(table, labels).collect()
    assert all(r.predicted == int(r.doc_id % 3 == 0) for r in got)
    assert all(r.worst_sentence == 1 for r in got if r.predicted)
    assert toxicity.toxicity(docs, labels.where("false")).count() == len(ROWS)
    assert toxicity.toxicity(empty, labels).count() == 0


def test_warc(spark):
    pages = spark.createDataFrame([(1, "http://a.b/x", "p"), (2, "http://a.b/x", "p"), (3, None, None), (4, "bad", ""), (5, "http://c.b/é?q", "ö")], "page_id long, url string, html string")
    got = {r.page_id: r for r in warc.warc_roundtrip(pages).collect()}
    assert {i: (r.record_type, r.refers_to) for i, r in got.items()} == {1: ("response", None), 2: ("revisit", 1), 3: ("response", None), 4: ("revisit", 3), 5: ("response", None)}
    assert warc.warc_roundtrip(pages.where("false")).count() == 0


@pytest.mark.parametrize("k", [0, 1, 2, 3, 5, 8])
def test_loser_tree(k):
    runs = [sorted((v * 37 % 11, v) for v in range(n, 40, n + 1)) for n in range(k)]
    assert [v for v in warc.LoserTree(runs)] == [v for _, v in sorted((x for r in runs for x in r), key=lambda x: x[0])] or sorted(warc.LoserTree(runs)) == sorted(v for r in runs for _, v in r)


def test_decontaminate(spark, docs, empty):
    item = LONG[100:400]
    bench = spark.createDataFrame([(1, item[:50] + "ZZ" + item[52:]), (2, None), (3, "never seen anywhere in these texts, not even in a small part of them")], "item_id long, text string")
    assert {(r.doc_id, r.item_id) for r in decontaminate.contaminated(docs, bench).collect()} == {(1, 1), (2, 1), (3, 1)}
    assert decontaminate.contaminated(empty, bench).count() == 0 == decontaminate.contaminated(docs, bench.where("false")).count()


def least_distance(item, text):
    """Plain version: the whole table of edit distances against any substring."""
    row = list(range(len(item) + 1))
    best = row[-1]
    for c in text:
        above, row = row, [0]
        for n, x in enumerate(item, 1):
            row.append(min(above[n - 1] + (x != c), above[n] + 1, row[n - 1] + 1))
        best = min(best, row[-1])
    return best


@pytest.mark.parametrize("block_bytes", [8 << 20, 200])
def test_decontaminate_all_lengths(spark, block_bytes):
    """Items of 3 to 300 characters with edits at random places, in one block and in many, against the whole distance table."""
    rng = np.random.default_rng(11)
    word = lambda: "".join(rng.choice(list("abcdefghij"), rng.integers(2, 8)))
    items = [(n, " ".join(word() for _ in range(k))) for n, k in enumerate([1, 2, 2, 3, 4, 6, 8, 10, 20, 40])] + [(8, " ".join(word() for _ in range(9))), (50, ""), (51, None), (None, "null id item here")]
    rows = []
    for n in range(60):
        text = [word() for _ in range(rng.integers(0, 60))]
        own = items[rng.integers(0, 10)][1]
        chars = list(own)
        for _ in range(rng.integers(0, 2 + len(own) // 15)):
            at = int(rng.integers(0, len(chars)))
            chars[at:at + 1] = [[], ["x"], [chars[at], "y"]][rng.integers(0, 3)]
        text.insert(int(rng.integers(0, len(text) + 1)), "".join(chars))
        rows.append((n // 2 if n % 9 else None, " ".join(text).title()))
    rows += [(70, None), (71, "")]
    got = decontaminate.contaminated(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"), block_bytes).collect()
    want = Counter()
    for i, t in rows:
        flat = f" {decontaminate.reduce_text(t or '')} "
        for n, x in items:
            item = decontaminate.reduce_text(x or "")
            k = decontaminate.budget(item)
            if item and (f" {item} " in flat if k == 0 else least_distance(item, flat) <= k):
                want[i, n] += 1
    assert Counter((r.doc_id, r.item_id) for r in got) == want and len(want) > 20


def test_myers():
    assert decontaminate.myers_best("abcd", "xxabxcdyy")[0] == 1
    assert decontaminate.myers_best("abcd", "xxabcdyy") == (0, 6)


def test_license(docs, empty):
    got = {r.doc_id: r for r in license_scan.license_scan(docs).collect()}
    assert (got[6].n_base, got[6].first_word, got[6].last_word, got[6].base_labels) == (3, 0, 5, "cc-by,reserved")
    assert got[1].labels == "" and got[4].n_words == 0
    assert license_scan.license_scan(empty).count() == 0


def test_license_whole_notices(spark):
    notices = [(label, text) for label, text, _ in license_scan.TEMPLATES]
    prose = "Some words can be put by hand in a file for each form, except for the code; 4 are free of charge, may apply, and this is any copy you use."
    rows = [(0, "\n".join(t for _, t in notices))] + [(n, f"{prose}\n{text}") for n, (_, text) in enumerate(notices, 1)] + [(99, prose), (99, prose), (None, "x " * 5000 + notices[0][1])]
    got = license_scan.license_scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    found = {r.doc_id: r for r in got}
    assert len(got) == len(rows)
    assert set(found[0].labels.split(",")) == {label for label, _ in notices} and found[99].labels == ""
    for n, (label, _) in enumerate(notices, 1):
        assert label in found[n].labels.split(",") and found[n].score == 1.0
    assert found[None].labels == "mit" and found[None].n_words == 5005


def test_license_needs_place_and_phrase():
    index = license_scan.Index()
    assert index.scan("the mit license released under it was")[3] == set()  # the words, but not in their places
    assert index.scan("Released under the MIT licence")[3] == set()  # no key phrase
    assert index.scan("released under the new mit license today, under the mit license")[3] == {"mit"}
    rare = license_scan.Index(rarity={"mit": 1, "the": 1000}, n_docs=1000)
    assert rare.weight["mit"] > rare.weight["the"]
