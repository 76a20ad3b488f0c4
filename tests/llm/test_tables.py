"""The registered queries over whole tables of sf0.01, against plain versions or the libraries."""

import base64
import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest

from sparsetier.llm import byte_bpe, license_scan, queries

DATA = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def texts(spark):
    return {r.doc_id: r.text or "" for r in spark.read.parquet(f"{DATA}/documents.parquet").select("doc_id", "text").collect()}


def rows_of(spark, name):
    return queries.queries()[name](spark, DATA).collect()


def test_op1(spark, texts):
    raw = {i: t.encode() for i, t in texts.items()}
    digest = lambda t, n: hashlib.blake2b(t[n:n + 400], digest_size=12).digest()
    seen = Counter(digest(t, n) for t in raw.values() for n in range(len(t) - 399))
    got = rows_of(spark, "op1_suffix_dedup")
    assert len(got) == len(raw)
    for r in got:
        t = raw[r.doc_id]
        gone = np.zeros(len(t) + 1, bool)
        for n in range(len(t) - 399):
            if seen[digest(t, n)] > 1:
                gone[n:n + 400] = True
        kept = np.frombuffer(t, np.uint8)[~gone[:-1]].tobytes()
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == (
            len(t), gone.sum(), int(gone[0]) + (gone[1:] & ~gone[:-1]).sum(), hashlib.sha256(kept).hexdigest()), r.doc_id


def test_op1_passages(spark, texts):
    """Passages of 51 words that stand twice, also those under 400 bytes, are told beside the strings of 400 bytes."""
    words = {i: [(m.start(), m.end()) for m in re.finditer(rb"[^\x20\x09-\x0D]+", t.encode())] for i, t in texts.items()}
    passage = lambda i, n: hashlib.blake2b(b" ".join(texts[i].encode()[a:b] for a, b in words[i][n:n + 51]), digest_size=12).digest()
    seen = Counter(passage(i, n) for i in texts for n in range(len(words[i]) - 50))
    short = 0
    for r in rows_of(spark, "op1_suffix_dedup"):
        gone = np.zeros(r.n_bytes + 1, bool)
        for n in range(len(words[r.doc_id]) - 50):
            if seen[passage(r.doc_id, n)] > 1:
                gone[words[r.doc_id][n][0]:words[r.doc_id][n + 50][1]] = True
        assert (r.passage_bytes, r.n_passages) == (gone.sum(), int(gone[0]) + (gone[1:] & ~gone[:-1]).sum()), r.doc_id
        short += r.n_removed == 0 < r.passage_bytes
    assert short > 0


def test_op2(spark, texts):
    import tiktoken

    coder = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.load_ranks("byte_bpe_50k.tiktoken"), special_tokens={})
    want = []
    for i, t in texts.items():
        ids = coder.encode_ordinary(t)
        want.append((i, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(t.encode()).hexdigest()))
    assert sorted(map(tuple, rows_of(spark, "op2_byte_bpe"))) == sorted(want)


def test_op4(spark, texts):
    from tokenizers import Tokenizer

    tok, at, want = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json")), 0, []
    for i, t in sorted(texts.items()):
        ids = np.array(tok.encode(t, add_special_tokens=False).ids + [2], "<u4")
        want.append((i, at, len(ids), zlib.crc32(ids.tobytes())))
        at += len(ids)
    assert sorted(map(tuple, rows_of(spark, "op4_token_files"))) == want


def test_op5(spark, texts):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want = [(i, len(t.encode()), n, n > 1024) for i, t in texts.items() for n in [len(tok.encode(t, add_special_tokens=False).ids)]]
    assert sorted(map(tuple, rows_of(spark, "op5_token_counts"))) == sorted(want)


def test_op7(spark):
    pages = spark.read.parquet(f"{DATA}/pages.parquet").collect()
    first, want = {}, []
    for p in pages:
        body = (p.html or "").encode()
        first[body] = min(first.get(body, p.page_id), p.page_id)
    for p in pages:
        body = (p.html or "").encode()
        other = first[body] != p.page_id
        want.append((p.page_id, len(body), base64.b32encode(hashlib.sha1(body).digest()).decode(), "revisit" if other else "response", first[body] if other else None))
    got = [(r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in rows_of(spark, "op7_warc")]
    assert sorted(got) == sorted(want)


def shingle_sets(texts):
    out = {}
    for i, t in texts.items():
        w = t.encode().lower().split()
        out[i] = {tuple(w[n:n + 5]) for n in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    return out


def test_op9(spark, texts):
    """Every pair that shares a shingle is compared, for all rows; the links of the ids divisible by 100 are among them."""
    sets, holders, pairs = shingle_sets(texts), {}, Counter()
    for i, s in sets.items():
        for x in s:
            holders.setdefault(x, []).append(i)
    for own in holders.values():
        for n, a in enumerate(own):
            for b in own[n + 1:]:
                pairs[a, b] += 1
    parent = {i: i for i in sets}

    def root(i):
        while parent[i] != i:
            parent[i] = i = parent[parent[i]]
        return i

    links = [(a, b) for (a, b), both in pairs.items() if 100 * both >= 75 * (len(sets[a]) + len(sets[b]) - both)]
    for a, b in links:
        a, b = sorted((root(a), root(b)))
        parent[b] = a
    got = {r.doc_id: r for r in rows_of(spark, "op9_near_dedup")}
    assert {i: (r.n_shingles, r.component_id, r.kept) for i, r in got.items()} == {i: (len(sets[i]), root(i), root(i) == i) for i in sets}
    asked = [(a, b) for a, b in links if a % 100 == 0 or b % 100 == 0]
    assert sum(got[a].component_id == got[b].component_id for a, b in asked) >= 0.9 * len(asked)


def test_op10_base(spark, texts):
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    want = {}
    for i, t in texts.items():
        w = word.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t))
        at = [(n, label) for phrase, label in license_scan.BASE.items() for k in [len(phrase.split())] for n in range(len(w)) if w[n:n + k] == phrase.split()]
        want[i] = (len(w), len(at), min((n for n, _ in at), default=None), max((n for n, _ in at), default=None), ",".join(sorted({x for _, x in at})))
    got = rows_of(spark, "op10_license_scan")
    assert {r.doc_id: (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) for r in got} == want
    assert all(set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(",")) and 0 <= r.score <= 1 for r in got)
