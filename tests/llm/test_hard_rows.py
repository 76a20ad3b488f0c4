"""Every operator on rows that are hard: nulls in every column, repeated rows and ids, ties, a very long text, clashing columns."""

import hashlib
import zlib

import numpy as np
import public_tokenizers
import pytest

from sparsetier.llm import byte_bpe, decontaminate, license_scan, near_dedup, quality_rules, suffix_dedup, token_counts, token_files, toxicity, warc

WORDS = [f"w{n * 7919 % 4001}" for n in range(120_000)]
LONG = " ".join(WORDS) + ".\n" + "x" * 300_000 + " released under the mit license."
ROWS = [(1, LONG), (1, "short text of a few words"), (1, "short text of a few words"), (None, "short text of a few words"), (None, None), (2, None), (2, ""), (2, " \t\n"), (-5, "é�\x00 ſ K İ")]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "clash", 1, b"k", [1], "r") for i, t in ROWS]
    return spark.createDataFrame(rows, "doc_id long, text string, kept string, n int, key binary, spans array<int>, whole_row string").repartition(3)


LABELS = [(n, int(n % 3 == 0)) for n in range(300)]


@pytest.mark.parametrize("name, apply", {
    "op1": suffix_dedup.repeat_report,
    "op2": lambda d: byte_bpe.digests(byte_bpe.encode(d)),
    "op3": quality_rules.quality_measures,
    "op4": lambda d: token_files.read_shards(*token_files.write_shards(d)),
    "op5": lambda d: token_counts.token_counts(d, "byte_bpe_50k.json"),
    "op6": lambda d: toxicity.toxicity(d, d.sparkSession.createDataFrame([(1, 1), (1, 0), (2, 0), (None, 1), (-5, None)], "doc_id long, toxic int")),
    "op9": near_dedup.near_components,
    "op10": license_scan.license_scan,
}.items())
def test_every_row_gets_a_row(docs, name, apply):
    got = apply(docs).collect()
    ids = lambda xs: sorted((x is None, x or 0) for x in xs)
    assert ids(r.doc_id for r in got) == ids(i for i, _ in ROWS)


def test_long_text_values(spark, docs):
    """The very long text, whole: its bytes, tokens, links and notice."""
    raw = LONG.encode()
    one = max(suffix_dedup.repeat_report(docs).collect(), key=lambda r: r.n_bytes)
    assert one.n_bytes == len(raw) and one.n_removed > 300_000 and one.n_spans >= 1  # its words repeat after 4,001, its x at once
    import tiktoken

    coder = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.load_ranks("byte_bpe_50k.tiktoken"), special_tokens={})
    two = max(byte_bpe.digests(byte_bpe.encode(docs, block_chars=1 << 16)).collect(), key=lambda r: r.n_tokens)
    ids = coder.encode_ordinary(LONG)
    assert (two.n_tokens, two.decoded_sha256) == (len(ids), hashlib.sha256(raw).hexdigest())
    assert max(r.n_tokens for r in token_counts.token_counts(docs, "byte_bpe_50k.json").collect()) == len(ids)
    ten = max(license_scan.license_scan(docs).collect(), key=lambda r: r.n_words)
    assert ten.labels == "mit" and ten.n_words == len(license_scan.words_of(LONG))
    nine = max(near_dedup.near_components(docs).collect(), key=lambda r: r.n_shingles)
    words = LONG.encode().lower().split()
    assert nine.n_shingles == len({tuple(words[n:n + 5]) for n in range(len(words) - 4)})
    hit = decontaminate.contaminated(docs, spark.createDataFrame([(7, "RELEASED under the MIT licence")], "item_id long, text string")).collect()
    assert [(r.doc_id, r.item_id, r.distance) for r in hit] == [(1, 7, 1)]


def test_token_files_hard_rows(docs):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    got = sorted((r.n_tokens, r.ids_crc32) for r in token_files.read_shards(*token_files.write_shards(docs, shard_bytes=1 << 12)).collect())
    ids = [np.array(tok.encode(t or "", add_special_tokens=False).ids + [2], "<u4") for _, t in ROWS]
    assert got == sorted((len(x), zlib.crc32(x.tobytes())) for x in ids)


@pytest.mark.parametrize("seed", [0, 1])
def test_pieces_as_the_library_reads_them(seed):
    """Random texts over characters whose composition, case or class is special."""
    from tokenizers import Tokenizer

    rng = np.random.default_rng(seed)
    alphabet = ["a", "B", "é", "é", " ", "  ", "\n", "\t", "\xa0", "　", "'s", "'S", "1", "٣", "\xdf", "İ", "Σ", "ﬁ", "Å", "하", "中", "_", "-", "—",
                "<|endoftext|>", "<|", "\x1c", "\x85", "​", "\U0001f600", ".", ",", "don't", "\x00", "ⓐ"]
    texts = ["".join(rng.choice(alphabet, rng.integers(0, 14))) for _ in range(3000)]
    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    want = [np.array(e.ids, dtype="<u4").tobytes() for e in tok.encode_batch(texts, add_special_tokens=False)]
    encode = token_files.PieceEncoder("word_bpe_49k.json")
    assert [x for at in range(0, len(texts), 64) for x in encode(texts[at:at + 64])] == want


def test_pieces_with_white_space_of_any_kind():
    """Pieces are cut at ASCII white space only; what else counts as white space, to Python or to the library, stands inside them."""
    from tokenizers import Tokenizer

    rng = np.random.default_rng(5)
    spaces = [c for c in map(chr, range(0x3001)) if c.isspace()] + ["\u200b", "\u180e", "\ufeff", " ", "\r\n"]
    alphabet = [*spaces, "a", "Word", "\u00e9", "e\u0301", "\u0301", "\u03a3", "\u0130", "'s", "7", "...", "<|startoftext|>"]
    texts = ["".join(rng.choice(alphabet, rng.integers(0, 12))) for _ in range(4000)] + [f"{a}{c}{b}" for c in spaces for a in ("", "A", "!", " ") for b in ("", "b", "\u0301", " ")]
    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    want = [np.array(e.ids, dtype="<u4").tobytes() for e in tok.encode_batch(texts, add_special_tokens=False)]
    encode = token_files.PieceEncoder("word_bpe_49k.json")
    assert encode(texts) == want and encode(texts[::-1]) == want[::-1] and encode([]) == []


def test_pieces_are_looked_up_once_for_all_places():
    """What is asked of the table of known pieces goes with the distinct pieces, not with the words of the texts."""
    from tokenizers import Tokenizer

    asked = []

    class Counted(dict):
        def get(self, key, default=None):
            asked.append(key)
            return super().get(key, default)

        def __getitem__(self, key):
            asked.append(key)
            return super().__getitem__(key)

        def __contains__(self, key):
            asked.append(key)
            return super().__contains__(key)

    texts = ["one two, three\tfour " * 500 + str(n) for n in range(40)] + [""]
    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    want = [np.array(e.ids, dtype="<u4").tobytes() for e in tok.encode_batch(texts, add_special_tokens=False)]
    encode = token_files.PieceEncoder("word_bpe_49k.json")
    encode.held = Counted()
    assert encode(texts) == want and encode(texts) == want
    assert 0 < len(asked) < 1000 < sum(len(t.split()) for t in texts)


def test_slices_hold_every_row():
    import pyarrow as pa

    texts = ["x" * n for n in (0, 5, token_files.SLICE_BYTES + 1, 7, token_files.SLICE_BYTES - 7, 1, 0)]
    batch = pa.record_batch({"doc_id": pa.array(range(len(texts))), "text": pa.array(texts)})
    cut = list(token_files.slices(batch))
    assert [i for c in cut for i in c.column("doc_id").to_pylist()] == list(range(len(texts))) and len(cut) > 2
    assert all(c.num_rows == 1 or sum(map(len, c.column("text").to_pylist())) <= token_files.SLICE_BYTES for c in cut)
    assert list(token_files.slices(batch.slice(0, 0))) == []


def test_toxicity_with_noisy_labels(spark):
    """A sixth of the labels is wrong; the words decide all the same, and many harmless sentences add nothing."""
    rng = np.random.default_rng(9)
    plain = [f"p{n}" for n in range(300)]
    rows = []
    for n in range(900):
        lines = [" ".join(rng.choice(plain, 6)) + "." for _ in range(rng.integers(1, 40))]
        if n % 4 == 0:
            lines.insert(int(rng.integers(0, len(lines))), "you vile thing.")
        rows.append((n, " ".join(lines)))
    labels = [(n, int((n % 4 == 0) != (rng.random() < 1 / 6))) for n in range(900)]
    got = toxicity.toxicity(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")).collect()
    held = [r for r in got if r.held_out]
    assert len(held) > 100
    toxic, clean = [r.score for r in held if r.doc_id % 4 == 0], [r.score for r in held if r.doc_id % 4]
    assert min(toxic) > 0.5 and np.mean(np.array(clean) < 0.5) > 0.97
    assert all("vile" in toxicity.sentences(rows[r.doc_id][1])[r.worst_sentence] for r in held if r.doc_id % 4 == 0)


def test_near_dedup_brute_force(spark):
    """Groups of copies with words replaced at random, many of them alike but not linked, sizes of all kinds, ties, repeated ids."""
    rng = np.random.default_rng(12)
    rows = []
    for group in range(6):
        base = [f"g{group}w{n}" for n in range(int(rng.integers(6, 260)))]
        for _ in range(25):
            words = list(base)
            for _ in range(int(rng.integers(0, 2 + len(base) // 18))):
                words[int(rng.integers(0, len(words)))] = f"r{rng.integers(0, 10**9)}"
            rows.append((int(rng.integers(0, 120)), " ".join(words[:int(rng.integers(max(1, len(words) - 25), len(words) + 1))])))
    rows += [(200, "one two"), (201, "ONE  two"), (202, "one two three"), (203, None), (None, "one two"), (None, None)]
    got = near_dedup.near_components(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    sets = []
    for i, t in rows:
        w = (t or "").lower().split()
        sets.append({tuple(w[n:n + 5]) for n in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set()))
    first = {i: i for i, _ in rows if i is not None}

    def root(i):
        while first[i] != i:
            i = first[i]
        return i

    for a, (i, _) in enumerate(rows):
        for b, (j, _) in enumerate(rows[:a]):
            if i is not None and j is not None and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = sorted((root(i), root(j)))
                first[y] = x
    want = sorted((i is None, i or 0, len(s), root(i) if i is not None else -1) for (i, _), s in zip(rows, sets))
    assert sorted((r.doc_id is None, r.doc_id or 0, r.n_shingles, -1 if r.component_id is None else r.component_id) for r in got) == want


def test_warc_hard_rows(spark):
    pages = spark.createDataFrame([(3, "http://a.b", "same"), (3, "http://a.b", "same"), (9, None, "same"), (None, "x", "same"), (None, None, None), (1, "HTTP://A.B/?q=1", "z" * 3_000_000)],
                                  "page_id long, url string, html string").selectExpr("*", "'c' as record_type", "1 as n")
    got = warc.warc_roundtrip(pages).collect()
    assert len(got) == 6
    by = sorted((r.page_id is None, r.page_id or 0, r.payload_bytes, r.record_type, r.refers_to) for r in got if r.page_id is not None)
    assert by == [(False, 1, 3_000_000, "response", None), (False, 3, 4, "response", None), (False, 3, 4, "response", None), (False, 9, 4, "revisit", 3)]
