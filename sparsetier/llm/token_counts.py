"""Token counts: Arrow functions that return lengths only.

Batches given to the tokenizer are balanced by bytes, and long texts are cut where the pre-tokenizer always
starts a new piece: before a single blank or newline with non-blank neighbours. Null or empty text: 0 tokens. Texts
without such a place stay whole, as do all texts where the vocabulary's pre-tokenizer is not the byte-level one. Repeated rows, and rows
with repeated or null doc_ids, give a row each; other input columns are ignored, whatever their names. Very long texts need a
few times their own size.
"""

from __future__ import annotations

import json
import os
import re

import public_tokenizers
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.llm.common import arrow_rows, texts_of

_CUT = re.compile(r"(?<=\S)[ \n](?=\S)")


def safe_pieces(text: str, size: int) -> list[str]:
    """Cut a text into pieces of about ``size`` characters whose token counts add up to that of the whole."""
    pieces, at = [], 0
    while len(text) - at > size:
        cut = _CUT.search(text, at + size)
        if cut is None:
            break
        pieces.append(text[at:cut.start()])
        at = cut.start()
    pieces.append(text[at:])
    return pieces


def token_counts(docs: DataFrame, vocabulary: str, limit: int = 1024, batch_bytes: int = 1 << 20, piece_chars: int = 1 << 14) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) with the tokenizers or sentencepiece file ``vocabulary``."""

    def start():
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        path = public_tokenizers.path(vocabulary)
        if vocabulary.endswith(".model"):
            import sentencepiece

            model = sentencepiece.SentencePieceProcessor(model_file=path)
            lengths = lambda xs: [len(t) for t in model.encode(xs, num_threads=1)]
            cut = lambda text: [text]
        else:
            from tokenizers import Tokenizer

            tok = Tokenizer.from_file(path)
            tok.no_truncation()
            tok.no_padding()
            lengths = lambda xs: [len(e) for e in tok.encode_batch_fast(xs, add_special_tokens=False)]
            first = json.loads(tok.to_str()).get("pre_tokenizer") or {}
            safe = first.get("type") == "ByteLevel" and first.get("use_regex", True) and not first.get("add_prefix_space")
            cut = (lambda text: safe_pieces(text, piece_chars)) if safe else (lambda text: [text])

        def work(cols):
            totals = [0] * len(cols["text"])
            held, owners, weight = [], [], 0

            def drain():
                for owner, n in zip(owners, lengths(held)):
                    totals[owner] += n

            for owner, text in enumerate(cols["text"]):
                for piece in cut(text):
                    held.append(piece)
                    owners.append(owner)
                    weight += len(piece) if piece.isascii() else len(piece.encode("utf-8", "surrogatepass"))
                    if weight >= batch_bytes:
                        drain()
                        held, owners, weight = [], [], 0
            drain()
            yield from zip(cols["doc_id"], totals, cols["n_bytes"])

        return work

    texts = texts_of(docs).withColumn("n_bytes", F.octet_length("text").cast("long"))
    return arrow_rows(texts, "doc_id long, n_tokens long, n_bytes long", start).select(
        "doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
