"""Toxicity by multiple-instance learning: a document is a bag of sentences.

A sentence's intensity is the sum of the weights (none negative) of its distinct words and its probability 1 - exp(-intensity), so a
sentence without any weighted word adds nothing, however many there are. The document's score is the noisy-or of its sentences and
of a leak that stands for labels without a cause in the text. Weights and leak are fitted on document labels alone by
expectation-maximization: a positive document's label is dealt among the words that can have caused it; a word keeps a weight
only if more than ``penalty`` documents' worth of labels fall to it. The penalty is chosen by cross-validation on the training rows.
The sentence probabilities then point at the offending sentences.

Training takes at most ``sample`` labelled documents (smallest hash of doc_id) outside the held-out
fold, crc32(doc_id as text) mod 5 = 0; every document is scored on its whole text. No usable label, or one class only:
all scores are the base rate. Null or empty text: one sentence without words. A null doc_id is never in the training rows and
not held out. Repeated labels of one document count once (toxic if any is); rows that repeat a doc_id are scored one by one, and the
first text in order is the one learned from. Other input columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.llm.common import arrow_rows, texts_of

SAMPLE, PENALTIES, FOLDS, LEAST_DOCS = 4000, (1.0, 3.0, 8.0, 20.0), 3, 5
_SENTENCE = re.compile(r"[.!?\n]+")
_WORD = re.compile(r"[^\W\d_]+")


def sentences(text: str) -> list[str]:
    return [s for s in _SENTENCE.split(text) if s.strip()] or [""]


def _held_out():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False))


def _counts(rows: list[tuple[str, int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[str], np.ndarray]:
    """(document, word, number of its sentences with the word) as three arrays, the words, and the labels."""
    number: dict[str, int] = {}
    doc, word, times = [], [], []
    for d, (text, _) in enumerate(rows):
        own = Counter(w for s in sentences(text) for w in set(_WORD.findall(s.lower())))
        doc.extend([d] * len(own))
        word.extend(number.setdefault(w, len(number)) for w in own)
        times.extend(own.values())
    return np.array(doc, dtype=np.int64), np.array(word, dtype=np.int64), np.array(times, dtype=float), list(number), np.array([y for _, y in rows], dtype=float)


def _maximize(doc, word, times, n_words, y, penalty: float, steps: int = 80):
    """(weights, leak) by expectation-maximization."""
    # words that stand in few documents, or no more often in positive ones than others do, would end with no weight
    seen, good = np.bincount(word, minlength=n_words), np.bincount(word, y[doc], n_words)
    use = ((seen >= LEAST_DOCS) & (good > penalty) & (good > 2 * y.mean() * seen))[word]
    doc, word, times = doc[use], word[use], times[use]
    exposure = np.bincount(word, times, n_words) + 1.0
    theta, leak = np.bincount(word, y[doc] * times, n_words) / exposure, max(1e-6, y.mean())
    for _ in range(steps):
        x = np.bincount(doc, theta[word] * times, len(y)) + leak
        blame = y / -np.expm1(-x)  # labels per unit of intensity
        theta = np.maximum(0.0, theta * np.bincount(word, times * blame[doc], n_words) - penalty) / exposure
        leak = max(1e-6, leak * blame.sum() / len(y))
    return theta, leak


def fit(rows: list[tuple[str, int]]):
    """(weights by word, leak) from (text, label) rows."""
    base = (sum(y for _, y in rows) + 0.5) / (len(rows) + 1)
    if not rows or len({y for _, y in rows}) < 2:
        return {}, float(-np.log1p(-base))
    doc, word, times, words, y = _counts(rows)
    fold, loss = np.arange(len(rows)) % FOLDS, []
    for penalty in PENALTIES:
        total = 0.0
        for f in range(FOLDS):
            own = fold[doc] != f
            theta, leak = _maximize(doc[own], word[own], times[own], len(words), np.where(fold != f, y, 0.0), penalty)
            leak *= FOLDS / (FOLDS - 1)  # the fold's rows stood there without labels
            x = np.clip(np.bincount(doc, theta[word] * times, len(y)) + leak, 1e-6, 30)[fold == f]
            total += np.where(y[fold == f] > 0, -np.log(-np.expm1(-x)), x).sum()
        loss.append(total)
    theta, leak = _maximize(doc, word, times, len(words), y, PENALTIES[int(np.argmin(loss))])
    return {words[k]: float(theta[k]) for k in np.flatnonzero(theta)}, float(leak)


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE):
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), "toxic").where("doc_id is not null and toxic is not null").where(~_held_out())
    chosen = known.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    rows = texts_of(docs).join(F.broadcast(chosen), "doc_id").collect()
    once = {r.doc_id: (r.text, int(r.toxic)) for r in sorted(rows, key=lambda r: (r.doc_id, r.text))}
    return fit([once[k] for k in sorted(once)])


def sentence_scores(text: str, weights: dict[str, float]) -> list[float]:
    return [-math.expm1(-sum(weights.get(w, 0.0) for w in set(_WORD.findall(s.lower())))) for s in sentences(text)]


def toxicity(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, threshold: float = 0.5) -> DataFrame:
    """(doc_id, held_out, score, predicted, worst_sentence, offending): the place of the sentence with the highest probability
    and the number of sentences at or over the threshold."""
    weights, leak = train(docs, labels, sample)
    shared = docs.sparkSession.sparkContext.broadcast((weights, leak))  # at most the sample's vocabulary

    def start():
        weights, leak = shared.value
        base = -math.expm1(-leak)

        def work(cols):
            for doc_id, held, text in zip(cols["doc_id"], cols["held_out"], cols["text"]):
                if weights.keys().isdisjoint(_WORD.findall(text.lower())):
                    yield doc_id, held, base, int(base >= threshold), 0, 0
                    continue
                p = sentence_scores(text, weights)
                none = math.exp(-leak)
                for chance in p:
                    none *= 1 - chance
                yield doc_id, held, 1 - none, int(1 - none >= threshold), max(range(len(p)), key=p.__getitem__), sum(chance >= threshold for chance in p)

        return work

    rows = texts_of(docs).withColumn("held_out", _held_out())
    return arrow_rows(rows, "doc_id long, held_out boolean, score double, predicted int, worst_sentence int, offending int", start)
