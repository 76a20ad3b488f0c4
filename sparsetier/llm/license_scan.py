"""License scans through a positional rare-token index.

The index holds the postings (template, position) of every word of the licence templates, and how rare each of these words is over all
documents. For each text its licence words are looked up, rarest first; their postings vote for a relative position of
a template. A template whose best position gathers ``LEAST_WORDS`` different words gets its label when all of its mandatory
key phrases stand in the text. The score is the share of the template's weight (inverse document frequency) at that position, 1 for
base phrases. Base phrases are searched in every text.

Null or empty text: no words, empty labels, score 0. Rows are scanned one by one: repeated rows and ids, and rows without doc_id, give
repeated results. Ties between positions go to the earlier one. Whole texts are scanned, however long, in time in proportion to
their words. Other input columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import defaultdict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.llm.common import arrow_rows, texts_of

LEAST_WORDS = 4
#: Phrases and labels of the contract.
BASE = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

#: Fixed values: (label, words of a notice as it stands in files, mandatory key phrases).
TEMPLATES = [
    ("mit", "released under the mit license", ["mit license"]),
    ("mit", "licensed under the mit license see license file in the project root for license information", ["mit license"]),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction "
            "including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software", ["permission is hereby granted free of charge", "sublicense"]),
    ("apache-2.0", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at", ["apache license"]),
    ("apache-2.0", "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied "
                   "see the license for the specific language governing permissions and limitations under the license", ["governing permissions and limitations"]),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met "
            "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer", ["redistribution and use in source and binary forms"]),
    ("bsd", "released under the bsd license", ["bsd license"]),
    ("gpl", "this work is licensed under the gnu general public license version 3", ["general public license"]),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation "
            "either version 3 of the license or at your option any later version", ["gnu general public license", "free software"]),
    ("lgpl", "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation", ["lesser general public license"]),
    ("agpl", "under the terms of the gnu affero general public license as published by the free software foundation", ["affero general public license"]),
    ("cc-by", "this work is licensed under a creative commons attribution 4 0 international license", ["creative commons attribution"]),
    ("cc-by-nc", "licensed under cc by nc 4 0", ["cc by nc"]),
    ("cc-by-sa", "licensed under cc by sa 4 0", ["cc by sa"]),
    ("cc0", "to the extent possible under law the author has waived all copyright and related or neighboring rights to this work", ["waived all copyright"]),
    ("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at", ["mozilla public license"]),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
     ["permission to use copy modify", "with or without fee"]),
    ("bsl-1.0", "distributed under the boost software license version 1 0", ["boost software license"]),
    ("unlicense", "this is free and unencumbered software released into the public domain", ["unencumbered software"]),
    ("epl-2.0", "this program and the accompanying materials are made available under the terms of the eclipse public license 2 0", ["eclipse public license"]),
]
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_LOWER = {c: c + 32 for c in range(65, 91)}


def words_of(text: str) -> list[str]:
    return _WORD.findall(text.translate(_LOWER))


class Index:
    """Postings of the templates' words, and weights from ``rarity``: word -> number of documents that hold it."""

    def __init__(self, templates=TEMPLATES, rarity: dict[str, int] | None = None, n_docs: int = 0):
        self.templates = [(label, text.split(), [p.split() for p in phrases]) for label, text, phrases in templates]
        self.postings = defaultdict(list)
        for n, (_, words, _) in enumerate(self.templates):
            for at, word in enumerate(words):
                self.postings[word].append((n, at))
        self.base = [(p.split(), label) for p, label in BASE.items()]
        self.wanted = set(self.postings).union(*(p for _, _, ps in self.templates for p in ps), *(p for p, _ in self.base))
        rarity = rarity or {}
        self.weight = {w: math.log((n_docs + 1) / (rarity.get(w, 0) + 1)) + 1 for w in self.wanted}
        self.total = [sum(self.weight[w] for w in set(words)) for _, words, _ in self.templates]

    def scan(self, text: str):
        """(number of words, places of base phrases, base labels, labels, score)."""
        words = words_of(text)
        here = self.wanted.intersection(words)
        spots = defaultdict(list)
        if here:
            for at, word in enumerate(words):
                if word in here:
                    spots[word].append(at)

        def places(phrase):
            k = len(phrase)
            return [at for at in spots[phrase[0]] if words[at:at + k] == phrase] if here.issuperset(phrase) else []

        starts, base = [], set()
        for phrase, label in self.base:
            if found := places(phrase):
                starts += found
                base.add(label)
        labels, score = set(base), 1.0 if base else 0.0
        open_ = [n for n, (_, own, phrases) in enumerate(self.templates) if len(here.intersection(own)) >= min(LEAST_WORDS, len(set(own))) and all(places(p) for p in phrases)]
        if open_:
            votes = {n: defaultdict(set) for n in open_}
            for word in sorted(here, key=lambda w: (-self.weight[w], w)):
                for n, place in self.postings.get(word, ()):
                    if n in votes:
                        for at in spots[word]:
                            votes[n][at - place].add(word)
            for n in open_:
                label, own, _ = self.templates[n]
                place = max(votes[n], key=lambda p: (sum(self.weight[w] for w in votes[n][p]), -p))
                got = votes[n][place]
                if len(got) >= min(LEAST_WORDS, len(set(own))):
                    labels.add(label)
                    score = max(score, min(1.0, sum(self.weight[w] for w in got) / self.total[n]))
        return len(words), starts, base, labels, score


def word_rarity(texts: DataFrame, wanted: set[str]) -> tuple[dict[str, int], int]:
    """Documents per licence word, over all documents, and their number: at most one row per word of the templates."""

    def run(batches):
        import pyarrow as pa

        seen, n = dict.fromkeys(wanted, 0), 0
        for batch in batches:
            for text in batch.column("text").to_pylist():
                n += 1
                for word in wanted.intersection(words_of(text)):
                    seen[word] += 1
        yield pa.RecordBatch.from_arrays([pa.array([*seen, None], pa.string()), pa.array([*seen.values(), n], pa.int64())], names=["word", "n"])

    rows = texts.select("text").mapInArrow(run, "word string, n long").groupBy("word").agg(F.sum("n").alias("n")).collect()
    found = {r.word: r.n for r in rows}
    return found, found.pop(None, 0)


def license_scan(docs: DataFrame) -> DataFrame:
    """(doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score)."""
    texts = texts_of(docs)
    rarity, n_docs = word_rarity(texts, Index().wanted)

    def start():
        index = Index(TEMPLATES, rarity, n_docs)

        def work(cols):
            for doc_id, text in zip(cols["doc_id"], cols["text"]):
                n, starts, base, labels, score = index.scan(text)
                yield (doc_id, n, len(starts), min(starts, default=None), max(starts, default=None),
                       ",".join(sorted(base)), ",".join(sorted(labels)), score)

        return work

    return arrow_rows(texts, "doc_id long, n_words long, n_base long, first_word long, last_word long, "
                      "base_labels string, labels string, score double", start)
