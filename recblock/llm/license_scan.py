"""License scans by a positional index of rare words.

The templates' words are an index from word to (template, place). The words of a document
that the index knows are weighed by inverse document frequency over all documents; for each
template every place of its key phrase's rarest word gives an offset at which the template
would stand, and each is verified: the key phrase must stand there word by word. The score is
the share of the template's weight that stands at its place.

Nulls and texts without words have no places, no labels and score 0. Repeated rows are
scanned each for itself; an empty table gives no rows; other columns are not looked at."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from recblock.llm import textkernel as K

#: Base phrases and their labels.
PHRASES = (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl"))
#: Label, key phrase, notice (public licence notices in lower-case words).
TEMPLATES = (
    ("mit-text", "hereby granted free of charge", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software"),
    ("apache-2.0", "apache license version 2 0", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0 unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied"),
    ("gpl-3.0", "general public license version 3", "licensed under the gnu general public license version 3"),
    ("gpl-notice", "under the terms of the gnu general public license", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version"),
    ("lgpl", "lesser general public license", "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation"),
    ("agpl", "affero general public license", "you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation"),
    ("cc-by-nc-4.0", "cc by nc 4 0", "licensed under cc by nc 4 0"),
    ("cc-by-sa-4.0", "cc by sa 4 0", "licensed under cc by sa 4 0"),
    ("cc-by-4.0", "cc by 4 0", "licensed under cc by 4 0"),
    ("cc-by-text", "creative commons attribution", "this work is licensed under a creative commons attribution 4 0 international license"),
    ("cc0", "waived all copyright and related or neighboring rights", "to the extent possible under law the author has waived all copyright and related or neighboring rights to this work"),
    ("bsd", "redistribution and use in source and binary forms", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution"),
    ("mpl-2.0", "mozilla public license", "this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at"),
    ("epl", "eclipse public license", "this program and the accompanying materials are made available under the terms of the eclipse public license"),
    ("isc", "with or without fee is hereby granted", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies"),
    ("zlib", "this software is provided as is without any express or implied warranty", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely"),
    ("boost-1.0", "boost software license version 1 0", "distributed under the boost software license version 1 0"),
    ("unlicense", "free and unencumbered software released into the public domain", "this is free and unencumbered software released into the public domain anyone is free to copy modify publish use compile sell or distribute this software"),
)
BREAKS = np.ones(256, bool)
BREAKS[[*range(0x30, 0x3A), *range(0x61, 0x7B), *range(0x80, 0x100)]] = False


def _hashes(words: list[str]) -> np.ndarray:
    data = np.frombuffer("".join(words).encode(), np.uint8)
    offs = np.append(0, np.cumsum([len(w.encode()) for w in words]))
    return K.span_hash(K.prefix_hash(data), offs[:-1], offs[1:])


class Index:
    def __init__(self, templates: tuple = TEMPLATES, phrases: tuple = PHRASES):
        self.templates = [(label, key.split(), notice.split()) for label, key, notice in templates]
        for label, key, notice in self.templates:
            if self._place(key, notice) is None:
                raise ValueError(f"the key phrase of {label} is not in its notice")
        self.phrases = [(p.split(), label) for p, label in phrases]
        self.words = sorted({w for _, _, n in self.templates for w in n} | {w for p, _ in self.phrases for w in p})
        h = _hashes(self.words)
        self.order = np.argsort(h)
        self.hashes = h[self.order]
        self.number = {w: i for i, w in enumerate(self.words)}
        self.coded = [(label, np.array([self.number[w] for w in key]), self._place(key, notice), np.array([self.number[w] for w in notice])) for label, key, notice in self.templates]

    @staticmethod
    def _place(key: list[str], notice: list[str]) -> int | None:
        return next((i for i in range(len(notice) - len(key) + 1) if notice[i : i + len(key)] == key), None)

    def coded_words(self, data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Number of each word in the index, -1 if it has none, and the words' texts."""
        data = K.LOWER[data]
        start, end, doc = K.words(data, offs, BREAKS)
        if not len(start):
            return np.zeros(0, np.int64), doc
        h = K.span_hash(K.prefix_hash(data), start, end)
        at = np.minimum(np.searchsorted(self.hashes, h), len(self.hashes) - 1)
        return np.where(self.hashes[at] == h, self.order[at], -1), doc

    def verified(self, words: np.ndarray, idf: np.ndarray) -> tuple[set[str], float]:
        """Labels and best score of one document's coded words."""
        labels, best = set(), 0.0
        present = set(words[words >= 0].tolist())
        for label, key, key_at, notice in self.coded:
            if not present.issuperset(key.tolist()):
                continue
            rarest = max(range(len(key)), key=lambda i: (idf[key[i]], key[i]))
            places = np.flatnonzero(words == key[rarest]) - rarest
            places = places[(places >= 0) & (places + len(key) <= len(words))]
            for i, w in enumerate(key):
                places = places[words[places + i] == w]
            for s in (places - key_at).tolist():
                lo, hi = max(s, 0), min(s + len(notice), len(words))
                right = words[lo:hi] == notice[lo - s : hi - s]
                labels.add(label)
                best = max(best, float(idf[notice[lo - s : hi - s]][right].sum() / idf[notice].sum()))
        return labels, best


def document_frequencies(docs: DataFrame, index: Index) -> tuple[np.ndarray, int]:
    """In how many documents each of the index's words stands, and how many documents there are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros(len(index.words) + 1, np.int64), 0
        for batch in batches:
            for a, b, data, offs in K.chunks(batch.column(0)):
                words, doc = index.coded_words(data, offs)
                own = np.unique(doc[words >= 0] * len(index.words) + words[words >= 0])
                total[:-1] += np.bincount(own % len(index.words), minlength=len(index.words))
                n += b - a
        total[-1] = n
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total), dtype=np.int32)), pa.array(total)], ["w", "n"])

    counts = np.zeros(len(index.words) + 1, np.int64)
    for w, n in docs.select(F.col("text").cast("string").alias("text")).mapInArrow(run, "w int, n long").groupBy("w").agg(F.sum("n")).collect():  # one row per word of the index
        counts[w] = n
    return counts[:-1], int(counts[-1])


def scan(docs: DataFrame, index: Index | None = None) -> DataFrame:
    """``docs(doc_id, text)`` to n_words, base places, labels and score."""
    index = index or Index()
    df, n_docs = document_frequencies(docs, index)
    idf = np.log((n_docs + 1) / (df + 1)) + 1e-9
    kind = docs.schema["doc_id"].dataType.simpleString()
    must = np.zeros(len(index.words) + 1, bool)  # a template's rarest key word: without it there is nothing to verify
    must[[max(key.tolist(), key=lambda w: (idf[w], w)) for _, key, _, _ in index.coded]] = True
    phrases = [(np.array([index.number[w] for w in p]), label) for p, label in index.phrases]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, data, offs in K.chunks(batch.column(1)):
                n = b - a
                words, doc = index.coded_words(data, offs)
                size = np.bincount(doc, minlength=n)
                first = np.append(0, np.cumsum(size))
                base, low, high = np.zeros(n, np.int64), np.full(n, np.iinfo(np.int64).max), np.full(n, -1)
                labels: list[set[str]] = [set() for _ in range(n)]
                for codes, label in phrases:
                    m = len(words) - len(codes) + 1
                    if m <= 0:
                        continue
                    hit = doc[:m] == doc[len(codes) - 1 :]
                    for i, c in enumerate(codes):
                        hit = hit & (words[i : m + i] == c)
                    at = np.flatnonzero(hit)
                    own = doc[at]
                    base += np.bincount(own, minlength=n)
                    np.minimum.at(low, own, at - first[own])
                    np.maximum.at(high, own, at - first[own])
                    for d in np.unique(own).tolist():
                        labels[d].add(label)
                of_base = [",".join(sorted(x)) for x in labels]
                score = (base > 0).astype(float)
                for d in np.unique(doc[must[words]]).tolist():
                    more, best = index.verified(words[first[d] : first[d + 1]], idf)
                    labels[d] |= more
                    score[d] = max(score[d], min(best, 1.0))
                none = base == 0
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(a, n), pa.array(size.astype(np.int64)), pa.array(base), pa.array(low, mask=none), pa.array(high.astype(np.int64), mask=none), pa.array(of_base), pa.array([",".join(sorted(x)) for x in labels]), pa.array(score)],
                    ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score"],
                )

    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(run, f"doc_id {kind}, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double")


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
