"""License scan: phrases, and an exact set-similarity join of text blocks with license notices.

A block is a run of consecutive words, wherever lines break and whatever marks stand between: for a notice of n words,
each run of ceil(n · SLACK) words (of the whole text, if it is shorter).
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import per_batch, utf8
from .decontamination import normal_words

# fixed values
PHRASES = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}
NOTICES = {
    "agpl-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "apache-2.0": "Licensed under the Apache License, Version 2.0",
    "apache-2.0-header": "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "apache-2.0-terms": "Subject to the terms and conditions of this License, each Contributor hereby grants to You a perpetual, worldwide, non-exclusive, no-charge, royalty-free, irrevocable copyright license to reproduce, prepare Derivative Works of, publicly display, publicly perform, sublicense, and distribute the Work and such Derivative Works in Source or Object form.",
    "bsd": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "bsd-conditions": "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "bsd-disclaimer": "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS AS IS AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED.",
    "boost": "Distributed under the Boost Software License, Version 1.0.",
    "cc-by-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License",
    "cc-by-nc-4.0": "Licensed under CC BY-NC 4.0",
    "cc-by-sa-4.0": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License",
    "cc0-1.0": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work",
    "gpl-3.0": "This work is licensed under the GNU General Public License, version 3",
    "gpl-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version",
    "gpl-warranty": "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    "isc": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "lgpl-header": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.",
    "mit": "Released under the MIT License",
    "mit-header": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions",
    "mit-warranty": "THE SOFTWARE IS PROVIDED AS IS, WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY",
    "mpl-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at",
    "unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
}
#: Most MB of notices that an index takes; it is sent to every executor.
MAX_NOTICE_MB = 8.0
#: Words of a block to words of the notice: a quarter may be put in between.
SLACK = 1.25
#: Bytes of words that are held as a list at once.
PIECE = 1 << 20


def token_counts(docs: DataFrame, tokens: set[bytes]) -> dict[bytes, int]:
    """In how many documents each token of the notices stands: counted over all documents, one number a token comes back."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        found: Counter = Counter()
        for t in utf8(batch.column(0)):
            found.update(tokens.intersection(normal_words(t or b"").split()))
        return pa.RecordBatch.from_arrays([pa.array([k.decode() for k in found], pa.string()), pa.array(found.values(), pa.int64())], ["token", "n"])

    counted = docs.select("text").mapInArrow(per_batch(run), "token string, n long").groupBy("token").agg(F.sum("n").alias("n"))
    return {r.token.encode(): r.n for r in counted.collect()}


class NoticeIndex:
    """Notices as token sets in an order common to all, the token held by the fewest documents first.

    A block that holds a share of threshold or more of a notice misses fewer of its tokens than its prefix has, so it
    holds one of the prefix: only around prefix tokens blocks are looked at. The length filter asks for as many words as
    the overlap needs. The positional filter: a block whose first shared token stands at a place in the order can share
    no more than what the notice has left from there on.
    """

    def __init__(self, notices: dict[str, str], frequency: dict[bytes, int], threshold: float):
        self.tokens: dict[str, set[bytes]] = {}
        self.need: dict[str, int] = {}
        self.width: dict[str, int] = {}
        self.index: dict[bytes, list[str]] = defaultdict(list)
        for label, text in notices.items():
            words = normal_words(text.encode()).split()
            tokens = sorted(set(words), key=lambda t: (frequency.get(t, 0), t))
            if tokens:
                self.tokens[label], self.need[label], self.width[label] = set(tokens), math.ceil(threshold * len(tokens) - 1e-9), math.ceil(SLACK * len(words))
                # later places of the order cannot come first: len(tokens) - place < need there
                for token in tokens[: len(tokens) - self.need[label] + 1]:
                    self.index[token].append(label)
        self.widest = max(self.width.values(), default=1)

    def matches(self, words: list[bytes]) -> Iterator[tuple[str, int, int, int]]:
        """(label, shared tokens, first word, word after the last) of the best block of each group of blocks that meet."""
        near: dict[str, list[int]] = defaultdict(list)
        for at, word in enumerate(words):
            for label in self.index.get(word, ()):
                near[label].append(at)
        for label, places in near.items():
            width = self.width[label]
            while places:
                last = next((i for i, (a, b) in enumerate(zip(places, places[1:])) if b - a >= width), len(places) - 1)
                a, b = max(0, places[0] - width + 1), min(len(words), places[last] + width)
                places = places[last + 1 :]
                if b - a >= self.need[label] and (found := self.best(label, words, a, b)):
                    yield label, *found

    def best(self, label: str, words: list[bytes], a: int, b: int) -> tuple[int, int, int] | None:
        """Most shared tokens in a block of words[a:b], and where; the first of equal ones."""
        tokens, width = self.tokens[label], self.width[label]
        places = [i for i in range(a, b) if words[i] in tokens]
        held: Counter = Counter()
        most, where, out = self.need[label] - 1, (0, 0), 0
        for i in places:
            held[words[i]] += 1
            while places[out] <= i - width:
                gone = words[places[out]]
                held[gone] -= 1
                if not held[gone]:
                    del held[gone]
                out += 1
            if len(held) > most:
                most, where = len(held), (places[out], i + 1)
        return (most, *where) if where[1] else None


def pieces(normal: bytes, overlap: int) -> Iterator[tuple[int, list[bytes]]]:
    """The words in lists of about PIECE bytes, each with the overlap last words of the one before, and its first word's number."""
    held: list[bytes] = []
    at = number = 0
    while at < len(normal):
        end = normal.find(b" ", at + PIECE) + 1 or len(normal)
        held += normal[at:end].split()
        yield number, held
        number += max(0, len(held) - overlap)
        held, at = held[-overlap:], end


def places(normal: bytes, phrase: str) -> list[int]:
    """Word numbers at which the phrase stands."""
    out, pattern, at, word = [], b" " + phrase.encode() + b" ", -1, 0
    read = 0
    while (at := normal.find(pattern, at + 1)) >= 0:
        word += normal.count(b" ", read, at)
        read = at
        out.append(word)
    return out


def scan_licenses(docs: DataFrame, notices: dict[str, str] | None = None, threshold: float = 0.8) -> DataFrame:
    """doc_id, n_words, the places of the phrases, labels, score and the blocks (first word-last word:label) that hold a notice.

    The join is exact: every block that holds threshold of a notice's distinct words gives its label; of blocks that
    meet, the best is listed. score: the best containment, 1 where a phrase stands, else 0. Two passes over the
    documents, no shuffle but of one count for each token of the notices. Null or empty text: no words, no labels. Long
    texts are read in pieces that overlap by a block. Repeated rows are judged each; other columns are ignored; an empty
    table gives no rows. Ties of two notices give both labels.
    """
    notices = NOTICES if notices is None else notices
    if (size := sum(map(len, notices.values())) / 1e6) > MAX_NOTICE_MB:
        raise ValueError(f"{size:.0f} MB of notices; the index takes {MAX_NOTICE_MB:.0f} MB")
    vocabulary = {t for text in notices.values() for t in normal_words(text.encode()).split()}
    frequency = token_counts(docs, vocabulary)
    made: list[NoticeIndex] = []

    def scan(text: bytes) -> tuple:
        index = made[0]
        normal = normal_words(text)
        base = {label: at for phrase, label in PHRASES.items() if (at := places(normal, phrase))}
        starts = [x for at in base.values() for x in at]
        labels, score, blocks = set(base), float(bool(base)), set()
        for number, words in pieces(normal, index.widest):
            for label, shared, a, b in index.matches(words):
                labels.add(label)
                score = max(score, shared / len(index.tokens[label]))
                blocks.add((number + a, number + b - 1, label))
        join = lambda x: ",".join(sorted(x))
        return max(0, normal.count(b" ") - 1), len(starts), min(starts, default=None), max(starts, default=None), join(base), join(labels), score, [f"{a}-{b}:{x}" for a, b, x in sorted(blocks)]

    kinds = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.float64(), pa.list_(pa.string())]
    names = ["n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "blocks"]

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        if not made:
            made.append(NoticeIndex(notices, frequency, threshold))
        rows = [scan(t or b"") for t in utf8(batch.column(1))]
        cols = zip(*rows) if rows else [[]] * len(names)
        return pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds))], ["doc_id", *names])

    d = docs.select("doc_id", "text")
    return d.mapInArrow(per_batch(run), f"doc_id {d.schema['doc_id'].dataType.simpleString()}, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, blocks array<string>")
