"""License scans: base phrases, and an exact containment join of text blocks with templates.

Blocks are the lines of a text, its paragraphs (lines up to an empty one) and each two
paragraphs in a row, so that a notice may span an empty line; blocks and templates count as
sets of words. A template T, however short, is found in a block B if
|B & T| >= threshold * |T|; short templates of common words are therefore best left to phrases. The join is exact and skips most work by filters over one
global order of tokens, rarest in the corpus first: of T only a prefix of
|T| - required + 1 tokens is indexed (a block without any of them can't reach the
required overlap), blocks with fewer tokens than required are dropped by length, and a
candidate ends as soon as the tokens after its match position can't make up the rest.
Frequencies are counted over all documents; templates are a short parameter list, so what
travels to the tasks doesn't grow with the corpus.

Null text counts as empty: no words, no labels, score 0. Repeated rows and extra columns
don't matter. With an empty table the result is empty.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows

PHRASES = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}

#: Notices as projects print them; public texts.
TEMPLATES = (
    ("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software"),
    ("isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("bsd", "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."),
    ("apache", "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied."),
    ("gpl", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation"),
    ("lgpl", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation"),
    ("mpl", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at"),
    ("cc-by", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("cc-by-sa", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("cc0", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."),
    ("unlicense", "This is free and unencumbered software released into the public domain."),
)

_SEPARATORS = bytes([*range(0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)])
#: A-Z become a-z before anything else, so those two don't separate.
_WORDS = bytes(c + 32 if 0x41 <= c <= 0x5A else 0x20 if c in _SEPARATORS else c for c in range(256))
_LINES = bytes(0x0A if c == 0x0A else _WORDS[c] for c in range(256))
_FOUND = re.compile(b"(?<![^ ])(?:" + b"|".join(re.escape(p.encode()) for p in PHRASES) + b")(?![^ ])")


def word_list(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(_WORDS).split()


class Templates:
    """Templates ready to be matched under one token order."""

    def __init__(self, templates, frequency: dict[bytes, int], threshold: float):
        self.rank = {t: i for i, t in enumerate(sorted({w for _, text in templates for w in word_list(text)}, key=lambda w: (frequency.get(w, 0), w)))}
        self.sets, self.index = [], {}
        for label, text in templates:
            own = sorted({self.rank[w] for w in word_list(text)})
            need = max(1, math.ceil(threshold * len(own) - 1e-9))
            for at, token in enumerate(own[: len(own) - need + 1]):
                self.index.setdefault(token, []).append((len(self.sets), at))
            self.sets.append((label, frozenset(own), need))
        words = {i: w for w, i in self.rank.items()}
        self.first = frozenset(words[t] for t in self.index)

    def matches(self, block: list[bytes]) -> dict[str, float]:
        """label -> containment of its best template that reaches the threshold."""
        distinct = set(block)
        if self.first.isdisjoint(distinct):
            return {}
        own = sorted(self.rank[w] for w in distinct if w in self.rank)
        seen: Counter = Counter()
        for i, token in enumerate(own):
            for t, at in self.index.get(token, ()):
                _, tokens, need = self.sets[t]
                if len(distinct) >= need and seen[t] >= 0:
                    seen[t] = seen[t] + 1 if seen[t] + min(len(own) - i, len(tokens) - at) >= need else -1
        found: dict[str, float] = {}
        for t, n in seen.items():
            label, tokens, need = self.sets[t]
            if n > 0 and (both := len(tokens.intersection(own))) >= need:
                found[label] = max(found.get(label, 0.0), both / len(tokens))
        return found


def blocks(text: str | None) -> Iterator[list[bytes]]:
    """Words of each line, of each paragraph of several lines, and of each two paragraphs in a row."""
    paragraph: list[bytes] = []
    before: list[bytes] = []
    held = 0
    for line in [*(text or "").encode("utf-8", "surrogatepass").translate(_LINES).split(b"\n"), b""]:
        words = line.split()
        if words:
            yield words
            paragraph += words
            held += 1
        elif held:
            if held > 1:
                yield paragraph
            if before:
                yield before + paragraph
            before, paragraph, held = paragraph, [], 0


def token_frequencies(docs: DataFrame, templates=TEMPLATES) -> dict[bytes, int]:
    """In how many documents each template token occurs; one row per template token reaches the driver."""
    wanted = frozenset(w for _, text in templates for w in word_list(text))

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        total: Counter = Counter()
        for got in batches:
            for text in got["body"]:
                total.update(wanted.intersection(word_list(text)))
        yield {"token": [t.decode() for t in total], "n": list(total.values())}

    rows = map_rows(docs, [F.col("text").alias("body")], "token string, n bigint", run)
    return {r["token"].encode(): r["n"] for r in rows.groupBy("token").agg(F.sum("n").alias("n")).collect()}


def scan(docs: DataFrame, *, templates=TEMPLATES, threshold: float = 0.8) -> DataFrame:
    """(doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score) of every whole text.

    score is 1 where a base phrase stands, else the best containment found, else 0.
    """
    ready = Templates(templates, token_frequencies(docs, templates), threshold)

    def one(text: str | None) -> tuple:
        words = word_list(text)
        joined = b" ".join(words)
        places = [(m.start(), PHRASES[m.group().decode()]) for m in _FOUND.finditer(joined)] if b"license" in joined or b"cc by" in joined else []
        base = {label for _, label in places}
        more: dict[str, float] = {}
        if not ready.first.isdisjoint(words):
            for block in blocks(text):
                for label, share in ready.matches(block).items():
                    more[label] = max(more.get(label, 0.0), share)
        at = [joined.count(b" ", 0, places[i][0]) for i in (0, -1)] if places else [None, None]
        return len(words), len(places), *at, ",".join(sorted(base)), ",".join(sorted(base | set(more))), 1.0 if base else max(more.values(), default=0.0)

    names = ("n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score")

    def run(batches: Iterator[dict]) -> Iterator[dict]:
        for got in batches:
            yield {"doc_id": got["key"]} | dict(zip(names, map(list, zip(*map(one, got["body"]))) if got["key"] else [[]] * len(names)))

    return map_rows(docs, [F.col("doc_id").cast("bigint").alias("key"), F.col("text").alias("body")], "doc_id bigint, n_words bigint, n_base bigint, first_word bigint, last_word bigint, base_labels string, labels string, score double", run)
