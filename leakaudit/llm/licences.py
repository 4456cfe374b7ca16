"""Licence scans by conditional compression."""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import accumulate

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from leakaudit.llm.common import lean, pieces

#: Wordings of public licences: notices and opening paragraphs (fixed values).
TEMPLATES = {
    "MIT": (
        "Released under the MIT License.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    ),
    "Apache-2.0": (
        "Licensed under the Apache License, Version 2.0.",
        "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License.",
    ),
    "GPL-3.0": (
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    ),
    "GPL-2.0": (
        "This work is licensed under the GNU General Public License, version 2.",
        "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    ),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    "CC-BY-4.0": ("Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    "BSD": ("Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",),
    "Proprietary": ("All rights reserved.", "This software is confidential and proprietary."),
}
#: Places are looked for round these. Every template has more words with one than may be missing, so line ends can part no cue.
CUE = re.compile(r"licen[sc]e|copyright|redistribut|hereby|reserved|proprietary|spdx|software|binary|permitted|\bgnu\b|\bCC BY", re.I)
#: A template is confirmed if at most this share of its words differs from the block's.
MOST_DIFFERENT = 0.1
#: A template is compared word by word where knowing it saves so many bytes at least. Short notices with other words among theirs save
#: no more than that; a higher bound lost some of them.
LEAST_SAVED = 1
#: A word that is parted after a hyphen goes on behind the line end and the next line's comment signs.
WORDS = re.compile(r"\w+(?:[.\-]\w+|-[ \t]*\r?\n[^\w\n]*\w+)*")
PARTED = re.compile(r"-\s*\n\W*")
#: Words are held in runs of so many.
RUN = 20_000


PLAIN = zstandard.ZstdCompressor(level=3, write_checksum=False, write_content_size=False, write_dict_id=False)


class Wording:
    """A template: its words, and the places in a word list where at most ``MOST_DIFFERENT`` of them are missing."""

    def __init__(self, name: str, text: str):
        self.name = name
        self.words = [w.lower() for w in WORDS.findall(text)]
        self.most = int(MOST_DIFFERENT * len(self.words))
        #: A place takes up so many words: a quarter and two may stand between.
        self.reach = len(self.words) + len(self.words) // 4 + 2
        self.bits: dict[str, int] = {}
        for i, w in enumerate(self.words):
            self.bits[w] = self.bits.get(w, 0) | 1 << i
        # one of these must be there if no more than ``most`` are missing
        self.first = set(self.words[: self.most + 1])
        self.press = self._given(text.lower())
        #: The same for words without line ends and signs between them.
        self.press_words = self._given(" ".join(self.words))

    @staticmethod
    def _given(text: str) -> zstandard.ZstdCompressor:
        raw = zstandard.ZstdCompressionDict(text.encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        raw.precompute_compress(level=3)
        return zstandard.ZstdCompressor(dict_data=raw, write_checksum=False, write_content_size=False, write_dict_id=False)

    def saved(self, raw: bytes, plain: int) -> int:
        """By how many bytes ``raw``, some words, shrinks once the template is known; ``plain``: its size without."""
        return plain - len(self.press_words.compress(raw))

    def common(self, words: list[str]) -> int:
        """The most words of the template that ``words`` has in the same order, bit by bit over the template."""
        full = (1 << len(self.words)) - 1
        rest = full
        for w in words:
            both = rest & self.bits.get(w, 0)
            rest = ((rest + both) | (rest - both)) & full
        return len(self.words) - rest.bit_count()

    def matched(self, words: list[str]) -> list[int]:
        """Places in ``words`` of the words that ``common`` counts, with the earliest end."""
        table = [[0] * (len(words) + 1)]
        for t in self.words:
            above, row = table[-1], [0]
            for j, w in enumerate(words):
                row.append(above[j] + 1 if w == t else max(above[j + 1], row[j]))
            table.append(row)
        i, j, found = len(self.words), len(words), []
        while i and j:
            if table[i][j] == table[i][j - 1]:
                j -= 1
            elif table[i][j] == table[i - 1][j]:
                i -= 1
            else:
                i, j = i - 1, j - 1
                found.append(j)
        return found[::-1]

    def places(self, words: list[str], upto: int) -> Iterator[tuple[int, list[int]]]:
        """(words missing, places of those matched) of each start before ``upto`` where the template is confirmed."""
        need = len(self.words) - self.most
        known = list(accumulate((w in self.bits for w in words), initial=0))
        for i in range(min(upto, len(words) - need + 1)):
            end = min(i + self.reach, len(words))
            if words[i] in self.first and known[end] - known[i] >= need and self.common(words[i:end]) >= need:
                at = self.matched(words[i:end])
                yield len(self.words) - len(at), [i + j for j in at]


class Scanner:
    """All wordings, none left out by rank: where a stretch of words shrinks enough given the template, the words are compared; a confirmed place is measured by how much it shrinks."""

    def __init__(self, templates: dict[str, tuple[str, ...]] = TEMPLATES):
        self.each = [Wording(name, text) for name, texts in templates.items() for text in texts]
        self.reach = max((w.reach for w in self.each), default=0)

    def gain(self, k: int, some: str) -> float:
        raw = some.lower().encode()
        return 1 - len(self.each[k].press.compress(raw)) / max(1, len(PLAIN.compress(raw)))

    def places(self, spans: list[tuple[int, int]], text: str, upto: int) -> list[tuple[int, int, int, list[int]]]:
        """(template, words missing, stop, starts of the matched words) of all wordings that start in the first ``upto`` words."""
        words, found = [PARTED.sub("-", text[a:b]).lower() for a, b in spans], []
        # stretches of twice the reach: a place lies whole in the one that its start falls into the first half of
        for low in range(0, min(upto, len(words)), max(1, self.reach)):
            some = words[low : low + 2 * self.reach]
            raw = " ".join(some).encode(errors="replace")
            plain, starts = len(PLAIN.compress(raw)), min(self.reach, upto - low)
            for k, wording in enumerate(self.each):
                if wording.saved(raw, plain) >= LEAST_SAVED:
                    found += [(k, missing, spans[low + at[-1]][1], [spans[low + i][0] for i in at]) for missing, at in wording.places(some, starts)]
        return found

    def scan(self, text: str) -> list[dict]:
        """All confirmed wordings with their places in code points, in order.

        Of wordings that share most of their words the longest stays, then the one with
        the fewest missing, then the shortest place: a notice can be the start of another.
        """
        hits: list[tuple[int, int, int, list[int]]] = []
        for start, stop in blocks(text, self.reach):
            held: list[tuple[int, int]] = []
            for m in WORDS.finditer(text, start, stop):
                held.append(m.span())
                if len(held) == RUN + self.reach:
                    hits += self.places(held, text, RUN)
                    del held[:RUN]
            hits += self.places(held, text, len(held))
        taken: set[int] = set()
        found = []
        for k, missing, stop, at in sorted(hits, key=lambda h: (-len(self.each[h[0]].words), h[1], h[2] - h[3][0], h[3][0], h[0])):
            if 2 * sum(x in taken for x in at) <= len(at):
                taken.update(at)
                found.append({"licence": self.each[k].name, "start": at[0], "stop": stop, "gain": self.gain(k, text[at[0] : stop]), "missing": missing, "words": len(self.each[k].words)})
        return sorted(found, key=lambda f: (f["start"], f["stop"]))


def ahead(text: str, at: int, words: int) -> int:
    """The end of the last of so many words from ``at`` on."""
    for n, m in enumerate(WORDS.finditer(text, at), 1):
        if n > words:
            return m.end()
    return len(text)


def behind(text: str, at: int, words: int) -> int:
    """The start of the first of so many words before ``at``."""
    size = 12 * words
    while True:
        low = max(0, at - size)
        # the first one of a slice may be the rest of a word
        starts = [m.start() for m in WORDS.finditer(text, low, at)]
        if low == 0 or len(starts) > words + 2:
            return starts[-words - 1] if len(starts) > words else 0
        size *= 2


def blocks(text: str, reach: int) -> Iterator[tuple[int, int]]:
    """Separate spans that hold ``reach`` words on both sides of every cue, whatever lines they stand on."""
    start = stop = last = -1
    for m in CUE.finditer(text):
        if start >= 0 and m.start() >= stop:
            stop = ahead(text, last, reach)
        if m.start() >= stop:
            begin = behind(text, m.start(), reach)
            if start < 0 or begin > stop:
                if start >= 0:
                    yield start, stop
                start = begin
            stop = ahead(text, m.end(), reach)
        last = m.end()
    if start >= 0:
        yield start, ahead(text, last, reach)


def scan(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", templates: dict[str, tuple[str, ...]] = TEMPLATES) -> DataFrame:
    """``doc_id, found`` of every row: confirmed licences with place, size reduction and words that differ.

    Null and empty texts have none; repeated rows each get theirs; no rows give none.
    """

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(templates)
        kind = pa.list_(pa.struct([("licence", pa.string()), ("start", pa.int32()), ("stop", pa.int32()), ("gain", pa.float64()), ("missing", pa.int32()), ("words", pa.int32())]))
        for part in pieces(batches, "text"):
            found = [scanner.scan(t) if t else [] for t in part.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(found, kind)], ["doc_id", "found"])

    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, found array<struct<licence:string,start:int,stop:int,gain:double,missing:int,words:int>>")
