"""``lexing`` over arrays: the pieces and marks of a batch of texts at once, from the bytes as Arrow holds them."""

from __future__ import annotations

import re
import unicodedata
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa

from leakaudit.functions import lexing

#: Bytes of text that a worker lexes at a time, one text at least.
BYTES_AT_ONCE = 1 << 20
OTHER, WHITE, LETTER, NUMBER = range(4)


def _narrow() -> np.ndarray:
    kinds = np.full(256, OTHER, np.uint8)
    kinds[[ord(c) for c in lexing.BLANKS]] = WHITE
    kinds[[i for i in range(128) if chr(i).isalpha() or chr(i) == "_"]] = LETTER
    kinds[[ord(c) for c in "0123456789"]] = NUMBER
    return kinds


_NARROW = _narrow()
_AFTER_BLANK, _TRIPLE = np.zeros(256, bool), np.zeros(256, bool)
_AFTER_BLANK[[ord(c) for c in " \n,."]], _TRIPLE[[ord(c) for c in "#%*$&="]] = True, True


@cache
def _wide() -> np.ndarray:
    """Letter, number or other, by code point."""
    kind = {"L": LETTER, "N": NUMBER}
    return np.fromiter((kind.get(unicodedata.category(chr(i))[0], OTHER) for i in range(0x110000)), np.uint8, 0x110000)


@cache
def _patterns(grammar: str) -> tuple:
    """Marks, comment and literal starts of a grammar, and the format rules, for Python's own engine."""
    starts = [x and re.compile(x) for x in (lexing.COMMENT_STARTS[grammar], lexing.LITERAL_STARTS[grammar])]
    # a letter: what is alphanumeric but no decimal, no line below and no number of another kind
    others = "".join(re.escape(chr(i)) for i in np.flatnonzero(_wide() == NUMBER) if not chr(i).isdecimal())
    return re.compile(lexing.MARKS[grammar]), *starts, re.compile(lexing.LINT_MARKS.replace(r"[\p{L}]", rf"[^\W\d_{others}]"))


@dataclass
class Pieces:
    """The pieces of some texts that aren't white space: row, bytes, number among all pieces of its text, place in code points, and kind."""

    row: np.ndarray
    tok: pa.Array
    pos: np.ndarray
    start: np.ndarray
    stop: np.ndarray
    kind: np.ndarray
    #: Where each row's code points begin among all.
    first: np.ndarray
    #: The rows in which a format rule may hit.
    faulty: np.ndarray


def slices(batches: Iterator[pa.RecordBatch], most: int = BYTES_AT_ONCE) -> Iterator[pa.RecordBatch]:
    """Batches of some ``most`` bytes of ``text``; a longer text stands alone."""
    for batch in batches:
        sizes, at, held = np.diff(_buffers(batch.column("text"))[0]), 0, 0
        for i, n in enumerate(sizes):
            if i > at and held + n > most:
                yield batch.slice(at, i - at)
                at, held = i, 0
            held += int(n)
        if at < batch.num_rows:
            yield batch.slice(at)


def _buffers(text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Offsets from 0 on, and the bytes; a null has none."""
    if text.null_count:
        text = text.fill_null("")
    if not len(text):
        return np.zeros(1, np.int64), np.zeros(0, np.uint8)
    kind = np.int64 if pa.types.is_large_string(text.type) else np.int32
    offsets = np.frombuffer(text.buffers()[1], kind)[text.offset : text.offset + len(text) + 1].astype(np.int64)
    raw = np.frombuffer(text.buffers()[2], np.uint8) if text.buffers()[2] is not None else np.zeros(0, np.uint8)
    return offsets - offsets[0], raw[offsets[0] : offsets[-1]]


def _kinds(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray | None]:
    """The kind of each code point, and its first byte (none where all are ASCII)."""
    kinds = _NARROW[raw]
    if not len(raw) or raw.max() < 0x80:
        return kinds, None
    at = np.flatnonzero((raw & 0xC0) != 0x80)
    lead = np.flatnonzero(raw >= 0xC0)
    first = raw[lead].astype(np.int64)
    more = 1 + (first >= 0xE0) + (first >= 0xF0)
    code = first & np.array([0, 0x1F, 0x0F, 0x07])[more]
    for k in (1, 2, 3):
        on = more >= k
        code[on] = code[on] << 6 | raw[lead[on] + k] & 0x3F
    kinds[lead] = _wide()[code]
    return kinds[at], at


def pieces(text: pa.Array) -> Pieces:
    offsets, raw = _buffers(text)
    kinds, at = _kinds(raw)
    first = offsets if at is None else np.searchsorted(at, offsets)
    fresh = np.zeros(len(kinds) + 1, bool)
    fresh[first] = True
    fresh = fresh[:-1]
    before = np.concatenate((np.zeros(1, np.uint8), kinds[:-1]))
    # a word goes on through letters and numbers; numbers before its first letter are a piece of their own
    begins = (kinds == OTHER) | fresh | ((kinds == WHITE) & (before != WHITE)) | ((kinds >= LETTER) & (before < LETTER))
    turn = np.flatnonzero((kinds == LETTER) & (before == NUMBER) & ~begins)
    if len(turn):
        starts = np.flatnonzero(begins)
        run, letters = starts[np.searchsorted(starts, turn, side="right") - 1], np.cumsum(kinds == LETTER)
        begins[turn[(kinds[run] == NUMBER) & (letters[turn] - letters[run] == 1)]] = True
    start = np.flatnonzero(begins)
    stop = np.append(start[1:], len(kinds))
    each = np.searchsorted(start, first)
    row = np.repeat(np.arange(len(text), dtype=np.int64), np.diff(each))
    low = np.append(start if at is None else at[start], len(raw)).astype(np.int64)
    every = pa.Array.from_buffers(pa.large_string(), len(start), [None, pa.py_buffer(low), pa.py_buffer(raw)])
    kind = kinds[start]
    kept = np.flatnonzero(kind != WHITE)
    row, of = row[kept], first[row[kept]]
    return Pieces(row, every.take(pa.array(kept)), kept - each[row] + 1, start[kept] - of, stop[kept] - of, kind[kept], first, _faulty(raw, offsets))


def _faulty(raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Rows that hold what a format rule begins with; which of it is a fault, the rules say."""
    if len(raw) < 2:
        return np.flatnonzero(np.diff(offsets)) if len(raw) else np.zeros(0, np.int64)
    blank = np.flatnonzero((raw[:-1] == 32) & _AFTER_BLANK[raw[1:]])
    comma = np.flatnonzero(raw[:-1] == 44)
    comma = comma[(_NARROW[raw[comma + 1]] == LETTER) | (raw[comma + 1] >= 0x80)]
    mark = np.flatnonzero(_TRIPLE[raw[:-1]] & (raw[:-1] == raw[1:]))
    return np.unique(np.searchsorted(offsets, np.concatenate((blank, comma, mark, np.flatnonzero(raw == 9))), side="right") - 1)


def marks(text: pa.Array, grammar: str, faulty: np.ndarray) -> list[tuple[str, int, int, int]]:
    """``kind, row, start, stop`` of comments, literals and format faults, in code points."""
    mark, comment, literal, lint = _patterns(grammar)
    found, suspect = [], set(faulty.tolist())
    begins = [c for c in lexing._BEGINS[grammar] if c != "<"] + ["<!--"] * ("<" in lexing._BEGINS[grammar])
    for row, t in enumerate(text.to_pylist()):
        if t and any(c in t for c in begins):
            for m in mark.finditer(t):
                kind = "comment" if comment and comment.search(m[0]) else "literal" if literal and literal.search(m[0]) else None
                if kind:
                    found.append((kind, row, m.start(), m.end()))
        if row in suspect:
            found += [("lint", row, m.start(), m.end()) for m in lint.finditer(t)]
    return found


def spread(piece: Pieces, spans: list[tuple[str, int, int, int]], kinds: tuple[str, ...]) -> list[np.ndarray]:
    """For each of ``kinds``, which pieces a span of it overlaps."""
    covered, stop, start = [], piece.first[piece.row] + piece.stop, piece.first[piece.row] + piece.start
    for kind in kinds:
        some = sorted((piece.first[row] + a, piece.first[row] + b) for k, row, a, b in spans if k == kind)
        if not some:
            covered.append(np.zeros(len(start), bool))
            continue
        first, last = np.array(some, np.int64).T
        # of the spans that start before a piece's end, the largest end
        before = np.searchsorted(first, stop - 1, side="right")
        covered.append((before > 0) & (np.concatenate(([-1], np.maximum.accumulate(last)))[before] > start))
    return covered
