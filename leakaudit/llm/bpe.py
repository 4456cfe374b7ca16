"""Byte-pair encoding and decoding over a table of distinct words."""

from __future__ import annotations

import codecs
import hashlib
import json
import os
import struct
import uuid
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import Column, DataFrame, GroupedData
from pyspark.sql import functions as F

from leakaudit.llm.common import lean, trim
from leakaudit.runtime import batch_rows, materialise

#: A byte-level tokenizer's word rule (fixed value), with white space as Unicode has it.
SPLIT = (
    r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{IsWhite_Space}\p{L}\p{N}]+"
    r"|\p{IsWhite_Space}+(?!\P{IsWhite_Space})|\p{IsWhite_Space}+"
)
#: Words of about so many bytes make a block, the unit within which positions are joined back.
BLOCK_BYTES = 16 << 20
#: A text crosses to the block builder in pieces of at most so many code points, so that a batch of rows has a bound in bytes.
PIECE = 2048
#: So many pieces cross in a batch.
PIECES_AT_ONCE = 1024
#: Words of about so many bytes are numbered at once.
SLICE_BYTES = 2 << 20
#: Ids of a document are decoded in rows of so many at most; ids below DENSE are looked up by place.
STEP, DENSE = 256, 1 << 24
#: So many ids at once are asked for and put together.
IDS = 1 << 18
#: Words are dealt to so many parts by a hash at most; each part encodes its distinct words.
MOST_PARTS = 4096
#: Each word is followed by END. Where a text itself has one of the two, it is escaped by characters of the same class, which moves no word's end.
END, ESCAPE = "\x1f", "\x1e"


class Vocabulary:
    """A tokenizer's JSON, read once where the query is built: what the executors need of it."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as file:
            self.text = file.read()
        self.specials = [t["content"] for t in json.loads(self.text)["added_tokens"]]

    def encoder(self):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        made = Tokenizer.from_str(self.text)
        made.no_truncation()
        made.no_padding()
        return made

    def pieces(self) -> list[bytes]:
        """The id-to-piece table: the bytes of each id, one row per vocabulary entry."""
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        letter = {chr(b): b for b in shown} | {chr(256 + k): b for k, b in enumerate(b for b in range(256) if b not in set(shown))}
        data = json.loads(self.text)
        table: dict[int, bytes] = {i: bytes(letter[c] for c in w) for w, i in data["model"]["vocab"].items()}
        table |= {t["id"]: t["content"].encode() for t in data["added_tokens"]}
        return [table.get(i, b"") for i in range(max(table) + 1)]


def marked(text: Column, specials: list[str]) -> Column:
    """The text with END after each of its words. A special token's string is a word of its own."""
    whole = F.coalesce(text.cast("string"), F.lit(""))
    whole = F.replace(F.replace(whole, F.lit(ESCAPE), F.lit(ESCAPE + "#")), F.lit(END), F.lit(ESCAPE + "%"))
    split = lambda t: F.regexp_replace(t, SPLIT, "$0" + END)
    if not specials:
        return split(whole)
    mark = lambda t: "\\Q" + t + "\\E"
    has = whole.contains(specials[0])
    for t in specials[1:]:
        has = has | whole.contains(t)
    around = "|".join(f"(?={mark(t)})|(?<={mark(t)})" for t in specials)
    parts = F.transform(F.split(whole, around), lambda p: F.when(p.isin(specials), F.concat(p, F.lit(END))).otherwise(split(p)))
    return F.when(has, F.array_join(parts, "")).otherwise(split(whole))


#: Values of one byte, further ones of two, of three; a lead byte of 255 stands for a larger one, kept whole.
ONE, TWO, THREE = 128, 64 * 256, 63 * 65536


def _pack(values: np.ndarray) -> bytes:
    """Non-negative integers in one to three bytes, each byte's place in a row of its own: frequent small ones compress best so."""
    v = values.astype(np.int64 if len(values) and int(values.max()) >= 2**31 else np.int32)
    two, three, whole = v >= ONE, v >= ONE + TWO, v >= ONE + TWO + THREE
    mid, high = v - ONE, v - ONE - TWO
    lead = np.where(whole, 255, np.where(three, 192 + (high >> 16), np.where(two, 128 + (mid >> 8), v))).astype(np.uint8)
    rows = [lead, np.where(three, (high >> 8) & 255, mid & 255)[two].astype(np.uint8), (high & 255)[three].astype(np.uint8), v[whole].astype("<u4")]
    return struct.pack("<IIII", *map(len, rows)) + b"".join(r.tobytes() for r in rows)


def _unpack(raw: bytes, at: int = 0) -> tuple[np.ndarray, int]:
    """The values packed at ``at``, and where the next ones begin."""
    sizes, rows = struct.unpack_from("<IIII", raw, at), []
    at += 16
    for n, kind in zip(sizes, ("u1", "u1", "u1", "<u4"), strict=True):
        rows.append(np.frombuffer(raw, kind, n, at).astype(np.int64 if sizes[3] else np.int32))
        at += n * np.dtype(kind).itemsize
    out, second, third, large = rows
    two, three, whole = out >= 128, out >= 192, out == 255
    longer = three[two]
    out[two & ~three] = ((out[two & ~three] - 128) << 8) + second[~longer] + ONE
    out[three] = ((out[three] - 192) << 16) + (second[longer] << 8) + third + ONE + TWO
    out[whole] = large
    return out, at


BLOCKS = "block string, part int, payload binary"
_NAMES = ["block", "part", "payload"]


def _rows(rows: list[tuple[str, int, bytes]]) -> pa.RecordBatch:
    block, part, payload = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(block, pa.string()), pa.array(part, pa.int32()), pa.array(payload, pa.binary())], _NAMES)


class _Block:
    """A block in the making: its distinct words so far, and per document the numbers of its words."""

    def __init__(self) -> None:
        self.names: dict[bytes, int] = {}
        self.docs: list[pa.Array] = []
        self.sizes: list[np.ndarray] = []
        self.words: list[np.ndarray] = []
        self.rest = np.zeros(0, np.uint8)
        self.held = 0

    def add(self, ids: pa.Array, first: np.ndarray, ends: np.ndarray, data: np.ndarray) -> None:
        """Rows of pieces: a document's id and whether the row begins it; where each row's bytes end; all rows' bytes."""
        self.held += len(data)
        begun = len(self.rest)
        data, ends = np.concatenate((self.rest, data)), ends + begun
        stops = np.flatnonzero(data == ord(END)) + 1
        offsets = np.concatenate(([0], stops)).astype(np.int32)
        coded = pa.BinaryArray.from_buffers(pa.binary(), len(stops), [None, pa.py_buffer(offsets), pa.py_buffer(data)]).dictionary_encode()
        names = self.names
        known = [names.setdefault(w, len(names)) for w in coded.dictionary.to_pylist()]
        self.words.append(np.array(known, np.int32)[coded.indices.to_numpy(zero_copy_only=False)])
        self.rest = data[offsets[-1] :].copy()
        # the document of each word: that of the row its end is in; 0 is the one that was open before
        count = np.bincount(np.cumsum(first)[np.searchsorted(ends, stops - 1, "right")], minlength=int(first.sum()) + 1)
        if self.sizes:
            self.sizes[-1][-1] += count[0]
        if first.any():
            self.docs.append(ids.filter(pa.array(first)))
            self.sizes.append(count[1:].astype("<u4"))

    def close(self, parts: int) -> pa.RecordBatch:
        """The rows of the block: codes and sizes (part -1), then the distinct words of each part."""
        press = zstandard.ZstdCompressor(level=6)
        known = [w[:-1].replace(b"\x1e%", b"\x1f").replace(b"\x1e#", b"\x1e") if b"\x1e" in w else w[:-1] for w in self.names]
        part = np.fromiter((zlib.crc32(w) % parts for w in known), np.int32, len(known))
        count = np.zeros(len(known), np.int64)
        for w in self.words:
            count += np.bincount(w, minlength=len(known))
        # a code is (rank by frequency in its part) * parts + part: frequent words have small codes, which compress well
        order = np.lexsort((-count, part))
        bounds = np.searchsorted(part[order], np.arange(parts + 1))
        code = np.empty(len(known), np.int32)
        code[order] = (np.arange(len(known)) - bounds[part[order]]) * parts + part[order]
        head = pa.BufferOutputStream()
        with pa.ipc.new_stream(head, pa.schema([("doc_id", pa.int64())])) as to:
            to.write_batch(pa.RecordBatch.from_arrays([pa.concat_arrays([d.cast(pa.int64()) for d in self.docs])], ["doc_id"]))
        head = head.getvalue().to_pybytes()
        body = [struct.pack("<III", len(head), parts, len(self.words)), head, np.concatenate(self.sizes).tobytes(), *(_pack(code[w]) for w in self.words)]
        name = uuid.uuid4().hex
        rows = [(name, -1, press.compress(b"".join(body)))]
        for p in np.flatnonzero(np.diff(bounds)).tolist():
            rows.append((name, p, press.compress(b"\xff".join(known[i] for i in order[bounds[p] : bounds[p + 1]].tolist()))))
        return _rows(rows)


def _to_blocks(parts: int) -> Callable:
    """(doc_id, pos, piece), a document's pieces in a row -> per block the documents' word codes (part -1), and its distinct words by part."""

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = _Block()
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, piece = batch.column("doc_id"), pc.fill_null(batch.column("piece"), "")
            first = pc.fill_null(batch.column("pos"), 0).to_numpy(zero_copy_only=False) == 0
            offsets = np.frombuffer(piece.buffers()[1], np.int32)[piece.offset : piece.offset + len(piece) + 1].astype(np.int64)
            data = np.frombuffer(piece.buffers()[2] or b"", np.uint8)
            starts, at = np.flatnonzero(first), 0
            while at < len(piece):
                # a slice ends where a document begins, so that a block is closed between documents
                full = int(np.searchsorted(offsets, offsets[at] + SLICE_BYTES))
                after = starts[np.searchsorted(starts, max(full, at + 1)) :]
                to = int(after[0]) if len(after) else len(piece)
                if first[at] and block.held >= BLOCK_BYTES:
                    yield block.close(parts)
                    block = _Block()
                    trim()
                block.add(ids.slice(at, to - at), first[at:to], offsets[at + 1 : to + 1] - offsets[at], data[offsets[at] : offsets[to]])
                at = to
        if block.docs:
            yield block.close(parts)

    return run


def _encode_parts(vocabulary: Vocabulary) -> Callable:
    """Blocks' words sorted by part -> their ids in the same order; each distinct word of a part is encoded once."""

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, press, open_ = vocabulary.encoder(), zstandard.ZstdCompressor(level=6), zstandard.ZstdDecompressor()
        part, known = -1, {}
        for batch in batches:
            for block, p, payload in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if p != part:
                    part, known = p, {}
                asked = open_.decompress(payload).split(b"\xff")
                new = [w for w in asked if w not in known]
                for at in range(0, len(new), 20000):
                    some = new[at : at + 20000]
                    for w, e in zip(some, encoder.encode_batch([w.decode() for w in some], add_special_tokens=False), strict=True):
                        known[w] = np.array(e.ids, "<u4").tobytes()
                ids = [known[w] for w in asked]
                body = _pack(np.fromiter(map(len, ids), np.int64, len(ids)) // 4) + _pack(np.frombuffer(b"".join(ids), "<u4"))
                yield _rows([(block, p, press.compress(body))])

    return run


def _chunks(rows: list[tuple[int, pa.Buffer]]) -> Iterator[tuple[int, pa.Array, np.ndarray, np.ndarray, bool]]:
    """The (part, payload) rows of one block, its codes and each part's ids -> some of its words at a time:

    the number of the first document among them, the documents' ids, where each one's
    token ids begin and end, the token ids, and whether the first document goes on
    from the chunk before.
    """
    open_ = zstandard.ZstdDecompressor()
    rows = sorted(rows, key=lambda r: r[0])
    body = open_.decompress(rows[0][1])
    n_head, n_parts, n_chunks = struct.unpack_from("<III", body)
    at = 12 + n_head
    doc_ids = pa.ipc.open_stream(body[12:at]).read_all().column("doc_id").combine_chunks()
    ends = np.cumsum(np.frombuffer(body, "<u4", len(doc_ids), at), dtype=np.int64)
    counts, flat, before, words = [np.zeros(0, np.int64)], [np.zeros(0, np.int32)], np.zeros(n_parts, np.int64), 0
    for p, raw in rows[1:]:
        raw = open_.decompress(raw)
        sizes, to = _unpack(raw)
        before[p], words = words, words + len(sizes)
        counts.append(sizes)
        flat.append(_unpack(raw, to)[0].astype(np.int32))
    count, flat = np.concatenate(counts), np.concatenate(flat)
    first = np.cumsum(count) - count
    at += 4 * len(doc_ids)
    word, doc, goes_on = 0, 0, False
    for _ in range(n_chunks):
        code, at = _unpack(body, at)
        code = before[code % n_parts] + code // n_parts  # the word's place among the block's
        n = count[code]
        upto = np.concatenate(([0], np.cumsum(n)))
        ids = flat[np.repeat(first[code] - upto[:-1], n) + np.arange(int(upto[-1]))]
        # the documents that end among these words, and one that begins and doesn't end
        to = int(np.searchsorted(ends, word + len(code), "right"))
        more = word + len(code) > (int(ends[to - 1]) if to else 0)
        bounds = upto[np.concatenate(([0], ends[doc:to] - word, [len(code)] * more)).astype(np.int64)]
        if len(bounds) > 1:
            yield doc, doc_ids.slice(doc, to + more - doc), bounds.astype(np.int32), ids, goes_on
        word, doc, goes_on = word + len(code), to, more
    if doc < len(doc_ids):
        yield doc, doc_ids.slice(doc), np.zeros(len(doc_ids) - doc + 1, np.int32), np.zeros(0, np.int32), False


def _payloads(columns: pa.Table | pa.RecordBatch) -> list[tuple[int, pa.Buffer]]:
    return [(p, x.as_buffer()) for p, x in zip(columns.column("part").to_pylist(), columns.column("payload"), strict=True)]


def _ids_of_block(table: pa.Table) -> pa.Table:
    """All rows of one block -> ``doc_id, ids`` of its documents."""
    names, streams, ends, total = [pa.array([], pa.int64())], [np.zeros(0, np.int32)], {}, 0
    for doc, some, bounds, ids, goes_on in _chunks(_payloads(table)):
        names.append(some.slice(1) if goes_on else some)
        ends |= zip(range(doc, doc + len(some)), (total + bounds[1:]).tolist(), strict=True)
        streams.append(ids)
        total += len(ids)
    bounds = pa.array([0, *(ends[k] for k in range(len(ends)))], pa.int32())
    return pa.table([pa.concat_arrays(names), pa.ListArray.from_arrays(bounds, pa.array(np.concatenate(streams)))], schema=pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int32()))]))


def _blocks(docs: DataFrame, vocabulary: Vocabulary, doc_id: str, text: str) -> GroupedData:
    """Per block the documents' codes and the ids of each part's words."""
    parts = min(MOST_PARTS, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    cut = F.regexp_extract_all(marked(F.col(text), vocabulary.specials), F.lit("(?s).{1,%d}" % PIECE), F.lit(0))
    split = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.posexplode_outer(cut).alias("pos", "piece"))
    with batch_rows(docs.sparkSession, PIECES_AT_ONCE):
        blocks = materialise(split.mapInArrow(_to_blocks(parts), BLOCKS), "blocks")
    ids = blocks.where("part >= 0").repartition("part").sortWithinPartitions("part").mapInArrow(_encode_parts(vocabulary), BLOCKS)
    return blocks.where("part < 0").union(ids).groupBy("block")


def encode(docs: DataFrame, vocabulary: Vocabulary, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, ids`` of every row, as the tokenizers library encodes it without adding special tokens.

    Texts are split into words by Spark. Per block of documents the distinct words
    are listed; the lists are dealt by a hash of the word, so that every distinct
    word is encoded once, by the task that holds its part; the ids go back to their
    blocks, where each position takes its word's ids. Memory: a batch holds pieces
    of PIECE code points, a block some BLOCK_BYTES (or one longer document). Null
    texts and empty ones have no ids; repeated rows each get theirs; no rows give none.
    """
    return _blocks(docs, vocabulary, doc_id, text).applyInArrow(_ids_of_block, "doc_id long, ids array<int>")


_ASKED = "doc_id long, first boolean, ids array<int>, ask array<int>"


def _asked(doc_id: pa.Array, ids: pa.Array, goes_on: bool = False) -> pa.RecordBatch:
    """A row that asks for the pieces of all distinct ids (``ask``), then the documents' ids in rows of STEP at most; the first document may go on from before."""
    sizes = pc.fill_null(pc.list_value_length(ids), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = pc.fill_null(ids.flatten(), -1)
    values = flat.to_numpy(zero_copy_only=False)
    distinct = np.unique(values)
    rows = np.maximum(1, -(-sizes // STEP))
    doc = np.repeat(np.arange(len(sizes)), rows)
    inside = (np.arange(len(doc)) - np.repeat(np.cumsum(rows) - rows, rows)) * STEP
    bounds = np.concatenate(([0], (np.cumsum(sizes) - sizes)[doc] + inside, [len(values)])).astype(np.int32)
    ask = np.concatenate(([0], np.full(len(doc) + 1, len(distinct)))).astype(np.int32)
    return pa.RecordBatch.from_arrays(
        [doc_id.take(pa.array(np.concatenate(([0], doc + 1)) - 1, pa.int64(), mask=np.arange(len(doc) + 1) == 0)), pa.array(np.concatenate(([False], (inside == 0) & ((doc > 0) | (not goes_on))))),
         pa.ListArray.from_arrays(pa.array(bounds), flat.cast(pa.int32())), pa.ListArray.from_arrays(pa.array(ask), pa.array(distinct.astype(np.int32)))], ["doc_id", "first", "ids", "ask"])


def _asked_slices(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    """``_asked`` of the documents of ``batch``, some IDS ids at a time (or one longer document)."""
    ends, at = np.cumsum(pc.fill_null(pc.list_value_length(batch.column("ids")), 0).to_numpy(zero_copy_only=False)), 0
    while at < batch.num_rows:
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + IDS, "right")))
        part = batch.slice(at, to - at)
        yield _asked(part.column("doc_id"), part.column("ids"))
        at = to


def _asked_of_block(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """All rows of one block -> ``_asked`` of some of its documents at a time: no more than the block's codes and one chunk's ids are held."""
    pa.set_memory_pool(pa.system_memory_pool())
    for _, some, bounds, ids, goes_on in _chunks([r for batch in batches for r in _payloads(batch)]):
        yield _asked(some, pa.ListArray.from_arrays(pa.array(bounds), pa.array(ids)), goes_on)
    trim()


@lean
def _asked_of_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        if batch.num_rows:
            yield from _asked_slices(batch)


def _placed(asked: DataFrame, vocabulary: Vocabulary) -> DataFrame:
    """``doc_id, first, ids, id, piece``: every id that is asked for, joined to its piece, before the rows that need it.

    The table of pieces is broadcast: it has as many rows as the vocabulary, whatever the input.
    """
    pieces = vocabulary.pieces()
    table = asked.sparkSession.createDataFrame(pa.table({"id": pa.array(range(len(pieces)), pa.int32()), "piece": pa.array(pieces, pa.binary())}))
    rows = asked.select("doc_id", "first", "ids", F.explode_outer("ask").alias("id"))
    return rows.join(F.broadcast(table), "id", "left").select("doc_id", "first", "ids", "id", "piece")


class _Digests:
    """A document's digests, fed as its pieces come."""

    schema = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])

    def __init__(self, doc_id: int | None) -> None:
        self.doc_id, self.n, self.ids, self.text = doc_id, 0, hashlib.sha256(), hashlib.sha256()
        self.open = codecs.getincrementaldecoder("utf-8")("replace")

    def add(self, ids: np.ndarray, data: bytes) -> None:
        self.n += len(ids)
        self.ids.update(ids.astype("<u4").tobytes())
        self.text.update(self.open.decode(data).encode())

    def row(self) -> tuple:
        self.text.update(self.open.decode(b"", True).encode())
        return self.doc_id, self.n, self.ids.hexdigest(), self.text.hexdigest()


class _Text:
    """A document's text, put together as its pieces come; bytes that aren't UTF-8 are replaced."""

    schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string())])

    def __init__(self, doc_id: int | None) -> None:
        self.doc_id, self.parts = doc_id, []

    def add(self, ids: np.ndarray, data: bytes) -> None:
        self.parts.append(data)

    def row(self) -> tuple:
        return self.doc_id, b"".join(self.parts).decode("utf-8", "replace")


class _Pieces:
    """The pieces of the ids that were asked for last."""

    def __init__(self) -> None:
        self.ids, self.pieces, self.open = [], [], True

    def add(self, ids: pa.Array, pieces: pa.Array) -> None:
        if not self.open:
            self.__init__()
        self.ids.append(ids.to_numpy(zero_copy_only=False))
        self.pieces.append(pc.fill_null(pieces, b""))

    def of(self, ids: np.ndarray) -> tuple[np.ndarray, memoryview]:
        """Where each id's piece ends in the bytes of all, and these."""
        if self.open:
            self.known, self.open = np.concatenate([np.zeros(0, np.int32), *self.ids]), False
            self.table = pa.concat_arrays([pa.array([], pa.binary()), *self.pieces])
            self.order = np.argsort(self.known, kind="stable")
            self.place = None
            if len(self.known) and self.known.min() >= 0 and self.known.max() < DENSE:
                self.place = np.zeros(int(self.known.max()) + 1, np.int32)
                self.place[self.known] = np.arange(len(self.known))
        at = self.place[ids] if self.place is not None else self.order[np.searchsorted(self.known, ids, sorter=self.order)]
        found = self.table.take(pa.array(at))
        return np.frombuffer(found.buffers()[1], np.int32)[found.offset :][: len(found) + 1], memoryview(found.buffers()[2] or b"")


def _in_order(kind: type) -> Callable:
    """Rows of ``_placed`` in their order -> the rows that ``kind`` makes of each document.

    They come from one explosion and a broadcast join, which keep the order within a task.
    """

    def made(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), kind.schema, strict=True)], schema=kind.schema)

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        doc, out, held, pieces = None, [], 0, _Pieces()
        for batch in batches:
            asks = batch.column("id").is_valid().to_numpy(zero_copy_only=False)
            turns = np.flatnonzero(np.concatenate(([True], asks[1:] != asks[:-1], [True]))).tolist() if len(asks) else []
            for a, b in zip(turns, turns[1:], strict=False):
                part = batch.slice(a, b - a)
                if asks[a]:
                    pieces.add(part.column("id"), part.column("piece"))
                    continue
                lists = part.column("ids")
                ids = lists.flatten().to_numpy(zero_copy_only=False)
                ends = np.concatenate(([0], np.cumsum(pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False)))).tolist()
                offsets, data = pieces.of(ids) if len(ids) else (np.zeros(1, np.int32), memoryview(b""))
                for k, (name, first) in enumerate(zip(part.column("doc_id").to_pylist(), part.column("first").to_pylist(), strict=True)):
                    if first:
                        if doc is not None:
                            out.append(doc.row())
                        doc = kind(name)
                    x, y = ends[k], ends[k + 1]
                    if y > x:
                        doc.add(ids[x:y], bytes(data[offsets[x] : offsets[y]]))
                held += len(data)
                if out and (held >= SLICE_BYTES or len(out) >= 1000):
                    yield made(out)
                    out, held = [], 0
        if doc is not None:
            yield made([*out, doc.row()])

    return run


def decode(encoded: DataFrame, vocabulary: Vocabulary, doc_id: str = "doc_id", ids: str = "ids") -> DataFrame:
    """``doc_id, text``: ids joined to their pieces, the pieces put together in order. Null ids give an empty text, an id without a piece nothing.

    As in encoding, what is joined are the distinct ids of each batch of rows; positions take theirs from the joined rows that come before them.
    """
    rows = encoded.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(ids).cast("array<int>").alias("ids")).mapInArrow(_asked_of_rows, _ASKED)
    return _placed(rows, vocabulary).mapInArrow(_in_order(_Text), "doc_id long, text string")


def digests(docs: DataFrame, vocabulary: Vocabulary, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256``: ``encode``, then ``decode`` block by block with only the digests leaving the worker."""
    rows = _blocks(docs, vocabulary, doc_id, text).applyInArrow(_asked_of_block, _ASKED)
    return _placed(rows, vocabulary).mapInArrow(_in_order(_Digests), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
