"""Repeated passages: compressed full-text indexes per shard, matching statistics of streamed documents."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from leakaudit.llm.common import lean, pieces, utf8
from leakaudit.llm.fm import DEPTH, Index, matching_statistics
from leakaudit.runtime import materialise

WINDOW = 50
#: Anchors are runs of so many words: each window has the one of least hash.
GRAM = 8
#: A span holds at most so many windows, so that a span's length is bounded.
SPAN = 64
#: Words of distinct spans that a shard aims at.
SHARD_WORDS = 300_000
LOWEST = -(2**63)

_ODD, _MIX = 0x9E3779B97F4A7C15, np.uint64(0xBF58476D1CE4E5B9)


def _grams(hashes: np.ndarray, size: int) -> np.ndarray:
    """A hash of each run of ``size`` (a power of two) word hashes, by doubling."""
    width, odd = 1, _ODD
    while width < size:
        hashes = hashes[:-width] * np.uint64(odd) + hashes[width:]
        width, odd = 2 * width, (odd * odd + 2) % 2**64
    hashes = (hashes ^ (hashes >> np.uint64(31))) * _MIX
    return hashes ^ (hashes >> np.uint64(29))


def _least(values: np.ndarray, width: int) -> np.ndarray:
    """The least of each ``width`` consecutive values."""
    reach = 1
    while 2 * reach <= width:
        values, reach = np.minimum(values[:-reach], values[reach:]), 2 * reach
    more = width - reach
    return np.minimum(values[:-more], values[more:]) if more else values


def anchors(words: list[bytes], window: int = WINDOW) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(anchor, first, last)``: runs of windows that share an anchor. Equal windows have equal anchors wherever they stand."""
    if len(words) < window:
        none = np.zeros(0, np.int64)
        return none, none, none
    hashes = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    gram = GRAM if window >= GRAM else 1
    least = _least(_grams(hashes, gram), window - gram + 1)
    at = np.arange(len(least))
    new = np.concatenate(([True], least[1:] != least[:-1]))
    run = np.maximum.accumulate(np.where(new, at, 0))
    new |= (at - run) % SPAN == 0
    first = np.flatnonzero(new)
    return least[first].view(np.int64), first, np.concatenate((first[1:], [len(least)])) - 1


_PASS = "did long, th long, doc_id long, n_words long, sha string, anchor array<long>, first array<int>, last array<int>"


def _survey(window: int):
    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in pieces(batches, "text"):
            count, sha, found = [], [], []
            for text in utf8(part.column("text")):
                words = text.split()
                count.append(len(words))
                sha.append(hashlib.sha256(b" ".join(words)).hexdigest())
                found.append(anchors(words, window))
            lists = [pa.array([x[k] for x in found], pa.list_(kind)) for k, kind in ((0, pa.int64()), (1, pa.int32()), (2, pa.int32()))]
            yield pa.RecordBatch.from_arrays([part.column("did"), part.column("th"), part.column("doc_id"), pa.array(count, pa.int64()), pa.array(sha), *lists], ["did", "th", "doc_id", "n_words", "sha", "anchor", "first", "last"])

    return run


def _spans(window: int, whole: bool):
    """Documents with their repeated anchors' spans -> one row per span: its place, and its words or only their hashes."""

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in pieces(batches, "text", 2 << 20):
            rows: list[tuple] = []
            for text, did, th, spans in zip(utf8(part.column("text")), part.column("did").to_pylist(), part.column("th").to_pylist(), part.column("spans").to_pylist(), strict=True):
                words = text.split()
                for s in spans:
                    content = b" ".join(words[s["first"] : s["last"] + window])
                    key = (s["anchor"], xxhash.xxh64_intdigest(content) - 2**63, xxhash.xxh64_intdigest(content, 1) - 2**63)
                    rows.append((*key, did, content) if whole else (*key, did, th, s["first"]))
            if rows:
                last = ("did", pa.int64()), ("content", pa.binary())
                if not whole:
                    last = ("did", pa.int64()), ("th", pa.int64()), ("first", pa.int32())
                names = ["anchor", "c1", "c2", *(n for n, _ in last)]
                kinds = [pa.int64()] * 3 + [k for _, k in last]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    return run


def shard_runs(contents: list[bytes], lows: np.ndarray, indexed: np.ndarray, window: int = WINDOW) -> list[tuple[int, int, int, int]]:
    """``(which, first window, windows, least document)`` of the runs of windows of ``contents`` that the index of the ``indexed`` ones holds.

    ``lows`` has the least document that each content stands in.
    """
    split = [c.split(b" ") for c in contents]
    names: dict[bytes, int] = {}
    for k in np.flatnonzero(indexed).tolist():
        for w in split[k]:
            names.setdefault(w, len(names) + 2)
    coded = [np.fromiter((names.get(w, 0) for w in s), np.int64, len(s)) for s in split]
    inside = np.flatnonzero(indexed)
    if not len(inside):
        return []
    text, owner = [], []
    for k in inside.tolist():
        text += [coded[k], np.ones(1, np.int64)]
        owner.append(np.full(len(coded[k]) + 1, lows[k]))
    index = Index(np.concatenate(text), max(DEPTH, window))
    owner = np.concatenate([*owner, [2**63 - 1]])[index.suffixes]
    group = np.concatenate(([True], index.common()[1:] < window))
    starts = np.flatnonzero(group)
    least, group = np.minimum.reduceat(owner, starts), np.cumsum(group) - 1
    which, start, low = [], [], []
    for w, s, a, _, n in matching_statistics(index, coded, window):
        full = n >= window
        which.append(w[full])
        start.append(s[full])
        low.append(least[group[a[full]]])
    which, start, low = np.concatenate(which), np.concatenate(start), np.concatenate(low)
    order = np.lexsort((start, which))
    which, start, low = which[order], start[order], low[order]
    if not len(which):
        return []
    cut = np.flatnonzero(np.concatenate(([True], (which[1:] != which[:-1]) | (start[1:] != start[:-1] + 1) | (low[1:] != low[:-1]))))
    size = np.diff(np.concatenate((cut, [len(which)])))
    return list(zip(which[cut].tolist(), start[cut].tolist(), size.tolist(), low[cut].tolist(), strict=True))


_RUNS = "anchor long, c1 long, c2 long, at int, n int, least long"


def _search(window: int):
    """Rows sorted by shard -> runs of windows with their least document; one index a shard."""

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def done() -> Iterator[pa.RecordBatch]:
            rows = pa.Table.from_batches(held).combine_chunks()
            found = shard_runs(rows.column("content").to_pylist(), rows.column("least").to_numpy(), rows.column("own").to_numpy(), window)
            if found:
                which, at, n, least = (np.array(x) for x in zip(*found, strict=True))
                keys = [pc.take(rows.column(c), pa.array(which)).combine_chunks() for c in ("anchor", "c1", "c2")]
                yield pa.RecordBatch.from_arrays([*keys, pa.array(at, pa.int32()), pa.array(n, pa.int32()), pa.array(least, pa.int64())], ["anchor", "c1", "c2", "at", "n", "least"])

        now = None
        for batch in batches:
            if not batch.num_rows:
                continue
            keys = np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in ("shard", "chunk")], axis=1)
            cuts = [0, *(np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1).tolist(), len(keys)]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if now is not None and now != tuple(keys[a]):
                    yield from done()
                    held = []
                now = tuple(keys[a])
                held.append(batch.slice(a, b - a))
        if held:
            yield from done()

    return run


def _strike(window: int, texts: bool):
    """Candidate documents with the runs of windows to remove -> counts and the digest of what is kept, or with ``texts`` the id and what is kept."""

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in pieces(batches, "text"):
            out = []
            for text, doc_id, runs in zip(utf8(part.column("text")), part.column("doc_id").to_pylist(), part.column("runs").to_pylist(), strict=True):
                words = text.split()
                edge = np.zeros(len(words) + 1, np.int64)
                for r in runs:
                    edge[r["at"]] += 1
                    edge[r["at"] + r["n"] - 1 + window] -= 1
                keep = np.cumsum(edge[:-1]) == 0
                kept = b" ".join(w for w, k in zip(words, keep.tolist(), strict=True) if k)
                out.append((doc_id, kept.decode()) if texts else (doc_id, len(words), len(words) - int(keep.sum()), hashlib.sha256(kept).hexdigest()))
            kinds = {"doc_id": pa.int64(), "kept": pa.string()} if texts else {"doc_id": pa.int64(), "n_words": pa.int64(), "n_removed": pa.int64(), "kept_sha256": pa.string()}
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds.values(), strict=True)], list(kinds))

    return run


def repeated(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", window: int = WINDOW, shard_words: int = SHARD_WORDS) -> tuple[DataFrame, DataFrame, DataFrame]:
    """``(survey, candidates, runs)``: all rows with their word counts; those with a passage to remove, with text; the runs to remove of each.

    A window (``window`` consecutive words) is to be removed if its words also start
    in a document of smaller doc_id; a null doc_id counts as the smallest. Every
    window belongs to the anchor of least hash in it, and only spans round anchors
    that two documents share are looked at. Equal spans are combined first; then
    each shard of anchors indexes its distinct spans and streams them against the
    index. A hot anchor's spans are dealt to chunks with an index each, and streamed
    against every chunk: memory stays bounded and no window is lost.
    """
    whole = F.coalesce(F.col(text).cast("string"), F.lit(""))
    base = docs.select(F.coalesce(F.col(doc_id).cast("long"), F.lit(LOWEST)).alias("did"), F.xxhash64(whole).alias("th"), F.col(doc_id).cast("long").alias("doc_id"), whole.alias("text"))
    survey = materialise(base.mapInArrow(_survey(window), _PASS), "survey")
    places = survey.select("did", "th", F.explode(F.arrays_zip("anchor", "first", "last")).alias("s")).select("did", "th", "s.*")
    shared = materialise(places.groupBy("anchor").agg(F.min("did").alias("lo"), F.max("did").alias("hi")).where("lo < hi").select("anchor"), "shared")
    mine = places.join(shared, "anchor").groupBy("did", "th").agg(F.collect_set(F.struct("anchor", "first", "last")).alias("spans"))
    found = materialise(base.join(materialise(mine, "spans"), ["did", "th"]), "candidates")
    contents = found.mapInArrow(_spans(window, True), "anchor long, c1 long, c2 long, did long, content binary")
    distinct = materialise(contents.groupBy("anchor", "c1", "c2", "content").agg(F.min("did").alias("least")), "contents")
    length = F.length("content") - F.length(F.translate(F.decode("content", "UTF-8"), " ", "").cast("binary")) + 1
    sizes = materialise(distinct.groupBy("anchor").agg(F.sum(length).alias("words")), "sizes")
    total = sizes.agg(F.sum("words")).first()[0] or 0
    shards = max(1, -(-total // shard_words))
    cold = F.pmod(F.xxhash64("anchor"), F.lit(shards))
    hot = sizes.where(F.col("words") > 2 * shard_words).select("anchor", F.ceil(F.col("words") / shard_words).cast("int").alias("chunks"))
    dealt = distinct.join(hot, "anchor", "left").withColumn("home", F.pmod(F.col("c1"), F.coalesce("chunks", F.lit(1))).cast("long"))
    dealt = dealt.withColumn("chunk", F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce("chunks", F.lit(1)).cast("long") - 1)))
    dealt = dealt.select("anchor", "c1", "c2", "content", "least", F.when(F.col("chunks").isNull(), cold).otherwise(F.col("anchor")).alias("shard"), F.when(F.col("chunks").isNull(), F.lit(-1)).otherwise(F.col("chunk")).cast("long").alias("chunk"), (F.col("home") == F.col("chunk")).alias("own"))
    matched = materialise(dealt.repartition("shard", "chunk").sortWithinPartitions("shard", "chunk").mapInArrow(_search(window), _RUNS), "runs")
    # a content that stands in one document only can still hold windows of smaller ones, so members are matched to all runs
    member = found.mapInArrow(_spans(window, False), "anchor long, c1 long, c2 long, did long, th long, first int")
    hits = member.join(matched, ["anchor", "c1", "c2"]).where("least < did")
    runs = materialise(hits.groupBy("did", "th").agg(F.collect_set(F.struct((F.col("first") + F.col("at")).alias("at"), "n")).alias("runs")), "hits")
    return survey, found, runs


def strike(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", window: int = WINDOW, shard_words: int = SHARD_WORDS) -> DataFrame:
    """``doc_id, n_words, n_removed, kept_sha256`` of every row: what is left without repeated passages.

    Null and short texts lose nothing; rows that repeat an id are one document and
    never remove each other's passages; an empty table gives no rows.
    """
    survey, found, runs = repeated(docs, doc_id, text, window, shard_words)
    struck = found.join(runs, ["did", "th"]).select("doc_id", "text", "runs").mapInArrow(_strike(window, False), "doc_id long, n_words long, n_removed long, kept_sha256 string")
    rest = survey.join(runs.select("did", "th"), ["did", "th"], "left_anti")
    return rest.select("doc_id", "n_words", F.lit(0).cast("long").alias("n_removed"), F.col("sha").alias("kept_sha256")).union(struck)


def kept_texts(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", window: int = WINDOW) -> DataFrame:
    """``doc_id, kept`` of the rows that lose words: the words that stay."""
    _, found, runs = repeated(docs, doc_id, text, window)
    return found.join(runs, ["did", "th"]).select("doc_id", "text", "runs").mapInArrow(_strike(window, True), "doc_id long, kept string")
