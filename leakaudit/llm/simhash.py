"""SimHash near-duplicates by deletion-variant signatures."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from leakaudit.llm.common import lean, packed, pieces, utf8
from leakaudit.operators.components import connected_components
from leakaudit.runtime import BROADCAST_ROWS, batch_rows, materialise

SHINGLE = 4
MOST_BITS = 4
#: Segments as (lowest bit, bits): of 4 differing bits in three segments, one segment holds at most one.
SEGMENTS = ((0, 21), (21, 21), (42, 22))
EXACT = 31
#: A bucket of more fingerprints is cut into chunks, and every pair of chunks is a group of its own.
CHUNK = 4096
#: Buckets of at most so many are compared many at a time.
FEW = 32


def fingerprint(words: list[bytes], shingle: int = SHINGLE) -> int:
    """The 64-bit SimHash of a word list; 0 without words."""
    if not words:
        return 0
    line = b" ".join(words)
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(line, 42)
    ends = np.cumsum([len(w) + 1 for w in words])
    starts = np.concatenate(([0], ends[:-1]))[: len(words) - shingle + 1].tolist()
    stops = (ends[shingle - 1 :] - 1).tolist()
    digest = xxhash.xxh64_intdigest
    hashes = np.fromiter((digest(line[a:b], 42) for a, b in zip(starts, stops, strict=True)), np.uint64, len(starts))
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 8192):
        part = hashes[at : at + 8192].astype("<u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<u8")[0])


def _key(doc_id: Column, text: Column) -> Column:
    """What tells rows apart: a digest of doc_id and text, never null. Rows that repeat both share it."""
    return F.unhex(F.sha2(F.concat(F.coalesce(doc_id.cast("string"), F.lit("")), F.when(text.isNull(), "-").otherwise("/"), F.coalesce(text, F.lit(""))), 256))


def fingerprints(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shingle: int = SHINGLE, keyed: bool = False) -> DataFrame:
    """``doc_id, fp`` (signed 64 bits) of every row; ASCII capitals are lowered, a null text has no words. ``keyed`` adds ``key``, see ``_key``."""

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in pieces(batches, "text"):
            found = np.array([fingerprint(x.lower().split(), shingle) for x in utf8(part.column("text"))], np.uint64)
            also = {"key": part.column("key")} if keyed else {}
            yield pa.RecordBatch.from_pydict({"doc_id": part.column("doc_id"), "fp": pa.array(found.view(np.int64)), **also})

    also = [_key(F.col(doc_id).cast("long"), F.col(text).cast("string")).alias("key")] if keyed else []
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"), *also)
    return rows.mapInArrow(run, "doc_id long, fp long" + ", key binary" * keyed)


def variants(fps: DataFrame) -> DataFrame:
    """``key, fp``: the exact value and every one-wildcard value of each segment, 67 rows per fingerprint.

    A key holds the segment's number, the wildcard's place (``EXACT``: none) and
    the segment's bits, the wildcard's set to zero.
    """
    keys = []
    for number, (low, bits) in enumerate(SEGMENTS):
        part = F.shiftrightunsigned("fp", low).bitwiseAND(F.lit((1 << bits) - 1))
        head = lambda place, n=number: F.lit((n << 27) | (place << 22))
        keys.append((head(EXACT).bitwiseOR(part)).cast("int"))
        keys += [(head(p).bitwiseOR(part.bitwiseAND(F.lit(((1 << bits) - 1) & ~(1 << p))))).cast("int") for p in range(bits)]
    return fps.select(F.explode(F.array(*keys)).alias("key"), "fp")


def _tree(members: np.ndarray) -> list[tuple[int, int]]:
    """Edges of a binary tree over ``members``: few at any one node, few levels."""
    return [(int(members[i]), int(members[(i - 1) // 2])) for i in range(1, len(members))]


def link(left: np.ndarray, right: np.ndarray | None, bits: int = MOST_BITS) -> list[tuple[int, int]]:
    """Edges that join what pairs of at most ``bits`` differing bits join: among ``left``, or between the two sides.

    Breadth first with the unreached kept apart: a dense group costs one pass, and
    the edges of a group are a tree, never all its pairs.
    """
    every = left if right is None else np.concatenate((left, right))
    side = np.zeros(len(every), bool)
    if right is not None:
        side[len(left) :] = True
    rest, edges = np.arange(len(every)), []
    while len(rest) > 1:
        group, front, rest = [rest[:1]], list(rest[:1]), rest[1:]
        while front and len(rest):
            at = front.pop()
            near = np.bitwise_count(every[rest] ^ every[at]) <= bits
            if right is not None:
                near &= side[rest] != side[at]
            if near.any():
                group.append(rest[near])
                front.extend(rest[near])
                rest = rest[~near]
        if len(group) > 1:
            edges += _tree(every[np.concatenate(group)].view(np.int64))
    return edges


def _bucket(key: int, fps: np.ndarray, halves: np.ndarray | None, bits: int) -> list[tuple[int, int]]:
    """A bucket without wildcard links all its members; one with a wildcard only the two values of that bit."""
    place, (low, _) = (key >> 22) & 31, SEGMENTS[key >> 27]
    if place == EXACT:
        return link(fps, None, bits) if halves is None else link(fps[~halves], fps[halves], bits)
    bit = (fps >> np.uint64(low + place)) & np.uint64(1) == 1
    if halves is None:
        return link(fps[~bit], fps[bit], bits) if bit.any() and not bit.all() else []
    return [e for one in (bit, ~bit) if (one & halves).any() and (~one & ~halves).any() for e in link(fps[~one & ~halves], fps[one & halves], bits)]


def _shifted(rows: np.ndarray, bits: int) -> list[tuple[int, int, int]]:
    """The links of many small buckets at once: each row against the next one, the next but one, and so on."""
    key, fp, out = rows[:, 0], np.ascontiguousarray(rows[:, 3]).view(np.uint64), []
    place, low = (key >> 22) & 31, np.array([x for x, _ in SEGMENTS])[key >> 27]
    shift = np.where(place == EXACT, 0, low + place).astype(np.uint64)
    for d in range(1, FEW):
        same = np.flatnonzero(key[d:] == key[:-d])
        if not len(same):
            break
        differ = fp[same] ^ fp[same + d]
        near = (np.bitwise_count(differ) <= bits) & ((place[same] == EXACT) | ((differ >> shift[same]) & np.uint64(1) == 1))
        out += [(0, a, b) for a, b in zip(fp[same[near]].view(np.int64).tolist(), fp[same[near] + d].view(np.int64).tolist(), strict=True)]
    return out


SCHEMA = "kind int, a long, b long"


def _scan(bits: int, chunk: int):
    """Rows sorted by (key, pair) -> edges (kind 0), or the members of a bucket of over ``chunk`` (kind 1: key, fingerprint)."""

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def done(rows: np.ndarray) -> pa.RecordBatch | None:
            # rows: key, pair, half, fp; whole buckets only
            starts = np.flatnonzero(np.concatenate(([True], (rows[1:, 0] != rows[:-1, 0]) | (rows[1:, 1] != rows[:-1, 1]))))
            stops = np.concatenate((starts[1:], [len(rows)]))
            sizes = stops - starts
            small = np.repeat((sizes <= FEW) & (rows[starts, 1] < 0), sizes)
            out: list[tuple[int, int, int]] = _shifted(rows[small], bits) if small.any() else []
            for a, b in zip(starts[sizes > 1].tolist(), stops[sizes > 1].tolist(), strict=True):
                key, pair = int(rows[a, 0]), int(rows[a, 1])
                if small[a]:
                    continue
                if pair < 0 and b - a > chunk:
                    out += [(1, key, x) for x in rows[a:b, 3].tolist()]
                else:
                    half = rows[a:b, 2]
                    out += [(0, *e) for e in _bucket(key, rows[a:b, 3].view(np.uint64), half == 1 if half.any() else None, bits)]
            if out:
                k, x, y = zip(*out, strict=True)
                return pa.RecordBatch.from_arrays([pa.array(k, pa.int32()), pa.array(x, pa.int64()), pa.array(y, pa.int64())], ["kind", "a", "b"])
            return None

        for batch in batches:
            if not batch.num_rows:
                continue
            rows = np.stack([c.cast(pa.int64()).to_numpy(zero_copy_only=False) for c in batch.columns], axis=1)
            last = np.flatnonzero((rows[:, 0] != rows[-1, 0]) | (rows[:, 1] != rows[-1, 1]))
            cut = int(last[-1]) + 1 if len(last) else 0
            if cut == 0 and held and not (held[-1][-1, :2] == rows[-1, :2]).all():
                if (found := done(np.concatenate(held))) is not None:
                    yield found
                held = [rows]
            elif cut == 0:
                held.append(rows)
            else:
                if (found := done(np.concatenate([*held, rows[:cut]]))) is not None:
                    yield found
                held = [rows[cut:]]
        if held and (found := done(np.concatenate(held))) is not None:
            yield found

    return run


def edges(fps: DataFrame, bits: int = MOST_BITS, chunk: int = CHUNK) -> DataFrame:
    """``a, b``: edges whose paths join exactly the distinct fingerprints ``fps`` that links of at most ``bits`` bits join.

    Buckets are sorted runs of one key. One with over ``chunk`` members isn't
    worked on in place: its members are dealt into chunks and every pair of chunks
    becomes a bucket of at most twice that size, so memory is bounded and no link is lost.
    """
    scan = _scan(bits, chunk)
    none = lambda df: df.select("key", F.lit(-1).cast("long").alias("pair"), F.lit(0).alias("half"), "fp")
    first = materialise(none(variants(fps)).repartition("key").sortWithinPartitions("key").mapInArrow(scan, SCHEMA), "links")
    late = first.where("kind = 1").select(F.col("a").cast("int").alias("key"), F.col("b").alias("fp"))
    if late.isEmpty():
        return first.select("a", "b")
    cuts = late.groupBy("key").agg(F.ceil(F.count(F.lit(1)) / chunk).cast("int").alias("cuts"))
    dealt = late.join(cuts, "key").withColumn("part", F.pmod(F.xxhash64("fp"), F.col("cuts")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("cuts") - 1)).alias("other")
    pairs = dealt.select("key", "fp", "part", "cuts", other).select(
        "key", (F.least("part", "other").cast("long") * F.col("cuts") + F.greatest("part", "other")).alias("pair"), (F.col("part") > F.col("other")).cast("int").alias("half"), "fp")
    second = pairs.repartition("key", "pair").sortWithinPartitions("key", "pair").mapInArrow(scan, SCHEMA)
    return first.where("kind = 0").select("a", "b").union(materialise(second, "links").select("a", "b"))


def _classes(rows: DataFrame, first: Column, bits: int) -> DataFrame:
    """``fp, first``: every fingerprint of ``rows`` with the least ``first`` over all rows whose fingerprints it reaches."""
    names = materialise(rows.groupBy("fp").agg(F.min(first).alias("low")), "distinct")
    found = connected_components(edges(names.select("fp"), bits))
    joined = names.join(found, names["fp"] == found["node"], "left").select("fp", "low", F.coalesce("component", "fp").alias("root"))
    least = joined.groupBy("root").agg(F.min("low").alias("first"))
    return materialise(joined.join(least, "root").select("fp", "first"), "roots")


def near_groups(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shingle: int = SHINGLE, bits: int = MOST_BITS) -> DataFrame:
    """One row per row of ``docs``: ``doc_id, fp, component_id``, the smallest doc_id reachable over links of at most ``bits`` bits.

    Copies meet in one fingerprint first, so the links are between different
    fingerprints only. A text without words has fingerprint 0 and is linked like
    any other. A null doc_id never names a component unless all its ids are null.
    Repeated rows each get their row. No rows: none.
    """
    with batch_rows(docs.sparkSession, 2000):
        rows = materialise(fingerprints(docs, doc_id, text, shingle), "fps")
    table = _classes(rows, F.col("doc_id"), bits).select("fp", F.col("first").alias("component_id"))
    return rows.join(table, "fp").select("doc_id", "fp", "component_id")


def keep_one(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shingle: int = SHINGLE, bits: int = MOST_BITS) -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns: of each group exactly one, that of least doc_id (null last).

    Groups are told apart by fingerprints, rows by a digest of doc_id and text:
    unlike texts under one doc_id, or without one, each stay. Of rows that share a
    doc_id within a group the one of least digest stays; of rows that repeat both,
    any one. Texts aren't shuffled where the digests of the dropped rows are few
    enough to be broadcast; beyond that bound they are joined.
    """
    spark = docs.sparkSession
    with batch_rows(spark, 2000):
        rows = materialise(fingerprints(docs, doc_id, text, shingle, keyed=True), "fps")
    once = rows.groupBy("doc_id", "fp", "key").agg(F.count(F.lit(1)).alias("n"))
    table = _classes(rows, F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "key"), bits).select("fp", F.col("first.key").alias("stays"))
    judged = materialise(once.join(table, "fp").where("key <> stays or n > 1").select("key", (F.col("key") == F.col("stays")).alias("stays")), "judged")
    gone, repeated = judged.where("not stays").select("key"), judged.where("stays").select("key")
    each = docs.select(packed(docs).alias("_row"), _key(F.col(doc_id).cast("long"), F.col(text).cast("string")).alias("key"))
    few = lambda keys: F.broadcast(keys) if keys.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else keys
    left = each.join(few(gone), "key", "left_anti")
    if not repeated.isEmpty():
        repeated = few(repeated)
        left = left.join(repeated, "key", "left_anti").union(left.join(repeated, "key", "left_semi").dropDuplicates(["key"]))
    return left.select("_row.*")
