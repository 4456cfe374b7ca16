"""Balanced, leakage-safe splits and the proofs that they are."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from leakaudit.functions import lexer
from leakaudit.operators import rows
from leakaudit.operators.components import connected_components
from leakaudit.operators.tokens import _listed, _numbers
from leakaudit.runtime import batch_rows, lookup, materialise, running


def balance(samples: DataFrame, by: tuple[str, ...] = ("slice", "role"), n: int | None = None) -> DataFrame:
    """As many members as others in each group of ``by``: the first by content key, ``n`` of each at most.

    Only keys are ordered, range by range; the last key that still belongs is one
    row a group and class, and the samples are compared with it where they are.
    """
    keys = samples.groupBy(*by, "is_member", "content_key", "sample_id").agg(F.count(F.lit(1)).alias("one"))
    ranked = running(keys, [*by, "is_member"], ["content_key", "sample_id"], ["one"])
    sizes = ranked.groupBy(*by).agg(F.least(F.sum(F.when(F.col("is_member"), F.col("one")).otherwise(0)), F.sum(F.when(F.col("is_member"), 0).otherwise(F.col("one")))).alias("_least"))
    bound = F.col("_least") if n is None else F.least(F.col("_least"), F.lit(n))
    last = ranked.join(F.broadcast(sizes), list(by)).where(F.col("before_one") < bound).groupBy(*by, "is_member").agg(F.max(F.struct("content_key", "sample_id")).alias("_last"))
    return samples.join(F.broadcast(last), [*by, "is_member"]).where(F.struct("content_key", "sample_id") <= F.col("_last")).select(*samples.columns)


def overlap(a: DataFrame, b: DataFrame, on: str = "content_key") -> DataFrame:
    """The keys that both sides hold; none if they are apart."""
    return a.select(on).intersect(b.select(on))


def long_lines(samples: DataFrame, min_len: int = 40) -> DataFrame:
    """``sample_id, line`` (a digest) of the distinct lines of at least ``min_len`` characters."""
    lines = F.filter(F.split("text", "\n"), lambda x: F.length(x) >= min_len)
    return samples.select("sample_id", F.explode(F.array_distinct(lines)).alias("x")).select("sample_id", F.md5("x").alias("line"))


def line_overlap(a: DataFrame, b: DataFrame, min_len: int = 40) -> DataFrame:
    """The samples of ``a`` that share a long line with one of ``b``."""
    return long_lines(a, min_len).join(long_lines(b, min_len).select("line"), "line", "left_semi").select("sample_id").distinct()


def line_groups(samples: DataFrame, min_len: int = 40) -> DataFrame:
    """``samples`` with ``group``: samples that share long lines, also by way of others, are one group, to be put on one side of a split.

    Each line joins its samples to the least of them only, so a line of many samples costs as many edges.
    """
    lines = long_lines(samples, min_len)
    least = lines.groupBy("line").agg(F.min("sample_id").alias("a"), F.count(F.lit(1)).alias("n")).where("n > 1").select("line", "a")
    return isolate(samples, lines.join(least, "line").select("a", F.col("sample_id").alias("b")).where("a <> b").distinct())


def _mixed(x: np.ndarray) -> np.ndarray:
    for shift, by in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(by)
    return x ^ (x >> np.uint64(31))


def _shingled(text: pa.Array, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Row and digest (64 bits) of the distinct runs of ``shingle`` words of lower-cased texts, in order of both."""
    row, word = _listed(pc.ascii_split_whitespace(text))
    full = pc.greater(pc.binary_length(word), 0)
    row, coded = row[full.to_numpy(zero_copy_only=False).astype(bool)], word.filter(full).dictionary_encode()
    size = max(0, len(row) - shingle + 1)
    one = np.fromiter(map(xxhash.xxh3_64_intdigest, coded.dictionary.to_pylist()), np.uint64, len(coded.dictionary))[_numbers(coded.indices)]
    digest = np.zeros(size, np.uint64)
    for k in range(shingle):
        digest = _mixed(digest * np.uint64(0x9E3779B97F4A7C15) + one[k : k + size])
    whole = row[:size] == row[len(row) - size :]
    row, digest = row[:size][whole], digest[whole].view(np.int64)
    order = np.lexsort((digest, row))
    row, digest = row[order], digest[order]
    fresh = np.concatenate(([True], (np.diff(row) != 0) | (np.diff(digest) != 0))) if len(row) else np.zeros(0, bool)
    return row[fresh], digest[fresh]


def _per_text(samples: DataFrame, run, out: str, tag: str) -> DataFrame:
    """What ``run`` makes of slices of ``sample_id`` and lower-cased ``text``, written once."""
    id_type = samples.schema["sample_id"].dataType.simpleString()
    with batch_rows(samples.sparkSession, rows.SAMPLES_AT_ONCE):
        return materialise(samples.where("text is not null").select("sample_id", F.lower("text").alias("text")).mapInArrow(run, out.format(id=id_type)), tag)


def _lists(row: np.ndarray, values: np.ndarray, size: int) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.searchsorted(row, np.arange(size + 1)).astype(np.int32)), pa.array(values))


def shingle_hashes(samples: DataFrame, shingle: int = 5) -> DataFrame:
    """``sample_id, hashes``: the distinct digests of each run of ``shingle`` lower-cased words, written once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in lexer.slices(batches):
            row, digest = _shingled(part.column("text"), shingle)
            made = pa.RecordBatch.from_arrays([part.column("sample_id"), _lists(row, digest, part.num_rows)], ["sample_id", "hashes"])
            yield made.filter(pc.greater(pc.list_value_length(made.column("hashes")), 0))

    return _per_text(samples, run, "sample_id {id}, hashes array<long>", "hashes")


#: Shingles that a worker counts together, and most frequent shingles that each worker holds.
SHINGLES_AT_ONCE, OFTEN = 4_000_000, 1_000_000


class Often:
    """The most frequent shingles and their counts."""

    def __init__(self, found: Iterable[pa.Table]):
        whole = pa.concat_tables(found)
        h, n = whole.column("h").to_numpy(), whole.column("n").to_numpy()
        order = np.argsort(h)
        self.h, self.n = h[order], n[order]

    def count(self, digest: np.ndarray) -> np.ndarray:
        if not len(self.h):
            return np.zeros(len(digest), np.int64)
        at = np.minimum(np.searchsorted(self.h, digest), len(self.h) - 1)
        return np.where(self.h[at] == digest, self.n[at], 0)


def _often(samples: DataFrame, shingle: int):
    """``Often`` for the workers: shingles that repeat among those counted together, from the least power of two that leaves at most ``OFTEN`` of them."""

    def repeated(held: list[np.ndarray]) -> pa.RecordBatch:
        h, n = np.unique(np.concatenate([np.zeros(0, np.int64), *held]), return_counts=True)
        return pa.RecordBatch.from_arrays([pa.array(h[n > 1]), pa.array(n[n > 1].astype(np.int64))], ["h", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for part in lexer.slices(batches):
            held.append(_shingled(part.column("text"), shingle)[1])
            size += len(held[-1])
            if size >= SHINGLES_AT_ONCE:
                yield repeated(held)
                held, size = [], 0
        yield repeated(held)

    found = materialise(_per_text(samples, run, "h long, n long", "repeated").groupBy("h").agg(F.sum("n").alias("n")), "often")
    power = F.floor(F.log2("n")).cast("int")
    least, size = 64, 0
    for r in found.groupBy(power.alias("p")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("p")).collect():  # 64 rows at most
        size += r.n
        if size > OFTEN:
            break
        least = r.p
    return rows._sent(Often, materialise(found.where(power >= least), "often"))


def _heads(samples: DataFrame, shingle: int, least: float) -> DataFrame:
    """``sample_id, set, n, prefix``: digest and size of each shingle set and its first shingles, rare ones before frequent ones."""
    often = _often(samples, shingle)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in lexer.slices(batches):
            row, digest = _shingled(part.column("text"), shingle)
            if not len(row):
                continue
            size = np.bincount(row, minlength=part.num_rows)
            last = np.cumsum(size)
            ids = np.flatnonzero(size)
            sets = pa.array([xxhash.xxh3_128_digest(digest[last[k] - size[k] : last[k]].tobytes()) for k in ids], pa.binary())
            order = np.lexsort((digest, often.value.count(digest), row))
            first = np.arange(len(row)) - (last - size)[row] < (size - np.ceil(np.round(least * size, 6)).astype(np.int64) + 1)[row]
            prefix = _lists(row[first], digest[order][first], part.num_rows).take(pa.array(ids))
            yield pa.RecordBatch.from_arrays([part.column("sample_id").take(pa.array(ids)), sets, pa.array(size[ids].astype(np.int32)), prefix], ["sample_id", "set", "n", "prefix"])

    return _per_text(samples, run, "sample_id {id}, set binary, n int, prefix array<long>", "heads")


#: How many places further on, in order of size, a set is compared first with others of a shingle where groups alone are asked for.
LINKS = (1, 2, 4, 8)
#: Up to so many ids go to every worker, a few bytes each.
IDS = 1_000_000


def near_copies(samples: DataFrame, shingle: int = 5, least: float = 0.8, linked: bool = False) -> DataFrame:
    """``a, b, jaccard``: pairs of samples whose shingle sets have a similarity of ``least`` or more, with a < b.

    Samples of equal sets are joined to their least id only. Different sets meet by
    prefix filtering: if two sets are that similar, the first few shingles of both
    in one order (size - ceil(least * size) + 1 of them) have one in common, so
    an equi-join on these misses no pair, whatever the order; rare shingles come
    first, so that common lines join few. The similarity is then exact, but for
    equal digests (64 bits a shingle) of unequal shingles.

    With ``linked``, pairs enough to join the same samples into the same groups, for
    ``isolate``: sets near in size are compared first, then all that share a first
    shingle and aren't in one group yet. A large group needn't list all its pairs.
    """
    heads = _heads(samples, shingle, least)
    same = heads.groupBy("set").agg(F.min("sample_id").alias("a"))
    copies = materialise(heads.select("sample_id", "set").join(same, "set").where("sample_id > a").select("a", F.col("sample_id").alias("b"), F.lit(1.0).alias("jaccard")), "copies")
    # ids alone decide which rows go on: neither prefixes nor texts are shuffled for that
    each = lookup(heads, copies.select(F.col("b").alias("sample_id")), ["sample_id"], "left_anti", rows=IDS).select("sample_id", "n", F.posexplode("prefix").alias("at", "h"))
    met = materialise(each.withColumn("_met", F.count(F.lit(1)).over(Window.partitionBy("h"))).where("_met > 1").drop("_met"), "met")

    def may(x: str, y: str) -> Column:
        # a shingle in common bounds the overlap: what stands before it in both, itself, and what can follow in both
        at, n = (lambda s: F.col(f"{s}.at")), (lambda s: F.col(f"{s}.n"))
        return F.least(at(x), at(y)) + F.least(n(x) - at(x), n(y) - at(y)) >= least / (1 + least) * (n(x) + n(y)) - 1e-6

    def alike(found: DataFrame) -> DataFrame:
        # the prefix that ends first holds all that the sets share up to its end; the other prefix holds those too, so they are counted here
        many = found.where(may("x", "y")).groupBy(*[F.col(f"{s}.{c}").alias(f"{s}_{c}") for s in "xy" for c in ("sample_id", "n")]).agg(F.count(F.lit(1)).alias("both"))
        rest = lambda n: F.ceil(F.round(least * F.col(n), 6)) - 1
        pairs = many.where(F.col("both") + F.greatest(rest("x_n"), rest("y_n")) >= least / (1 + least) * (F.col("x_n") + F.col("y_n")) - 1e-6)
        pairs = materialise(pairs.select(F.least("x_sample_id", "y_sample_id").alias("a"), F.greatest("x_sample_id", "y_sample_id").alias("b")), "pairs")
        asked = materialise(pairs.select(F.col("a").alias("sample_id")).union(pairs.select("b")).distinct(), "asked")
        sets = shingle_hashes(lookup(samples, asked, ["sample_id"], "left_semi", rows=IDS), shingle)
        left, right = (sets.select(F.col("sample_id").alias(c), F.col("hashes").alias(f"_{c}")) for c in "ab")
        whole = pairs.join(left, "a").join(right, "b")
        found = whole.select("a", "b", F.size(F.array_intersect("_a", "_b")).alias("both"), (F.size("_a") + F.size("_b")).alias("sum"))
        return materialise(found.select("a", "b", (F.col("both") / (F.col("sum") - F.col("both"))).alias("jaccard")).where(F.col("jaccard") >= least), "alike")

    first, left, apart = None, met, F.col("x.sample_id") < F.col("y.sample_id")
    if linked:
        order = Window.partitionBy("h").orderBy("n", "sample_id")
        one = F.struct("sample_id", "n", "at")
        ahead = met.select(one.alias("x"), F.array(*[F.lead(one, k).over(order) for k in LINKS]).alias("ys")).select("x", F.explode("ys").alias("y"))
        first = alike(ahead.where("y is not null"))
        named = met.join(connected_components(first).withColumnRenamed("node", "sample_id"), "sample_id", "left").withColumn("component", F.coalesce("component", "sample_id"))
        inside = Window.partitionBy("h")
        left = materialise(named.withColumns({"_low": F.min("component").over(inside), "_high": F.max("component").over(inside)}).where("_low <> _high").drop("_low", "_high"), "apart")
        apart = F.col("x.component") < F.col("y.component")
    x, y = left.alias("x"), left.alias("y")
    found = alike(x.join(y, (F.col("x.h") == F.col("y.h")) & apart))
    return (found if first is None else first.union(found)).union(copies)


def isolate(samples: DataFrame, pairs: DataFrame) -> DataFrame:
    """``samples`` with ``group``: samples joined by ``pairs`` (a, b) are one group, to be put on one side of a split."""
    groups = connected_components(pairs)
    lows = groups.groupBy("component").agg(F.min("node").alias("group"))
    named = groups.join(lows, "component").select(F.col("node").alias("sample_id"), "group")
    return samples.join(named, "sample_id", "left").withColumn("group", F.coalesce("group", "sample_id"))


def assign_grouped(samples: DataFrame, salt: str = "") -> DataFrame:
    """Membership and role by a digest of the group: near copies never face each other."""
    key = F.md5(F.concat(F.lit(salt), F.col("group").cast("string")))
    return samples.withColumn("is_member", F.substring(key, 1, 1) < "8").withColumn("role", F.when(F.substring(key, 2, 1) < "8", "shadow").otherwise("holdout"))
