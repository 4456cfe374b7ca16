"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree (native)."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from leakaudit.llm.common import WORD, packed
from leakaudit.runtime import lookup, materialise

WEIGHTS = (5, 2, 1)
SHARE = 1.5
MOST_TIMES = 2
#: A block aims at so many words and documents; a source has at most 2**16 blocks by default, so that one window can order them.
BLOCK_WORDS, BLOCK_DOCS, MOST_BLOCKS_LOG2 = 32768, 256, 16
#: Output shards: as many as give each some blocks, a power of two between these bounds (defaults of ``mix``; more shards and blocks make a larger tree).
BLOCKS_PER_SHARD, SHARDS, MOST_SHARDS = 16, 16, 4096


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def targets(sized: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST_TIMES) -> DataFrame:
    """One row per source: ``source, source_size, n_docs, idx, weight, target``.

    Sources by code point, null last, take ``weights`` in turn and share ``share``
    times all words. No target exceeds ``most`` times its source; what is above goes
    to the others by weight. In order of size over weight the capped ones come
    first, so the common level of the rest is found with two running sums.
    """
    order = Window.orderBy(F.col("source").isNull(), F.col("source"))
    src = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_docs"))
    src = src.withColumn("idx", F.row_number().over(order) - 1)
    src = src.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("idx") % len(weights) + 1).cast("int")))
    src = src.withColumn("_cap", most * F.col("source_size").cast("double"))
    every = Window.partitionBy()
    by = Window.orderBy(F.col("_cap") / F.col("weight"), "idx")
    before, after = by.rowsBetween(Window.unboundedPreceding, -1), by.rowsBetween(0, Window.unboundedFollowing)
    src = src.withColumn("_all", share * F.sum("source_size").over(every).cast("double"))
    src = src.withColumn("_level", (F.col("_all") - F.coalesce(F.sum("_cap").over(before), F.lit(0.0))) / F.sum("weight").over(after))
    src = src.withColumn("_level", F.min(F.when(F.col("_level") * F.col("weight") <= F.col("_cap"), F.struct((F.col("_cap") / F.col("weight")).alias("r"), F.col("idx").alias("i"), F.col("_level").alias("level")))).over(every)["level"])
    target = F.coalesce(F.least("_cap", F.col("_level") * F.col("weight")), F.col("_cap"))
    return src.select("source", "source_size", "n_docs", "idx", "weight", target.alias("target"))


def _let(value: Column, body) -> Column:
    """``body(value)`` with ``value`` computed once."""
    return F.transform(F.array(value), body)[0]


def hypergeometric(total: Column, marked: Column, drawn: Column, unit: Column) -> Column:
    """Marked ones among ``drawn`` of ``total`` (doubles), at quantile ``unit``: inversion over mean +- 12 deviations, or all of a small support."""
    one = F.lit(1.0)
    share = marked / F.greatest(total, one)
    spread = F.ceil(12 * F.sqrt(F.greatest(F.lit(0.0), drawn * share * (1 - share) * (total - drawn) / F.greatest(total - 1, one)))) + 6
    mode = F.floor((drawn + 1) * (marked + 1) / (total + 2))
    support = F.sequence(F.greatest(F.lit(0.0), drawn + marked - total, mode - spread).cast("long"), F.least(drawn, marked, mode + spread).cast("long"))

    def ratio(k: Column) -> Column:
        return (marked - k) * (drawn - k) / ((k + 1) * F.greatest(total - marked - drawn + k + 1, one))

    def walk(ks: Column) -> Column:
        mass = F.aggregate(ks, F.struct(one.alias("w"), F.lit(0.0).alias("s")), lambda a, k: F.struct((a["w"] * ratio(k)).alias("w"), (a["s"] + a["w"]).alias("s")), lambda a: a["s"])
        return _let(mass * unit, lambda goal: F.aggregate(
            ks, F.struct(one.alias("w"), F.lit(0.0).alias("s"), F.lit(-1).cast("long").alias("x")),
            lambda a, k: F.struct((a["w"] * ratio(k)).alias("w"), (a["s"] + a["w"]).alias("s"), F.when((a["x"] < 0) & (a["s"] + a["w"] >= goal), k).otherwise(a["x"]).alias("x")),
            lambda a: F.when(a["x"] < 0, F.element_at(ks, -1)).otherwise(a["x"]).cast("double")))

    return _let(support, walk)


def splitting_tree(quotas: DataFrame, shards: int = SHARDS, seed: int = 0) -> DataFrame:
    """``idx, shard, first, n``: which positions of each source's permuted blocks a shard gets.

    ``quotas`` has ``idx, quota``. The root holds all quotas; each node gives its
    left half of the shards as many blocks as their share, source by source a
    hypergeometric draw given what is left: the counts are distributed as if all
    blocks had been shuffled and dealt, and no block is looked at.
    """
    nodes = quotas.groupBy().agg(F.array_sort(F.collect_list(F.struct("idx", "quota"))).alias("all")).where(F.size("all") > 0).select(
        F.lit(0).alias("lo"), F.lit(shards).alias("hi"), F.col("all.idx").alias("ids"), F.transform("all", lambda x: x["quota"].cast("double")).alias("q"))
    for _ in range(math.ceil(math.log2(max(1, shards)))):
        half = F.floor((F.col("hi") - F.col("lo")) / 2).cast("int")
        every = F.aggregate("q", F.lit(0.0), lambda a, x: a + x)

        def deal(state: Column, marked: Column) -> Column:
            unit = (F.pmod(F.xxhash64(F.lit(seed), F.col("lo"), F.col("hi"), F.size(state["out"])), F.lit(1 << 52)) + 0.5) / float(1 << 52)
            return _let(hypergeometric(state["total"], marked, state["drawn"], unit), lambda d: F.struct(
                (state["total"] - marked).alias("total"), (state["drawn"] - d).alias("drawn"), F.array_append(state["out"], d).alias("out")))

        start = F.struct(every.alias("total"), F.floor(every * half / (F.col("hi") - F.col("lo"))).cast("double").alias("drawn"), F.array().cast("array<double>").alias("out"))
        nodes = nodes.withColumn("left", F.when(half > 0, F.aggregate("q", start, deal, lambda s: s["out"])))
        node = lambda lo, hi, q: F.struct(lo.alias("lo"), hi.alias("hi"), q.alias("q"))
        kids = F.when(half > 0, F.array(node(F.col("lo"), F.col("lo") + half, F.col("left")), node(F.col("lo") + half, F.col("hi"), F.zip_with("q", "left", lambda a, b: a - b)))).otherwise(
            F.array(node(F.col("lo"), F.col("hi"), F.col("q"))))
        nodes = nodes.select("ids", F.explode(kids).alias("k")).select("k.lo", "k.hi", "ids", "k.q")
    flat = nodes.select(F.col("lo").alias("shard"), F.explode(F.arrays_zip("ids", "q")).alias("z")).select(F.col("z.ids").alias("idx"), "shard", F.col("z.q").cast("long").alias("n"))
    upto = Window.partitionBy("idx").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    return flat.select("idx", "shard", F.coalesce(F.sum("n").over(upto), F.lit(0).cast("long")).alias("first"), "n")


def _blocked(rows: DataFrame, sources: DataFrame, doc_id: str, seed: int) -> DataFrame:
    """``rows`` with the index, size and target of their source, and the block a hash deals them to."""
    known = lookup(rows.withColumn("_none", F.col("_source").isNull()).withColumn("_source", F.coalesce("_source", F.lit(""))), sources, ["_source", "_none"])
    key = F.xxhash64(F.lit(seed), F.col(doc_id))
    return known.withColumn("_block", key.bitwiseAND(F.col("_blocks") - 1)).withColumn("_key", F.xxhash64(F.lit(seed + 1), F.col(doc_id)))


def mix(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST_TIMES, shards: int | None = None, seed: int = 7, keep: list[str] | None = None, blocks_log2: int = MOST_BLOCKS_LOG2, most_shards: int = MOST_SHARDS) -> DataFrame:
    """``row, size, source_size, target, draws, key``: each row of ``docs`` as a struct (of the columns ``keep``, or all), and what the mix takes of it.

    ``draws`` lists (epoch, shard, words): the row is read so often, from that
    shard, whole or up to so many words. Every epoch deals a source's blocks in a
    new order; whole epochs come first, the last one ends in the block where the
    target is reached, and in that block at the document and word, so a source's
    words differ from its target by rounding only. Reruns give the same.

    Bounds, by parameter: a source has up to 2**``blocks_log2`` blocks, which one
    task orders; the tree has a row for each of up to ``most_shards`` shards with the
    quotas of all sources, so sources are meant to be thousands at most.

    A null text has no words, a null source is a source; sources without words have
    target 0 and draw nothing. Rows that repeat a doc_id are dealt to one block each
    on its own; no rows give none.
    """
    sized = materialise(docs.select(F.col(doc_id).alias("doc_id"), F.col(source).cast("string").alias("source"), word_count(F.col(text).cast("string")).alias("size")), "sized")
    goal = F.greatest(F.lit(1.0), F.col("source_size") / BLOCK_WORDS, F.col("n_docs") / BLOCK_DOCS)
    src = materialise(targets(sized, weights, share, most).withColumn("_blocks", F.pow(F.lit(2.0), F.least(F.lit(float(blocks_log2)), F.ceil(F.log2(goal)).cast("double"))).cast("long")), "sources")
    keyed = src.select(F.coalesce("source", F.lit("")).alias("_source"), F.col("source").isNull().alias("_none"), F.col("idx").alias("_idx"), F.col("source_size").alias("_source_size"), F.col("target").alias("_target"), "_blocks")
    words = _blocked(sized.withColumnRenamed("source", "_source"), keyed, "doc_id", seed).groupBy("_idx", "_block").agg(F.sum("size").alias("words"))
    plan = lookup(words, src.select(F.col("idx").alias("_idx"), "source_size", F.round("target").cast("long").alias("goal")), ["_idx"]).where("source_size > 0 and goal > 0 and words > 0")
    turns = plan.withColumn("epoch", F.explode(F.sequence(F.lit(0).cast("long"), F.expr("(goal - 1) div source_size"))))
    within = Window.partitionBy("_idx", "epoch").orderBy(F.xxhash64(F.lit(seed + 2), F.col("epoch"), F.col("_block")), "_block")
    turns = turns.withColumn("rank", F.row_number().over(within)).withColumn("_upto", F.sum("words").over(within.rowsBetween(Window.unboundedPreceding, 0)))
    left = F.col("goal") - F.col("epoch") * F.col("source_size") - (F.col("_upto") - F.col("words"))
    drawn = turns.withColumn("take", F.least(F.col("words"), left)).where("take > 0")
    place = Window.partitionBy("_idx").orderBy("epoch", "rank")
    drawn = materialise(drawn.withColumn("place", F.row_number().over(place).cast("long")).select("_idx", "_block", "epoch", "place", "take", "words"), "draws")
    if shards is None:
        shards = min(most_shards, max(SHARDS, 1 << math.ceil(math.log2(max(1, drawn.count() / BLOCKS_PER_SHARD)))))
    tree = splitting_tree(drawn.groupBy(F.col("_idx").alias("idx")).agg(F.count(F.lit(1)).alias("quota")), shards, seed)
    dealt = tree.where("n > 0").select(F.col("idx").alias("_idx"), "shard", F.explode(F.expr("sequence(first + 1, first + n)")).alias("place"))
    blocks = drawn.join(dealt, ["_idx", "place"]).groupBy("_idx", "_block").agg(F.array_sort(F.collect_list(F.struct("epoch", "shard", F.when(F.col("take") < F.col("words"), F.col("take")).alias("take")))).alias("_takes"))
    blocks = materialise(blocks, "blocks")
    full = docs.select((packed(docs) if keep is None else F.struct(*keep)).alias("row"), F.col(doc_id).alias("_id"), F.col(source).cast("string").alias("_source"), word_count(F.col(text).cast("string")).alias("size"))
    rows = _blocked(full, keyed, "_id", seed).join(blocks, ["_idx", "_block"], "left")
    inner = Window.partitionBy("_idx", "_block").orderBy("_key", "_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("_before", F.coalesce(F.sum("size").over(inner), F.lit(0).cast("long")))
    part = lambda d: F.when(d["take"].isNull(), F.col("size")).otherwise(F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), d["take"] - F.col("_before"))))
    draws = F.filter(F.transform(F.coalesce("_takes", F.array().cast("array<struct<epoch:bigint,shard:int,take:bigint>>")), lambda d: F.struct(d["epoch"].alias("epoch"), d["shard"].alias("shard"), part(d).alias("words"))), lambda d: d["words"] > 0)
    return rows.select("row", "size", F.col("_source_size").alias("source_size"), F.col("_target").alias("target"), draws.alias("draws"), F.col("_key").alias("key"))


def mixed_rows(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: ``row`` (a struct) as often as it is drawn, with ``shard, epoch, words``, shuffled within its shard."""
    out = mix(docs, **options).withColumn("d", F.explode("draws"))
    order = F.xxhash64(F.lit(11), "d.shard", "d.epoch", "key")
    out = out.select("row", F.col("d.shard").alias("shard"), F.col("d.epoch").alias("epoch"), F.col("d.words").alias("words"), order.alias("order"))
    return out.repartition("shard").sortWithinPartitions("shard", "order").drop("order")
