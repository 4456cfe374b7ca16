"""The count target: a smoothed context model whose logits, moments and entropies have closed forms."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from leakaudit.operators.tokens import context
from leakaudit.runtime import lookup, materialise

ALPHA = 0.01
CHUNK = 16
#: A context, or a pair of context and token, with at least this share of the training tokens is heavy; a layer has 1 / HEAVY of them at most.
HEAVY = 1e-3


@dataclass
class CountTarget:
    """``counts`` (layer, ctx, tok, n), ``contexts`` (layer, ctx, n_c, d_c, s1, s2, e1, e2, plogp), ``vocabulary`` size and smoothing.

    ``heavy``: the count from which a context or a pair is heavy.
    """

    counts: DataFrame
    contexts: DataFrame
    vocabulary: DataFrame
    alpha: float = ALPHA
    heavy: float = float("inf")


def chunk_digit(salt: str = ""):
    return F.substring(F.md5(F.concat(F.lit(salt), F.col("sample_id").cast("string"), F.lit("/"), F.expr(f"cast((pos - 1) div {CHUNK} as string)"))), 1, 1)


def exposed(tokens: DataFrame, sixteenths: int = 1) -> DataFrame:
    """The tokens of the chunks that the target is trained on: so many sixteenths of all, by a digest of sample and chunk."""
    return tokens if sixteenths >= 16 else tokens.where(chunk_digit() < F.lit("0123456789abcdef"[sixteenths]))


def count_rows(tokens: DataFrame, layers: tuple[int, ...], needed: DataFrame | None = None) -> DataFrame:
    """``layer, ctx, tok, n``; the map side combines, so a frequent context costs one row a task.

    With ``needed`` (layer, ctx), other contexts are never counted: the stream is semi-joined first.
    """
    each = F.array(*[F.struct(F.lit(k).alias("layer"), context(k).alias("ctx")) for k in layers])
    rows = tokens.select("key", F.explode(each).alias("c")).select("c.layer", "c.ctx", F.col("key").alias("tok"))
    if needed is not None:
        rows = lookup(rows, materialise(needed.select("layer", "ctx").distinct(), "needed"), ["layer", "ctx"], "left_semi")
    return rows.groupBy("layer", "ctx", "tok").agg(F.count(F.lit(1)).alias("n"))


def moments(counts: DataFrame, alpha: float = ALPHA) -> DataFrame:
    """One row per context instead of a vocabulary-wide vector: totals and sums over the seen continuations.

    With D = ln(n + a) - ln(a), zero for everything unseen: s1 and s2 are the sums
    of D and its square; e1, e2 and plogp hold sums weighted by n + a, from which
    the model's own moments and its entropy follow.
    """
    d = F.log(F.col("n") + alpha) - F.log(F.lit(alpha))
    mass = F.col("n") + alpha
    return counts.groupBy("layer", "ctx").agg(
        F.sum("n").alias("n_c"), F.count(F.lit(1)).alias("d_c"), F.sum(d).alias("s1"), F.sum(d * d).alias("s2"),
        F.sum(mass * d).alias("e1"), F.sum(mass * d * d).alias("e2"), F.sum(mass * F.log(mass)).alias("plogp"))


def train(tokens: DataFrame, sixteenths: int = 1, layers: tuple[int, ...] = (1,), alpha: float = ALPHA, needed: DataFrame | None = None) -> CountTarget:
    """The target of the member samples among ``tokens``.

    The vocabulary is that of the members at full exposure, plus one slot.
    ``needed`` (layer, ctx) names the contexts that somebody will ask for, where
    these are few: the token stream is semi-joined with them before it is counted.
    """
    members = tokens.where("is_member")
    vocabulary = members.agg((F.count_distinct("key") + 1).alias("v"))
    shown = exposed(members, sixteenths)
    return _made(materialise(count_rows(shown, layers, needed), "counts"), materialise(vocabulary, "vocabulary"), alpha)


def _made(counts: DataFrame, vocabulary: DataFrame, alpha: float) -> CountTarget:
    most = counts.groupBy("layer").agg(F.sum("n").alias("n")).agg(F.max("n")).first()[0] or 0
    return CountTarget(counts, materialise(moments(counts, alpha), "contexts"), vocabulary, alpha, max(2.0, HEAVY * most))


def known(counts: DataFrame, layer: int, vocabulary: int, alpha: float = ALPHA) -> CountTarget:
    """The target of one layer's written counts (``ctx, tok, n``) and the size of the vocabulary."""
    size = counts.sparkSession.range(1).select(F.lit(vocabulary).cast("long").alias("v"))
    return _made(counts.select(F.lit(layer).alias("layer"), "ctx", "tok", "n"), size, alpha)


def forward(tokens: DataFrame, target: CountTarget, layers: tuple[int, ...] = (1,)) -> DataFrame:
    """Token statistics of one pass: ``KEEP, pos, t, key, weight, kind, layer, logp, z, z_model, entropy, act``.

    All layers come from one explosion, then the contexts and the counts are joined.
    Layer 0 has one context for every token, and others follow Zipf's law: heavy
    contexts and heavy pairs, at most 1 / HEAVY a layer whatever the input, are
    broadcast, and their tokens spread over salts that the shuffled joins don't
    match, so no key holds more than about HEAVY of the training tokens.
    ``act`` are the eight activations.
    """
    keep = [c for c in ("sample_id", "slice", "is_member", "role", "pos", "t", "key", "kind", "weight") if c in tokens.columns]
    each = F.array(*[F.struct(F.lit(k).alias("layer"), context(k).alias("ctx")) for k in layers])
    rows = tokens.select(*keep, F.explode(each).alias("c")).select(*keep, "c.layer", "c.ctx")
    counts = target.counts.select("layer", "ctx", F.col("tok").alias("key"), "n")
    about = ("n_c", "d_c", "s1", "s2", "e1", "e2", "plogp")
    spread = 1 + F.pmod(F.xxhash64("sample_id", "pos"), F.lit(1 << 20)).cast("int")
    big = target.contexts.where(F.col("n_c") >= target.heavy).select("layer", "ctx", F.struct(*about).alias("_big"))
    rows = rows.join(F.broadcast(big), ["layer", "ctx"], "left").withColumn("_salt", F.when(F.col("_big").isNull(), 0).otherwise(spread))
    small = target.contexts.where(F.col("n_c") < target.heavy).select("layer", "ctx", F.lit(0).alias("_salt"), F.struct(*about).alias("_small"))
    rows = rows.join(small, ["layer", "ctx", "_salt"], "left").withColumn("_m", F.coalesce("_big", "_small")).select(*keep, "layer", "ctx", "_m.*")
    often = counts.where(F.col("n") >= target.heavy).withColumnRenamed("n", "_often")
    rows = rows.join(F.broadcast(often), ["layer", "ctx", "key"], "left").withColumn("_salt", F.when(F.col("_often").isNull(), 0).otherwise(spread))
    rare = counts.where(F.col("n") < target.heavy).select("layer", "ctx", "key", F.lit(0).alias("_salt"), F.col("n").alias("_rare"))
    rows = rows.join(rare, ["layer", "ctx", "key", "_salt"], "left").withColumn("n", F.coalesce("_often", "_rare")).crossJoin(F.broadcast(target.vocabulary))
    a = F.lit(target.alpha)
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("double")
    n, n_c, d_c, s1, s2, v = zero("n"), zero("n_c"), zero("d_c"), zero("s1"), zero("s2"), F.col("v").cast("double")
    delta = F.log(n + a) - F.log(a)
    whole = n_c + a * v
    logp = F.log(n + a) - F.log(whole)
    variance = F.greatest(F.lit(0.0), s2 / v - F.pow(s1 / v, F.lit(2.0)))
    z = F.when(variance > 1e-12, (delta - s1 / v) / F.sqrt(variance)).otherwise(F.lit(0.0))
    mean_m, square_m = zero("e1") / whole, zero("e2") / whole
    variance_m = F.greatest(F.lit(0.0), square_m - mean_m * mean_m)
    z_model = F.when(variance_m > 1e-12, (delta - mean_m) / F.sqrt(variance_m)).otherwise(F.lit(0.0))
    # entropy: seen continuations from their sums, the unseen ones all alike
    seen = (zero("plogp") - (n_c + a * d_c) * F.log(whole)) / whole
    entropy = -seen - (v - d_c) * (a / whole) * F.log(a / whole)
    act = F.array(delta, F.log(n_c + 1), logp, z, entropy, (n > 0).cast("double"), (n_c > 0).cast("double"), F.log(d_c + 1))
    return rows.select(*keep, "layer", logp.alias("logp"), (F.log(a) + s1 / v).alias("mu"), F.sqrt(variance).alias("sigma"), z.alias("z"), z_model.alias("z_model"), entropy.alias("entropy"), act.alias("act"))


def neighbours(tokens: DataFrame, copies: int = 5, swap: float = 0.3, seed: int = 0) -> DataFrame:
    """``copies`` augmented copies of every sample besides itself (copy 0): some adjacent tokens are swapped, which by a digest of sample, copy and place.

    Pairs (2k - 1, 2k) of scored tokens are swapped as a whole, so a copy keeps all
    tokens. Contexts are formed anew.
    """
    each = tokens.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies))))
    pair = F.expr("(t + 1) div 2")
    size = Window.partitionBy("sample_id", "copy")
    bound = F.lit(f"{round(swap * 256):02x}")
    digest = F.substring(F.md5(F.concat_ws("/", F.lit(str(seed)), "sample_id", "copy", pair)), 1, 2)
    swapped = (F.col("copy") > 0) & (digest < bound) & ~((F.col("t") % 2 == 1) & (F.col("t") == F.max("t").over(size)))
    each = each.withColumn("t", F.when(swapped, F.when(F.col("t") % 2 == 1, F.col("t") + 1).otherwise(F.col("t") - 1)).otherwise(F.col("t")))
    order = Window.partitionBy("sample_id", "copy").orderBy("t")
    for back in range(1, 5):
        each = each.withColumn(f"prev{back}", F.lag("key", back, "^").over(order))
    return each
