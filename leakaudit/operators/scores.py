"""Membership scores; higher always means more likely a member."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BY = ("sample_id", "slice", "is_member", "role")


def sigmoid(z: Column) -> Column:
    return 1 / (1 + F.exp(-z))


def lowest(values: Column, k: float) -> Column:
    """The mean of the least k percent of an array, one at least."""
    m = F.greatest(F.lit(1), F.floor(F.size(values) * k / 100)).cast("int")
    return F.aggregate(F.slice(F.array_sort(values), 1, m), F.lit(0.0), lambda a, x: a + x) / m


def quantile(values: Column, q: float) -> Column:
    """The element at rank floor(q (n - 1)) of an array, from the least."""
    return F.get(F.array_sort(values), F.floor(q * (F.size(values) - 1)).cast("int"))


def per_sample(stats: DataFrame, k: float = 20.0, entropy_q: float = 0.5, logp_q: float = 0.5) -> DataFrame:
    """All probability scores of one layer in one aggregation: a column per method.

    ``collect_list`` holds a sample's tokens: memory grows with the longest text, which ``max_tokens`` can bound.
    """
    s = sigmoid(F.col("z"))
    grouped = stats.groupBy(*BY).agg(
        F.count(F.lit(1)).alias("n_tokens"), F.avg("logp").alias("loss"), F.sum("logp").alias("loss_sum"),
        F.avg(s).alias("unweighted_z"), (F.sum(F.col("weight") * s) / F.sum("weight")).alias("weighted_z"),
        (F.sum(F.col("weight") * sigmoid(F.col("z_model"))) / F.sum("weight")).alias("weighted_z_model"),
        (F.sum(F.col("weight") * s) / F.max("weight") / F.count(F.lit(1))).alias("weighted_z_max"),
        (F.sum(F.col("weight") * F.col("logp")) / F.sum("weight")).alias("weighted_loss"),
        F.avg("weight").alias("mean_weight"), (F.count_distinct("key") / F.count(F.lit(1))).alias("distinct_ratio"),
        F.collect_list("logp").alias("_logp"), F.collect_list(F.struct(F.round("entropy", 9).alias("e"), F.round("logp", 9).alias("p"), "logp")).alias("_both"))
    low_e, low_p = quantile(F.col("_both.e"), entropy_q), quantile(F.col("_both.p"), logp_q)
    # thresholds are bound once, not sorted out anew for every token
    cut = F.transform(F.array(F.struct(low_e.alias("e"), low_p.alias("p"))), lambda c: F.filter("_both", lambda x: (x["e"] <= c["e"]) & (x["p"] <= c["p"])))
    chosen = cut[0]
    surprise = F.aggregate(chosen, F.lit(0.0), lambda a, x: a + x["logp"]) / F.nullif(F.size(chosen), F.lit(0))
    return grouped.withColumn("lowest_k", lowest(F.col("_logp"), k)).withColumn("surprise", F.coalesce(surprise, F.col("loss"))).withColumn("perplexity", -F.exp(-F.col("loss")))


METHODS = ("loss", "lowest_k", "surprise", "unweighted_z", "weighted_z", "weighted_loss")


def long_form(scores: DataFrame, methods: tuple[str, ...] = METHODS) -> DataFrame:
    """``BY, method, score``, one row a method."""
    return scores.unpivot(list(BY), list(methods), "method", "score")


def neighbour_calibrated(stats: DataFrame, far: float = 0.05, near: float = 0.30) -> DataFrame:
    """``BY, score`` from token statistics of a sample (copy 0) and its neighbours: own confidence less the neighbours' mean.

    Confidence is the mean of the top ``far`` share of log-probabilities less that of
    the bottom ``near`` share.
    """
    values = F.array_sort("_l")
    top = lambda share: F.greatest(F.lit(1), F.floor(F.size("_l") * share)).cast("int")
    mean = lambda xs, m: F.aggregate(xs, F.lit(0.0), lambda a, x: a + x) / m
    each = stats.groupBy(*BY, "copy").agg(F.collect_list("logp").alias("_l"))
    each = each.withColumn("c", mean(F.slice(values, -top(far), top(far)), top(far)) - mean(F.slice(values, F.lit(1), top(near)), top(near)))
    return each.groupBy(*BY).agg((F.max(F.when(F.col("copy") == 0, F.col("c"))) - F.avg(F.when(F.col("copy") > 0, F.col("c")))).alias("score"))
