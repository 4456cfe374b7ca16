"""Accuracy measures of scores: AUC, ROC, operating points, gaps, intervals."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from leakaudit.runtime import running


def _counts(scores: DataFrame, by: list[str]) -> DataFrame:
    """Members and others per distinct score (rounded to 9 digits): the rows that everything else is computed from."""
    return scores.where("score is not null").groupBy(*by, F.round("score", 9).alias("score")).agg(
        F.sum(F.col("is_member").cast("long")).alias("pos"), F.sum((~F.col("is_member")).cast("long")).alias("neg"))


def _area(counts: DataFrame, by: list[str]) -> DataFrame:
    """AUC from counts per distinct score: their running sums are taken range by range, so no task orders all scores of a method."""
    rows = running(counts, by, ["score"], ["neg"])
    total = rows.groupBy(*by).agg(F.sum("pos").alias("n_pos"), F.sum("neg").alias("n_neg"), F.sum(F.col("pos") * (F.col("before_neg") + F.col("neg") / 2)).alias("_wins"))
    return total.select(*by, "n_pos", "n_neg", F.round(F.col("_wins") / F.nullif(F.col("n_pos") * F.col("n_neg"), F.lit(0)), 6).alias("auc"))


def auc(scores: DataFrame, by: tuple[str, ...] = ("method",), how: str = "exact", bins: int = 65536) -> DataFrame:
    """``by, n_pos, n_neg, auc`` (and ``error``, its bound, if binned): P(member scores higher) plus half of P(equal).

    Exact: rows are first counted per distinct score. Binned: per one of ``bins``
    equal intervals of each group's range, so the state is bounded whatever the
    input; the bound is half of the sum of in-bin pairs. Null if a class is absent.
    """
    keys = list(by)
    if how == "exact":
        return _area(_counts(scores, keys), keys)
    if how != "binned":
        raise ValueError("how is exact or binned")
    some = scores.where("score is not null")
    ends = some.groupBy(*keys).agg(F.min("score").alias("_lo"), F.max("score").alias("_hi"))
    width = F.greatest(F.col("_hi") - F.col("_lo"), F.lit(1e-12))
    at = F.least(F.lit(bins - 1), F.floor((F.col("score") - F.col("_lo")) / width * bins))
    binned = some.join(ends, keys).withColumn("score", at.cast("double"))
    counts = _counts(binned, keys)
    error = counts.groupBy(*keys).agg((F.sum(F.col("pos") * F.col("neg")) / 2 / F.nullif(F.sum("pos") * F.sum("neg"), F.lit(0))).alias("error"))
    return _area(counts, keys).join(error.withColumn("error", F.round("error", 6)), keys)


def auc_summary(scores: DataFrame) -> DataFrame:
    """``method, pooled, macro``: all slices together, and the mean of the slices."""
    pooled = auc(scores, ("method",)).select("method", F.col("auc").alias("pooled"))
    macro = auc(scores, ("method", "slice")).groupBy("method").agg(F.round(F.avg("auc"), 6).alias("macro"))
    return pooled.join(macro, "method")


def with_overall(scores: DataFrame) -> DataFrame:
    """The scores once more under the slice ``overall``: AUC isn't additive, so the pooled one is computed from the rows."""
    return scores.withColumn("slice", F.explode(F.array("slice", F.lit("overall"))))


def roc(scores: DataFrame, by: tuple[str, ...] = ("method",), max_points: int | None = None) -> DataFrame:
    """``by, threshold, fpr, tpr``: a point per distinct score, flagged from the highest down; ``max_points`` thins evenly by rank."""
    keys = list(by)
    up = running(_counts(scores, keys).withColumn("one", F.lit(1).cast("long")), keys, ["score"], ["pos", "neg", "one"])
    # one row a group
    whole = up.groupBy(*[F.col(k).alias(f"_k_{k}") for k in keys]).agg(F.sum("pos").alias("_p"), F.sum("neg").alias("_q"), F.count(F.lit(1)).alias("_n"))
    same = F.lit(True)
    for k in keys:
        same = same & F.col(k).eqNullSafe(F.col(f"_k_{k}"))
    rows = up.join(whole, same).select(
        *keys, F.col("score").alias("threshold"), ((F.col("_q") - F.col("before_neg")) / F.nullif(F.col("_q"), F.lit(0))).alias("fpr"),
        ((F.col("_p") - F.col("before_pos")) / F.nullif(F.col("_p"), F.lit(0))).alias("tpr"), (F.col("_n") - F.col("before_one")).alias("_r"), "_n")
    if max_points:
        rows = rows.where((F.col("_r") == F.col("_n")) | (F.floor(F.col("_r") * max_points / F.col("_n")) > F.floor((F.col("_r") - 1) * max_points / F.col("_n"))))
    return rows.drop("_r", "_n")


def tpr_at_fpr(scores: DataFrame, fpr: float = 0.01, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """``by, tpr``: the largest true-positive rate among thresholds whose false-positive rate is at most ``fpr`` (0 if none)."""
    return roc(scores, by).groupBy(*by).agg(F.round(F.coalesce(F.max(F.when(F.col("fpr") <= fpr, F.col("tpr"))), F.lit(0.0)), 6).alias("tpr"))


def best_accuracy(scores: DataFrame, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """``by, threshold, accuracy``: the best share of right calls; of equal ones the highest threshold."""
    keys = list(by)
    total = scores.where("score is not null").groupBy(*keys).agg(F.sum(F.col("is_member").cast("long")).alias("p"), F.sum((~F.col("is_member")).cast("long")).alias("q"))
    points = roc(scores, by).join(total, keys)
    right = F.round((F.col("tpr") * F.col("p") + (1 - F.col("fpr")) * F.col("q")) / (F.col("p") + F.col("q")), 9)
    best = points.groupBy(*keys).agg(F.max(F.struct(right.alias("a"), F.col("threshold").alias("t"))).alias("b"))
    return best.select(*keys, F.round("b.t", 6).alias("threshold"), F.round("b.a", 6).alias("accuracy"))


def gap(table: DataFrame, ours: str = "weighted_z") -> DataFrame:
    """``slice, method, points``: by how many points of AUC ``ours`` is ahead of each other method."""
    mine = table.where(F.col("method") == ours).select("slice", F.col("auc").alias("_mine"))
    return table.where(F.col("method") != ours).join(mine, "slice").select("slice", "method", F.round(100 * (F.col("_mine") - F.col("auc")), 4).alias("points"))


#: The distribution function of Poisson(1) (fixed values).
POISSON = (0.367879, 0.735759, 0.919699, 0.981012, 0.996340, 0.999406, 0.999917)


def bootstrap(scores: DataFrame, reps: int = 200, seed: int = 7, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """``by, low, high``: the middle 95 % of AUC over ``reps`` resamplings with Poisson(1) weights, drawn by a digest of row and replica."""
    keys = [*by, "rep"]
    digits = F.substring(F.md5(F.concat_ws("/", F.lit(str(seed)), F.col("sample_id").cast("string"), "method", F.col("rep").cast("string"))), 1, 10)
    unit = F.conv(digits, 16, 10).cast("double") / float(1 << 40)
    weight = sum(((unit >= b).cast("long") for b in POISSON), F.lit(0).cast("long"))
    each = scores.where("score is not null").withColumn("rep", F.explode(F.sequence(F.lit(1), F.lit(reps)))).withColumn("_w", weight)
    counts = each.groupBy(*keys, F.round("score", 9).alias("score")).agg(F.sum(F.when(F.col("is_member"), F.col("_w")).otherwise(0)).alias("pos"), F.sum(F.when(F.col("is_member"), 0).otherwise(F.col("_w"))).alias("neg"))
    area = _area(counts, keys)
    return area.groupBy(*by).agg(F.percentile("auc", F.array(F.lit(0.025), F.lit(0.975))).alias("q")).select(*by, F.round(F.col("q")[0], 6).alias("low"), F.round(F.col("q")[1], 6).alias("high"))
