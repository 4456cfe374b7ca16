"""Per-layer probes, their selection and ensemble, and fusion with the logit half."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.ml.classification import LogisticRegression, MultilayerPerceptronClassifier
from pyspark.ml.feature import StandardScaler
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from leakaudit.operators import metrics
from leakaudit.runtime import materialise, running

BY = ("sample_id", "slice", "is_member", "role")
TOP = 5


def _fit(rows: DataFrame, kind: str, hidden: tuple[int, ...], seed: int, epochs: int):
    width = len(rows.first()["features"])
    if kind == "linear":
        made = LogisticRegression(featuresCol="x", labelCol="y", maxIter=epochs, regParam=0.01)
    else:
        made = MultilayerPerceptronClassifier(featuresCol="x", labelCol="y", layers=[width, *hidden, 2], maxIter=epochs, seed=seed)
    return made.fit(rows)


#: Shadow samples that a layer's probe is fitted on at most, some 130 MB of 160 features each.
MOST_SHADOW = 100_000


def shadow_sample(rows: DataFrame, frac: float = 1.0, seed: int = 0) -> DataFrame:
    """A random subset of the shadow samples, the same in every run; other roles stay whole. For probing, where activations of all are not wanted."""
    unit = F.pmod(F.xxhash64(F.lit(seed), F.lit("shadow"), "sample_id"), F.lit(1 << 40)) / float(1 << 40)
    return rows.where((F.col("role") != "shadow") | (unit < frac))


def train_probes(pooled: DataFrame, kind: str = "mlp", hidden: tuple[int, ...] = (16,), seed: int = 3, epochs: int = 60, fit_digit: str = "b", threads: int = 4, most: int = MOST_SHADOW) -> DataFrame:
    """``BY, layer, part, prob``: each layer's probe (cross-entropy on member or not) applied to all samples.

    A probe is fitted on one machine, on a random subset of about ``most`` samples where there are more.

    Probes are fitted on part ``fit`` of the shadow role; part ``select`` of it ranks
    them, and ``holdout`` is only predicted. Standardisation is learnt on the fit
    part. A few independent fits run at a time; the driver sees models and no rows.
    """
    digit = F.substring(F.md5(F.concat(F.lit("part/"), F.col("sample_id").cast("string"))), 1, 1)
    part = F.when(F.col("role") == "holdout", "holdout").when(digit < F.lit(fit_digit), "fit").otherwise("select")
    rows = materialise(pooled.withColumn("part", part), "pooled")
    layers = {r[0]: r[1] for r in rows.groupBy("layer").agg(F.count_if(F.col("part") == "fit")).orderBy("layer").collect()}

    def one(layer: int) -> DataFrame:
        mine = rows.where(F.col("layer") == layer).withColumn("v", array_to_vector("features")).withColumn("y", F.col("is_member").cast("double"))
        shown = shadow_sample(mine.where("part = 'fit'"), min(1.0, most / max(1, layers[layer])), seed).repartition(1).sortWithinPartitions("sample_id")
        scaler = StandardScaler(inputCol="v", outputCol="x", withMean=True, withStd=True).fit(shown)
        model = _fit(scaler.transform(shown), kind, hidden, seed, epochs)
        return model.transform(scaler.transform(mine)).select(*BY, "layer", "part", vector_to_array("probability")[1].alias("prob"))

    with ThreadPoolExecutor(threads) as pool:
        made = list(pool.map(one, layers))
    out = made[0]
    for more in made[1:]:
        out = out.union(more)
    return materialise(out, "probes")


def rank_layers(probs: DataFrame, part: str = "select") -> DataFrame:
    """``layer, auc, rank``: layers by how well their probe tells the selection part apart; ties by layer."""
    scored = probs.where(F.col("part") == part).withColumn("method", F.col("layer").cast("string")).withColumn("score", F.col("prob"))
    ranked = metrics.auc(scored).select(F.col("method").cast("int").alias("layer"), "auc")
    return ranked.withColumn("rank", F.row_number().over(Window.orderBy(F.desc_nulls_last("auc"), "layer")))


def ensemble(probs: DataFrame, ranking: DataFrame, top: int = TOP, weighted: bool = False) -> DataFrame:
    """``BY, score``: the mean of the ``top`` best layers' outputs (or their AUC-weighted mean), in [0, 1]."""
    # one row a layer
    best = F.broadcast(ranking.where(F.col("rank") <= top).select("layer", "auc"))
    joined = probs.where("part = 'holdout'").join(best, "layer")
    value = F.sum(F.col("prob") * F.col("auc")) / F.sum("auc") if weighted else F.avg("prob")
    return joined.groupBy(*BY).agg(value.alias("score"))


def fuse(logit: DataFrame, probe: DataFrame, how: str = "mean", alpha: float = 0.5) -> DataFrame:
    """``BY, score`` of the composite attack: a mean of both halves, of their ranks, or one half alone. (``stacked`` is in ``stack``.)"""
    both = logit.select(*BY, F.col("score").alias("a")).join(probe.select("sample_id", F.col("score").alias("b")), "sample_id")
    if how == "rank_mean":
        # ranks by way of counts per distinct score, whose running sums are taken range by range
        both = materialise(both, "both")
        total = both.count()
        for c in ("a", "b"):
            per = running(both.groupBy(F.lit(0).alias("all"), c).agg(F.count(F.lit(1)).alias("n")), ["all"], [c], ["n"])
            both = both.join(per.select(c, ((F.col("before_n") + (F.col("n") + 1) / 2) / F.lit(total)).alias(f"r{c}")), c)
        return both.select(*BY, (alpha * F.col("ra") + (1 - alpha) * F.col("rb")).alias("score"))
    value = {"mean": alpha * F.col("a") + (1 - alpha) * F.col("b"), "logit_only": F.col("a"), "probe_only": F.col("b")}[how]
    return both.select(*BY, value.alias("score"))


def stack(pooled: DataFrame, logit: DataFrame) -> DataFrame:
    """``pooled`` with the logit half's score as one more feature of every layer: probes trained on it fuse both halves themselves."""
    return pooled.join(logit.select("sample_id", F.col("score").alias("_z")), "sample_id").withColumn("features", F.concat("features", F.array("_z"))).drop("_z")
