"""Activations per layer, pooled plainly and by weight."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WIDTH = 8
BY = ("sample_id", "slice", "is_member", "role")


def pool(stats: DataFrame, how: str = "both", width: int = WIDTH) -> DataFrame:
    """``BY, layer, features``: the mean of each component, its weighted mean, or both concatenated (twice the width)."""
    plain = [F.avg(F.col("act")[k]) for k in range(width)]
    weighted = [F.sum(F.col("weight") * F.col("act")[k]) / F.sum("weight") for k in range(width)]
    parts = {"mean": plain, "weighted": weighted, "both": [*plain, *weighted]}[how]
    return stats.groupBy(*BY, "layer").agg(F.array(*parts).alias("features"))


def univariate(pooled: DataFrame) -> DataFrame:
    """``BY, method, score``: every pooled component of every layer as a score of its own."""
    each = pooled.select(*BY, "layer", F.posexplode("features").alias("k", "score"))
    return each.select(*BY, F.concat_ws(":", F.lpad("layer", 2, "0"), F.lpad("k", 2, "0")).alias("method"), "score")
