"""Character masks as runs, and their projection to tokens."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from leakaudit.functions.weights import Scheme


def runs(spans: DataFrame, scheme: Scheme | None = None) -> DataFrame:
    """``sample_id, start, stop, weight``: disjoint runs of span rows (``sample_id, kind, start, stop``).

    Between neighbouring boundaries the weight is the largest of the covering
    kinds; a tag assigns its own, even a lower one. Uncovered stretches have no run.
    A sweep: every span counts up where it starts and down where it stops; running
    sums per kind, over a sample's boundaries in order, tell what is open.
    """
    scheme = scheme or Scheme.default()
    kinds = [k for k in dict.fromkeys((*scheme.weights, "tag"))]
    ends = F.array(F.struct(F.col("start").alias("at"), F.lit(1).alias("step")), F.struct(F.col("stop").alias("at"), F.lit(-1).alias("step")))
    each = spans.select("sample_id", "kind", F.explode(ends).alias("e"))
    # the shuffle is by sample, so that the windows need no other one
    steps = [F.sum(F.when(F.col("kind") == k, F.col("e.step")).otherwise(0)).alias(f"_{k}") for k in kinds]
    bounds = each.repartition("sample_id").groupBy("sample_id", F.col("e.at").alias("start")).agg(*steps)
    order = Window.partitionBy("sample_id").orderBy("start")
    upto = order.rowsBetween(Window.unboundedPreceding, 0)
    rows = bounds.select("sample_id", "start", F.lead("start").over(order).alias("stop"), *[(F.sum(f"_{k}").over(upto) > 0).alias(f"_{k}") for k in kinds])
    top = [F.when(F.col(f"_{k}"), F.lit(float(scheme[k]))) for k in scheme.weights]
    weight = F.when(F.col("_tag"), F.lit(float(scheme["tag"]))).otherwise(F.greatest(*top, F.lit(None).cast("double")))
    return rows.select("sample_id", "start", "stop", weight.alias("weight")).where("stop is not null and weight is not null")


_TOKEN = "struct<pos:int,start:int,stop:int,weight:double>"
_RUN = "struct<start:int,stop:int,weight:double>"


def project(tokens: DataFrame, run_rows: DataFrame, how: str = "mean") -> DataFrame:
    """``sample_id, pos, weight``: over a token's characters the mean, or the largest, of its own weight and the runs'.

    A merge by position: the boundaries of tokens and runs of a sample in order cut
    it into segments that at most one token and one run cover, the last ones begun.
    Tokens that no run touches keep their weight; tokens and runs must not overlap
    among themselves. A token without characters keeps its weight.
    """
    t = tokens.select("sample_id", F.struct(F.col("pos").cast("int").alias("pos"), F.col("start").cast("int").alias("start"), F.col("stop").cast("int").alias("stop"), F.col("weight").cast("double").alias("weight")).alias("tok"))
    r = run_rows.select("sample_id", F.struct(F.col("start").cast("int").alias("start"), F.col("stop").cast("int").alias("stop"), F.col("weight").cast("double").alias("weight")).alias("run"))
    no_tok, no_run = F.lit(None).cast(_TOKEN), F.lit(None).cast(_RUN)
    events = t.select("sample_id", F.explode(F.array(F.struct(F.col("tok.start").alias("at"), F.col("tok").alias("tok"), no_run.alias("run")), F.struct(F.col("tok.stop").alias("at"), no_tok.alias("tok"), no_run.alias("run")))).alias("e"))
    events = events.union(r.select("sample_id", F.explode(F.array(F.struct(F.col("run.start").alias("at"), no_tok.alias("tok"), F.col("run").alias("run")), F.struct(F.col("run.stop").alias("at"), no_tok.alias("tok"), no_run.alias("run"))))))
    merged = events.select("sample_id", "e.*").repartition("sample_id").groupBy("sample_id", "at").agg(F.max("tok").alias("tok"), F.max("run").alias("run"))
    order = Window.partitionBy("sample_id").orderBy("at")
    upto = order.rowsBetween(Window.unboundedPreceding, 0)
    cut = merged.select("sample_id", "at", F.lead("at").over(order).alias("to"), F.last("tok", True).over(upto).alias("tok"), F.last("run", True).over(upto).alias("run"))
    inside = cut.where(F.col("tok").isNotNull() & ((F.col("tok.stop") > F.col("at")) | (F.col("tok.stop") == F.col("tok.start")) & (F.col("tok.start") == F.col("at"))))
    over = F.coalesce(F.when((F.col("run.stop") > F.col("at")) & (F.col("tok.stop") > F.col("at")), F.greatest(F.lit(0.0), F.col("run.weight") - F.col("tok.weight"))), F.lit(0.0))
    if how == "max":
        gain = F.max(over)
    else:
        gain = F.sum((F.coalesce(F.col("to"), F.col("at")) - F.col("at")) * over) / F.nullif(F.max(F.col("tok.stop") - F.col("tok.start")), F.lit(0))
    found = inside.groupBy("sample_id", "tok").agg(gain.alias("_g"))
    return found.select("sample_id", "tok.pos", (F.col("tok.weight") + F.coalesce("_g", F.lit(0.0))).alias("weight"))


def project_mean(tokens: DataFrame, run_rows: DataFrame) -> DataFrame:
    return project(tokens, run_rows, "mean")


def normalise(weights: Column, how: str = "sum") -> Column:
    """An array of weights over its sum (a convex mean) or its maximum."""
    whole = F.aggregate(weights, F.lit(0.0), lambda a, w: a + w) if how == "sum" else F.array_max(weights)
    return F.transform(weights, lambda w: w / whole)


def profile(tokens: DataFrame) -> DataFrame:
    """``slice, kind, n_tokens, n_chars, weight``: what the mask consists of in each slice."""
    return tokens.groupBy("slice", "kind").agg(F.count(F.lit(1)).alias("n_tokens"), F.sum(F.col("stop") - F.col("start")).cast("long").alias("n_chars"), F.sum("weight").alias("weight"))
