"""Auditing texts and events as they arrive."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from leakaudit.functions import lexing
from leakaudit.functions.weights import Scheme
from leakaudit.operators import target as targets
from leakaudit.operators.scores import sigmoid


def score_batch(samples: DataFrame, made: targets.CountTarget, words: DataFrame | None = None, scheme: Scheme | None = None) -> DataFrame:
    """``sample_id, weighted_z, loss`` of arriving samples under a target that is at hand: mask and score in flight."""
    from leakaudit.operators import scores, tokens

    some = samples.withColumn("is_member", F.lit(False)).withColumn("role", F.lit("stream"))
    stats = targets.forward(tokens.tokens(some, words=words, scheme=scheme), made)
    return scores.per_sample(stats).select("sample_id", "slice", "weighted_z", "loss")


def score_stream(stream: DataFrame, made: targets.CountTarget, path: str, checkpoint: str, words: DataFrame | None = None):
    """Scores a stream of samples into Parquet under ``path``; a replayed batch overwrites its own folder, so results come once."""

    def each(batch: DataFrame, number: int) -> None:
        score_batch(batch, made, words).withColumn("batch_id", F.lit(number)).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _timed(stream: DataFrame, column: str = "ts") -> DataFrame:
    """Event time as an instant: watermarks take no local timestamps."""
    return stream.withColumn(column, F.col(column).cast("timestamp"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Sessions of each user with the number of their events; rows later than the watermark are dropped."""
    return _timed(events).withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("stop"), "n")


def flagged_counts(scored: DataFrame, threshold: float, width: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Scored and flagged rows per tumbling or sliding window of event time."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return _timed(scored).withWatermark("ts", late).groupBy(window).agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("score") >= threshold).alias("flagged")).select(F.col("window.start").alias("start"), "n", "flagged")


def totals(scored: DataFrame, threshold: float) -> DataFrame:
    """Scored and flagged rows per slice since the start: the few slices are the state, written whole each time (output mode ``complete``)."""
    return scored.groupBy("slice").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("score") >= threshold).alias("flagged"))


def fresh(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each text once within the watermark, by content key."""
    return _timed(stream).withColumn("content_key", F.md5("text")).withWatermark("ts", late).dropDuplicatesWithinWatermark(["content_key"])


def with_labels(scored: DataFrame, labels: DataFrame, within: str = "2 hours", late: str = "1 hour") -> DataFrame:
    """Scores joined to labels that come later, at most ``within`` after them: a stream-stream join with bounded state."""
    s = _timed(scored).withWatermark("ts", late).alias("s")
    x = _timed(labels, "label_ts").withWatermark("label_ts", late).alias("x")
    on = F.expr(f"s.sample_id = x.label_id AND x.label_ts >= s.ts AND x.label_ts <= s.ts + INTERVAL {within}")
    return s.join(x, on).select("s.sample_id", "s.ts", "s.score", "x.is_member")


ROLLING = "slice string, n_pos long, n_neg long, auc double"


def rolling_auc(labelled: DataFrame, bins: int = 1024) -> DataFrame:
    """The binned AUC of each slice over all rows so far, from a histogram of members and others in the state.

    Scores are taken to lie in [0, 1]; the state has ``2 * bins`` numbers a slice,
    whatever the stream. Equal bins count one half.
    """

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        counts = list(state.get[0]) if state.exists else [0] * (2 * bins)
        for frame in frames:
            at = (frame["score"] * bins).astype(int).clip(0, bins - 1) * 2 + (~frame["is_member"].astype(bool)).astype(int)
            for k, n in at.value_counts().items():
                counts[k] += int(n)
        state.update((counts,))
        pos, neg = counts[::2], counts[1::2]
        wins, below = 0.0, 0
        for p, q in zip(pos, neg, strict=True):
            wins += p * (below + q / 2)
            below += q
        both = sum(pos) * sum(neg)
        yield pd.DataFrame({"slice": [key[0]], "n_pos": [sum(pos)], "n_neg": [sum(neg)], "auc": [round(wins / both, 6) if both else None]})

    return labelled.select("slice", "score", "is_member").groupBy("slice").applyInPandasWithState(update, ROLLING, "counts array<long>", "update", GroupStateTimeout.NoTimeout)


def token_classes(stream: DataFrame) -> DataFrame:
    """Arriving texts with counts of their identifiers and of tags: stateless, in one projection."""
    pieces = lexing.stretches(F.col("text"), lexing.PIECE)
    return stream.select("sample_id", F.size(F.filter(pieces, lexing.is_identifier)).alias("identifiers"), F.size(F.filter(pieces, lambda t: t.isin(*lexing.TAGS))).alias("tags"), sigmoid(F.lit(0.0)).alias("prior"))
