"""Exact de-duplication by skew-safe combining (native)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from leakaudit.llm.common import BLANKS, packed

#: Salts of a digest group: a bit mask of a BIGINT remembers which ones occur.
SALTS = 64
#: Ranks pack (code points, doc_id) into one decimal, so that hash aggregation can take their maximum.
SHIFT, TOP = 2**65, 2**64


def _whole(n: int) -> Column:
    return F.lit(str(n)).cast("decimal(38,0)")


def _rank(chars: Column, doc_id: Column) -> Column:
    """Larger: more code points, then smaller doc_id; a null doc_id comes last."""
    return chars.cast("decimal(12,0)") * _whole(SHIFT) + F.coalesce(_whole(TOP) - doc_id.cast("decimal(20,0)"), _whole(0))


def _digested(docs: DataFrame, doc_id: str, text: str) -> DataFrame:
    whole = F.coalesce(F.col(text), F.lit(""))
    content = F.translate(whole, BLANKS, "")
    return docs.select(
        F.col(doc_id).cast("long").alias("doc_id"),
        content.alias("_content"),
        F.unhex(F.sha2(content, 256)).alias("_digest"),
        F.pmod(F.xxhash64(F.col(doc_id)), F.lit(SALTS)).cast("int").alias("_salt"),
        F.char_length(whole).alias("_chars"),
    )


def groups(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per distinct normalised content: ``_digest, keep_id, keep_chars, group_size, _mask``.

    Copies are combined three times, and each time the whole content is part of
    the key: within a task (map-side aggregation), within (digest, salt), and over
    the salts. A digest that ever stood for two contents would end the job with an
    error instead of merging them.
    """
    ranked = _digested(docs, doc_id, text).withColumn("_rank", _rank(F.col("_chars"), F.col("doc_id")))
    salted = ranked.groupBy("_digest", "_salt", "_content").agg(F.max("_rank").alias("_rank"), F.count(F.lit(1)).alias("n"))
    whole = salted.groupBy("_digest", "_content").agg(
        F.max("_rank").alias("_rank"), F.sum("n").alias("n"), F.expr("bit_or(shiftleft(1L, _salt))").alias("_mask"))
    one = whole.groupBy("_digest").agg(
        F.max("_rank").alias("_rank"), F.max("n").alias("group_size"), F.max("_mask").alias("_mask"), F.count(F.lit(1)).alias("_contents"))
    safe = F.when(F.col("_contents") == 1, F.col("group_size")).otherwise(F.raise_error(F.lit("one digest, two contents")).cast("long"))
    low = F.col("_rank") % _whole(SHIFT)
    return one.select(
        "_digest",
        F.when(low > 0, (_whole(TOP) - low).cast("decimal(20,0)").cast("long")).alias("keep_id"),
        F.floor((F.col("_rank") - low) / _whole(SHIFT)).cast("int").alias("keep_chars"),
        safe.alias("group_size"),
        "_mask",
    )


def members(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per row of ``docs``: ``doc_id, keep_id, group_size, kept, text_sha256``.

    Texts are equal if identical after deleting the six blank characters; null
    counts as empty. The row with the most code points, then the smallest doc_id
    (null last) stays. Rows that repeat both doc_id and text all say ``kept``:
    nothing tells them apart (``deduplicate`` keeps one). An empty table gives none.
    Groups are looked up by (digest, salt), so a group that holds a third of all
    rows is spread over ``SALTS`` keys.
    """
    spread = groups(docs, doc_id, text).withColumn(
        "_salt", F.explode(F.expr(f"filter(sequence(0, {SALTS - 1}), s -> getbit(_mask, s) = 1)"))).drop("_mask")
    rows = _digested(docs, doc_id, text).drop("_content")
    return rows.join(spread, ["_digest", "_salt"]).select(
        "doc_id", "keep_id", "group_size",
        (F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("_chars") == F.col("keep_chars"))).alias("kept"),
        F.lower(F.hex("_digest")).alias("text_sha256"),
    )


def deduplicate(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns; exactly one of each group."""
    stay = groups(docs, doc_id, text).select("keep_id", "_digest", "keep_chars")
    whole = F.coalesce(F.col(text), F.lit(""))
    found = docs.select(
        packed(docs).alias("_row"), F.col(doc_id).cast("long").alias("_id"), F.unhex(F.sha2(F.translate(whole, BLANKS, ""), 256)).alias("_sha"), F.char_length(whole).alias("_chars"))
    match = F.col("_id").eqNullSafe(F.col("keep_id")) & (F.col("_sha") == F.col("_digest")) & (F.col("_chars") == F.col("keep_chars"))
    return found.join(stay, match, "left_semi").dropDuplicates(["_id", "_sha"]).select("_row.*")
