"""The operators' registered queries and their SQL."""

from __future__ import annotations

import os

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from leakaudit.llm import bpe, exact, licences, mixing, multiset, pii, quality, simhash, substring, toxicity
from leakaudit.llm.common import documents
from leakaudit.llm.sparse import held_out


def op1_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mixing.mix(documents(spark, sf_dir), keep=["doc_id"])
    taken = F.aggregate("draws", F.lit(0).cast("long"), lambda a, d: a + d["words"])
    return rows.select("row.doc_id", "size", "source_size", "target", taken.alias("taken"), F.col("draws.shard").alias("shards"))


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = simhash.near_groups(documents(spark, sf_dir))
    return rows.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = pii.find(documents(spark, sf_dir))
    shown = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["stop"])), ",")
    order = F.array(*[F.lit(k) for k in dict.fromkeys((*pii.KINDS, *pii.EXTRA))])
    every = F.array_sort(F.transform(F.concat("base", "extra"), lambda s: F.struct(F.array_position(order, s["kind"]).alias("at"), s["start"].alias("start"), s["stop"].alias("stop"), s["kind"].alias("kind"))))
    count = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long")
    return rows.select("doc_id", *[count(k).alias(f"n_{k}") for k in pii.KINDS], F.sha2(shown(F.col("base")), 256).alias("base_sha256"), shown(every).alias("spans"))


#: Metadata that op4 may look at: not lang, source or doc_id.
META = ("n_chars",)


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return quality.score(docs, quality.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), meta=META), meta=META)


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    chain = toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    rows = toxicity.classify(docs.select("doc_id", "text"), chain)
    return rows.select("row.doc_id", held_out(F.col("row.doc_id")).alias("held_out"), *[f"p_{c}" for c in toxicity.CHAIN], F.col("rejected").cast("int").alias("predicted"))


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.members(documents(spark, sf_dir))


OP5_SQL = """
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS whole, regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]', '', 'g') AS content FROM documents
), r AS (
  SELECT doc_id, content,
         first_value(doc_id) OVER (PARTITION BY content ORDER BY length(whole) DESC, doc_id) AS keep_id,
         count(*) OVER (PARTITION BY content) AS group_size
  FROM d
)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(content) AS text_sha256 FROM r
"""


def tokenizer_path() -> str:
    """The public byte-level vocabulary; LEAKAUDIT_TOKENIZER names another."""
    if found := os.environ.get("LEAKAUDIT_TOKENIZER"):
        return found
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op7_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digests(documents(spark, sf_dir), bpe.Vocabulary(tokenizer_path()))


def op8_substring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.strike(documents(spark, sf_dir))


OP8_SQL = """
WITH w AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS words FROM documents
), p AS (
  SELECT doc_id, words, unnest(range(1, len(words) + 1)) AS i FROM w
), k AS (
  SELECT doc_id, i, words[i] AS word, CASE WHEN i + 49 <= len(words) THEN array_to_string(words[i:i + 49], ' ') END AS win FROM p
), m AS (
  SELECT doc_id, i, word, win IS NOT NULL AND min(doc_id) OVER (PARTITION BY win) < doc_id AS again FROM k
), c AS (
  SELECT doc_id, i, word, bool_or(again) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 49 PRECEDING AND CURRENT ROW) AS gone FROM m
), g AS (
  SELECT doc_id, count(*) AS n_words, count(*) FILTER (gone) AS n_removed, coalesce(string_agg(word, ' ' ORDER BY i) FILTER (NOT gone), '') AS kept FROM c GROUP BY doc_id
)
SELECT d.doc_id, coalesce(n_words, 0) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM documents d LEFT JOIN g ON d.doc_id = g.doc_id
"""


def op9_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = multiset.edited(documents(spark, sf_dir))
    return rows.select(
        "doc_id", "n_chars", "edited_sha256",
        multiset.as_hex(F.col("lanes")).alias("fingerprint"), multiset.as_hex(F.col("edited_lanes")).alias("edited_fingerprint"),
        multiset.likeness(F.col("lanes"), F.col("edited_lanes")).alias("near_edited"),
        multiset.likeness(F.col("lanes"), F.col("next_lanes")).alias("near_next"),
    )


def op10_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = licences.scan(documents(spark, sf_dir))
    names = F.array_sort(F.array_distinct(F.transform("found", lambda m: m["licence"])))
    best = F.array_max(F.transform("found", lambda m: m["gain"]))
    return rows.select("doc_id", F.size("found").cast("long").alias("n_found"), F.array_join(names, ",").alias("licences"), best.alias("best_reduction"), F.size(F.filter("found", lambda m: m["missing"] == 0)).cast("long").alias("n_exact"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_mix": op1_mix,
    "op2_simhash": op2_simhash,
    "op3_pii": op3_pii,
    "op4_quality": op4_quality,
    "op5_exact_dedup": op5_exact_dedup,
    "op6_toxicity": op6_toxicity,
    "op7_bpe": op7_bpe,
    "op8_substring": op8_substring,
    "op9_fingerprint": op9_fingerprint,
    "op10_licences": op10_licences,
}

ORACLES: dict[str, str] = {"op5_exact_dedup": OP5_SQL, "op8_substring": OP8_SQL}
