"""Subword tokens of an installed tokenizer, with offsets in code points, and the mask's projection to them."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from leakaudit.operators.mask import project as merge
from leakaudit.operators.tokens import KEEP
from leakaudit.runtime import materialise

SCHEMA = "sample_id long, tokens array<struct<pos:int,id:int,start:int,stop:int>>"


def encode(samples: DataFrame, tokenizer_json: str, max_tokens: int | None = None) -> DataFrame:
    """``sample_id, tokens``: ids with the characters they come from, all or ``max_tokens`` a sample.

    ``tokenizer_json`` is the text of a tokenizers file: it travels with the plan, so
    executors need no file. Special tokens that no character stands for have
    start = stop.
    """
    kind = pa.list_(pa.struct([("pos", pa.int32()), ("id", pa.int32()), ("start", pa.int32()), ("stop", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from tokenizers import Tokenizer

        made = Tokenizer.from_str(tokenizer_json)
        for batch in batches:
            out = []
            for text in batch.column("text").to_pylist():
                e = made.encode(text or "", add_special_tokens=False)
                out.append([{"pos": k + 1, "id": i, "start": a, "stop": b} for k, (i, (a, b)) in enumerate(zip(e.ids[:max_tokens], e.offsets[:max_tokens], strict=True))])
            yield pa.RecordBatch.from_arrays([batch.column("sample_id"), pa.array(out, kind)], ["sample_id", "tokens"])

    return samples.select(F.col("sample_id").cast("long"), "text").mapInArrow(run, SCHEMA)


def project(tokens: Column, runs: Column, outside: float = 0.1, how: str = "max") -> Column:
    """A weight per token from an array of disjoint runs (start, stop, weight): the largest that it overlaps, or the mean over its characters.

    Characters without a run, and tokens without characters, weigh ``outside``.
    """

    def one(t: Column) -> Column:
        met = F.filter(runs, lambda r: (r["start"] < t["stop"]) & (r["stop"] > t["start"]))
        size = t["stop"] - t["start"]
        if how == "max":
            covered = F.aggregate(met, F.lit(0), lambda a, r: a + F.least(r["stop"], t["stop"]) - F.greatest(r["start"], t["start"]))
            top = F.array_max(F.transform(met, lambda r: r["weight"]))
            return F.when(F.size(met) == 0, F.lit(outside)).when(covered < size, F.greatest(top, F.lit(outside))).otherwise(top)
        part = F.aggregate(met, F.lit(0.0), lambda a, r: a + (r["weight"] - outside) * (F.least(r["stop"], t["stop"]) - F.greatest(r["start"], t["start"])))
        return F.when(size > 0, F.lit(outside) + part / size).otherwise(F.lit(outside))

    return F.transform(tokens, one)


def weighted(samples: DataFrame, masked: DataFrame, tokenizer_json: str, how: str = "max", outside: float = 0.1, max_tokens: int | None = None) -> DataFrame:
    """The token table of a subword tokenizer: ``KEEP, pos, tok, key, start, stop, t, prev1..prev4, kind, weight``.

    ``masked`` is the table of lexed tokens, whose weights are the character mask.
    A subword weighs the largest (or the mean) over its characters; those that no
    lexed token covers, and tokens without characters, weigh ``outside``. Its key is
    its id, so that a target can be trained on subwords.
    """
    keep = [c for c in KEEP if c in samples.columns]
    rows = encode(samples, tokenizer_json, max_tokens).select("sample_id", F.explode("tokens").alias("s")).select("sample_id", "s.pos", F.col("s.id").cast("string").alias("key"), "s.start", "s.stop")
    rows = materialise(rows.repartition("sample_id"), "subwords")
    # pieces of one character can share its place: the mask is asked once a place
    places = rows.where("stop > start").groupBy("sample_id", "start").agg(F.max("stop").alias("stop"))
    after = Window.partitionBy("sample_id").orderBy("start")
    places = places.withColumn("stop", F.least("stop", F.coalesce(F.lead("start").over(after), F.col("stop")))).withColumn("pos", F.col("start")).withColumn("weight", F.lit(float(outside)))
    found = merge(places, masked.select("sample_id", "start", "stop", "weight"), how).select("sample_id", F.col("pos").alias("start"), "weight")
    order = Window.partitionBy("sample_id").orderBy("pos")
    rows = rows.join(found, ["sample_id", "start"], "left").withColumn("weight", F.when(F.col("stop") > F.col("start"), F.coalesce("weight", F.lit(float(outside)))).otherwise(F.lit(float(outside))))
    for back in range(1, 5):
        rows = rows.withColumn(f"prev{back}", F.lag("key", back, "^").over(order))
    return rows.join(samples.select(*keep), "sample_id").select(*keep, "pos", F.col("key").alias("tok"), "key", "start", "stop", F.col("pos").alias("t"), "prev1", "prev2", "prev3", "prev4", F.lit("subword").alias("kind"), "weight")
