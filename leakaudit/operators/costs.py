"""What a run costs: rows and tokens seen, passes, time, and a projection."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def observe(df: DataFrame, name: str) -> tuple[DataFrame, Observation]:
    """The same rows with counters of rows and, where there is a text, of characters, filled when a job completes."""
    seen = Observation(name)
    counts = [F.count(F.lit(1)).alias("rows")]
    if "text" in df.columns:
        counts.append(F.coalesce(F.sum(F.length("text")), F.lit(0)).alias("chars"))
    if "sample_id" in df.columns:
        counts.append(F.approx_count_distinct("sample_id").alias("samples"))
    return df.observe(seen, *counts), seen


def shuffled_bytes(spark: SparkSession) -> int:
    """Bytes that the application's stages have written to shuffles so far, by its own status store."""
    sc = spark.sparkContext
    context = sc._jsc.sc()
    context.listenerBus().waitUntilEmpty(30_000)
    stages = context.statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), sc._jvm.java.util.ArrayList())
    return sum(stages.apply(k).shuffleWriteBytes() for k in range(stages.size()))


def timed(stages: dict[str, Callable[[], DataFrame]], passes: dict[str, int] | None = None, target_tokens: float = 2.5e13) -> DataFrame:
    """``stage, rows, seconds, rows_per_s, passes, shuffle_bytes, projected_h`` of each stage, run to the end without a sink.

    ``passes``: forward passes a stage takes, one where it isn't named.
    ``shuffle_bytes`` counts what the application shuffled meanwhile, tables written
    on the way included. ``projected_h``: hours for ``target_tokens`` rows at this
    rate on this machine.
    """
    out, spark = [], None
    for name, make in stages.items():
        before, began = shuffled_bytes(spark) if spark else None, time.time()
        df, seen = observe(make(), name)
        spark = df.sparkSession
        df.write.format("noop").mode("overwrite").save()
        took = time.time() - began
        rows = int(seen.get["rows"])
        moved = shuffled_bytes(spark) - before if before is not None else None
        out.append((name, rows, took, rows / max(took, 1e-9), (passes or {}).get(name, 1), moved, target_tokens / max(rows / max(took, 1e-9), 1e-9) / 3600))
    return spark.createDataFrame(out, "stage string, rows long, seconds double, rows_per_s double, passes int, shuffle_bytes long, projected_h double")
