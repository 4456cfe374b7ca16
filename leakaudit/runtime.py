"""Session-level helpers: the shared folder, written intermediate tables, size-checked lookups."""

from __future__ import annotations

import ctypes
import ctypes.util
import gc
import re
import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: A lookup side of at most this many rows is broadcast; above it the join is salted.
BROADCAST_ROWS = 100_000


def shared_dir(spark: SparkSession) -> str:
    """The folder every executor can reach: ``spark.checkpoint.dir``.

    Only a local session, whose executors are the driver, gets a folder of its own
    where none is set; on a cluster that would be a folder of one machine: an error.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        found = tempfile.mkdtemp(prefix="leakaudit-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def materialise(df: DataFrame, tag: str = "t", compression: str | None = None) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back.

    Cuts the lineage: a lost executor costs only the stage that reads the table.
    The table is deleted when the driver's JVM ends, on whatever file system it is.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/leakaudit/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path, compression=compression)
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(where)
    return spark.read.schema(df.schema).parquet(path)


def trim() -> None:
    """Gives freed memory back to the system, where the C library can: a worker lives on after its task, beside others."""
    gc.collect()
    release = getattr(ctypes.CDLL(ctypes.util.find_library("c")), "malloc_trim", None)
    if release:
        release(0)


_HELD: dict[int, list] = {}
_LOCK = threading.Lock()


@contextmanager
def batch_rows(spark: SparkSession, rows: int) -> Iterator[None]:
    """Within this block Arrow batches hold at most so many rows; what the session had set holds again after the last such block.

    For jobs that run within the block, such as ``materialise``. Blocks of several
    threads may overlap: the least bound holds while any of them lasts, which no
    result depends on.
    """
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    with _LOCK:
        held = _HELD.setdefault(id(spark), [0, spark.conf.get(key)])
        held[0] += 1
        now = int(spark.conf.get(key))
        spark.conf.set(key, str(min(rows, now) if now > 0 else rows))
    try:
        yield
    finally:
        with _LOCK:
            held[0] -= 1
            if not held[0]:
                spark.conf.set(key, held[1])
                del _HELD[id(spark)]


def lookup(big: DataFrame, small: DataFrame, on: list[str], how: str = "inner", salts: int = 64, rows: int = BROADCAST_ROWS) -> DataFrame:
    """``big`` joined to ``small`` (unique in ``on``, already materialised or cheap to count).

    ``small`` is counted: up to ``rows`` rows it is broadcast, beyond that both
    sides are salted so that one hot key is spread over ``salts`` tasks.
    """
    if small.limit(rows + 1).count() <= rows:
        return big.join(F.broadcast(small), on, how)
    salted = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return big.withColumn("_salt", F.pmod(F.xxhash64(*[big[c] for c in big.columns]), F.lit(salts)).cast("int")).join(salted, [*on, "_salt"], how).drop("_salt")


#: Up to so many rows are ordered by one window; beyond, ranges are ordered apart and their totals carried over.
ORDERED_ROWS = 1_000_000


def running(df: DataFrame, by: list[str], order: list[str], sums: list[str], most: int = ORDERED_ROWS) -> DataFrame:
    """``df`` with ``before_<c>``, for each ``c`` in ``sums``, the sum of ``c`` over the rows of the same group that come earlier in ``order``.

    Exact at every size. ``df`` is written first. Few rows take one window a group.
    Many are dealt by range of (by, order); a window runs within each range, and the
    ranges' totals, one row a range and group, are carried over. ``by`` and ``order``
    together must not repeat, or the order among equals is open.
    """
    spark, rows = df.sparkSession, materialise(df, "ordered")
    zero = F.lit(0).cast("long")
    if rows.limit(most + 1).count() <= most:
        upto = Window.partitionBy(*by).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
        return rows.select("*", *[F.coalesce(F.sum(c).over(upto), zero).alias(f"before_{c}") for c in sums])
    parts = max(2, int(spark.conf.get("spark.sql.shuffle.partitions")))
    placed = materialise(rows.repartitionByRange(parts, *by, *order).withColumn("_range", F.spark_partition_id()), "ranges")
    totals = placed.groupBy(*by, "_range").agg(*[F.sum(c).alias(c) for c in sums])
    upto = Window.partitionBy(*by).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    carried = totals.select(*[F.col(c).alias(f"_by_{c}") for c in by], F.col("_range").alias("_at"), *[F.coalesce(F.sum(c).over(upto), zero).alias(f"_sum_{c}") for c in sums])
    # at most a row a range and one more a group
    same = (placed["_range"] == carried["_at"])
    for c in by:
        same = same & placed[c].eqNullSafe(carried[f"_by_{c}"])
    inside = Window.partitionBy("_range", *by).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    joined = placed.join(F.broadcast(carried), same)
    return joined.select(*[placed[c] for c in rows.columns], *[(F.coalesce(F.sum(placed[c]).over(inside), zero) + F.col(f"_sum_{c}")).alias(f"before_{c}") for c in sums])
