"""Quality scores by a factorisation machine."""

from __future__ import annotations

import pickle
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from leakaudit.llm.common import lean, pieces, utf8
from leakaudit.llm.sparse import MOST_LABELLED, Machine, Rows, fit_in_task, fit_machine, held_out, labelled_sample, metadata

SLOTS = 1 << 16
#: Structure statistics are cut into bins, one feature each; they come after the hashed words, and after them hashed metadata.
BINS = 16
META = 1 << 10
THRESHOLD = 0.3
#: Byte classes that are counted (fixed values).
CLASSES = (b"0123456789", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b".,;:", b"!?", b"#$%&*|<>{}[]=~^_\\/", b"\n")
STATISTICS = len(CLASSES) + 8


def statistics(text: bytes, words: list[bytes], counts: Counter) -> list[float]:
    """Shares from 0 to 1, and logarithms of lengths."""
    size, n = max(1, len(text)), max(1, len(words))
    shares = [(len(text) - len(text.translate(None, c))) / size for c in CLASSES]
    lines = [x for x in text.split(b"\n") if x.strip()]
    return [
        *(min(1.0, 8 * s) for s in shares),
        len(counts) / n,
        len(set(lines)) / max(1, len(lines)),
        max(counts.values(), default=0) / n,
        sum(a == b for a, b in zip(words, words[1:], strict=False)) / n,
        sum(not w[-1:].isalnum() and w[-1] < 128 for w in words) / n,
        min(1.0, size / n / 20),
        min(1.0, np.log1p(n) / 12),
        min(1.0, np.log1p(len(text)) / 14),
    ]


def features(text: bytes, meta: list[str] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashed words, weighted by the logarithm of their count, binned statistics, and metadata (``name=value``): each of the three of unit length together."""
    meta = meta or []
    words = text.split()
    counts = Counter(words)
    index = np.fromiter((zlib.crc32(w) % SLOTS for w in counts), np.int64, len(counts))
    value = np.log1p(np.fromiter(counts.values(), np.float64, len(counts)))
    value /= max(1e-9, np.sqrt((value**2).sum()))
    binned = [SLOTS + k * BINS + min(BINS - 1, int(s * BINS)) for k, s in enumerate(statistics(text, words, counts))]
    about = [SLOTS + STATISTICS * BINS + zlib.crc32(m.encode()) % META for m in meta]
    weight = np.concatenate((value, np.full(STATISTICS, 1 / np.sqrt(STATISTICS)), np.full(len(meta), 1 / np.sqrt(max(1, len(meta))))))
    return np.concatenate((index, binned, about)).astype(np.int32), weight.astype(np.float32), np.zeros(0, np.int32)


def _fit(rows: list, labels: list[int]) -> bytes:
    return pickle.dumps(fit_machine(Rows.of([r[:2] for r in rows]), np.array(labels, float), SLOTS + STATISTICS * BINS + META))


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", most: int = MOST_LABELLED, meta: tuple[str, ...] = ()) -> Machine:
    """Fitted on at most ``most`` labelled rows outside the held-out fold; without any, every score is one half.

    ``meta`` names columns of ``docs`` that are inputs too; ``score`` must be given the same.
    """
    return pickle.loads(fit_in_task(labelled_sample(docs, labels, label, most, meta=meta), features, _fit))


def score(docs: DataFrame, model: Machine, doc_id: str = "doc_id", text: str = "text", meta: tuple[str, ...] = ()) -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every row. Null texts score as empty ones, repeated rows alike; no rows give none."""
    blob = pickle.dumps(model)

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = pickle.loads(blob)
        for part in pieces(batches, "text", 2 << 20):
            rows = Rows.of([features(x, m)[:2] for x, m in zip(utf8(part.column("text")), part.column("meta").to_pylist(), strict=True)])
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("held_out"), pa.array(machine.predict(rows), pa.float64())], ["doc_id", "held_out", "score"])

    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), held_out(F.col(doc_id)).alias("held_out"), F.col(text).cast("string").alias("text"), metadata(meta).alias("meta"))
    scored = rows.mapInArrow(run, "doc_id long, held_out boolean, score double")
    return scored.withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))


def measure(scored: DataFrame, labels: DataFrame, label: str = "quality") -> DataFrame:
    """One row on the labelled rows of the held-out fold: ``n, auc, accuracy`` of ``score``'s result."""
    y = labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y"))
    rows = scored.where("held_out").join(y, "doc_id").groupBy(F.round("score", 9).alias("score")).agg(F.sum("y").alias("pos"), F.sum(1 - F.col("y")).alias("neg"), F.sum((F.col("predicted") == F.col("y")).cast("long")).alias("right"))
    # distinct scores of the labelled rows of one fold, not of the corpus, are ordered
    below = F.coalesce(F.sum("neg").over(Window.orderBy("score").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return rows.withColumn("below", below).agg(
        F.sum(F.col("pos") + F.col("neg")).alias("n"), (F.sum(F.col("pos") * (F.col("below") + F.col("neg") / 2)) / F.nullif(F.sum("pos") * F.sum("neg"), F.lit(0))).alias("auc"), (F.sum("right") / F.sum(F.col("pos") + F.col("neg"))).alias("accuracy"))
