"""Toxicity by a chain of linear classifiers."""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from leakaudit.llm.common import lean, packed, pieces, utf8
from leakaudit.llm.sparse import FOLDS, MOST_LABELLED, Linear, Rows, fit_in_task, fit_linear, held_out, labelled_sample, telling

SLOTS = 1 << 18
STRIP = b".,;:!?%$*&#|\"'()[]"
#: The chain's order: kinds of toxic text as the labelled rows show them, the most frequent first, then the label itself.
KINDS = 3
CHAIN = (*(f"kind{k + 1}" for k in range(KINDS)), "toxic")
THRESHOLD = 0.5


def features(text: bytes, meta: list[str] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The presence of words and of their first 5 to 7 bytes, hashed; words alone, for the kinds. No metadata."""
    words = {w.strip(STRIP) for w in set(text.lower().split())}
    words.discard(b"")
    parts = words | {b"%d %s" % (n, w[:n]) for w in words for n in (5, 6, 7) if len(w) > n}
    index = np.unique(np.fromiter((zlib.crc32(p) % SLOTS for p in parts), np.int64, len(parts)))
    return index.astype(np.int32), np.ones(len(index), np.float32), np.unique(np.fromiter((zlib.crc32(w) % SLOTS for w in words), np.int32, len(words)))


def kinds(rows: list[np.ndarray], y: np.ndarray, most: int = KINDS, rounds: int = 20) -> np.ndarray:
    """Which of ``most`` kinds each row is of (row, kind): toxic rows grouped by the words that tell them from clean ones.

    Words that toxic rows have far oftener than others are grouped by the rows that
    hold them (k-means on unit vectors, begun with the farthest), the group in most
    rows first. A toxic row is of every kind of whose words it has one, so a row can
    be of several, or of none; clean rows are of none.
    """
    sizes = [len(r) for r in rows]
    flat = Rows(np.concatenate([np.zeros(0, np.int64), *rows]).astype(np.int64), np.ones(sum(sizes), np.float32), np.concatenate(([0], np.cumsum(sizes, dtype=np.int64))))
    on = np.bincount(flat.index, y[flat.owner()], SLOTS)
    off = np.bincount(flat.index, minlength=SLOTS) - on
    toxic, clean = max(1.0, y.sum()), max(1.0, len(y) - y.sum())
    words = np.flatnonzero(telling(flat, y, SLOTS) & (on >= 3) & (on / toxic > 10 * off / clean))
    found = np.zeros((len(rows), most), bool)
    if not len(words):
        return found
    place = np.full(SLOTS, -1)
    place[words] = np.arange(len(words))
    held = np.zeros((len(words), len(rows)), np.float32)
    use = (place[flat.index] >= 0) & (y[flat.owner()] > 0)
    held[place[flat.index[use]], flat.owner()[use]] = 1
    unit = held / np.maximum(1e-9, np.sqrt((held**2).sum(axis=1, keepdims=True)))
    centre = [unit[int(np.argmax(held.sum(axis=1)))]]
    while len(centre) < min(most, len(words)):
        centre.append(unit[int(np.argmin(np.max(unit @ np.stack(centre).T, axis=1)))])
    centre = np.stack(centre)
    for _ in range(rounds):
        group = np.argmax(unit @ centre.T, axis=1)
        centre = np.stack([unit[group == k].sum(axis=0) if (group == k).any() else centre[k] for k in range(len(centre))])
        centre /= np.maximum(1e-9, np.sqrt((centre**2).sum(axis=1, keepdims=True)))
    each = np.stack([held[group == k].any(axis=0) for k in range(len(centre))], axis=1)
    order = np.argsort(-each.sum(axis=0), kind="stable")
    found[:, : len(order)] = each[:, order]
    return found


def fit_chain(rows: Rows, targets: np.ndarray, seed: int = 1) -> list[Linear]:
    """One model per column of ``targets``; each takes the earlier ones' probabilities as inputs.

    What a later model learns from are out-of-fold predictions, made by models that
    didn't see the row, so it meets inputs as uncertain as it will in use.
    """
    n, chain = len(rows), []
    fold = np.arange(n) % FOLDS
    given = np.zeros((n, 0))
    for k in range(targets.shape[1]):
        y = targets[:, k].astype(float)
        chain.append(fit_linear(rows, given, y, SLOTS, epochs=24, decay=1e-5, seed=seed))
        if k + 1 < targets.shape[1]:
            out = np.zeros(n)
            for f in range(FOLDS):
                here, rest = np.flatnonzero(fold == f), np.flatnonzero(fold != f)
                if len(here) and len(rest):
                    model = fit_linear(rows.take(rest), given[rest], y[rest], SLOTS, epochs=8, decay=1e-5, seed=seed)
                    out[here] = model.predict(rows.take(here), given[here])
            given = np.column_stack((given, out))
    return chain


def predict_chain(chain: list[Linear], rows: Rows) -> np.ndarray:
    given = np.zeros((len(rows), 0))
    for model in chain:
        given = np.column_stack((given, model.predict(rows, given)))
    return given


def _fit(rows: list, labels: list[int]) -> bytes:
    y = np.array(labels, np.int64) == 1
    every = Rows.of([r[:2] for r in rows])
    targets = np.column_stack((kinds([r[2] for r in rows], y.astype(float)), y))
    # hashed features outnumber rows by far: only those that tell the classes apart take part
    return pickle.dumps(fit_chain(every.only(telling(every, y.astype(float), SLOTS)), targets))


def _fit_alone(rows: list, labels: list[int]) -> bytes:
    y = (np.array(labels, np.int64) == 1).astype(float)
    every = Rows.of([r[:2] for r in rows])
    return pickle.dumps([fit_linear(every.only(telling(every, y, SLOTS)), np.zeros((len(rows), 0)), y, SLOTS, epochs=24, decay=1e-5)])


def train(docs: DataFrame, labels: DataFrame, label: str = "toxic", most: int = MOST_LABELLED) -> list[Linear]:
    """The chain, fitted on at most ``most`` labelled rows outside the held-out fold."""
    return pickle.loads(fit_in_task(labelled_sample(docs, labels, label, most), features, _fit))


def train_alone(docs: DataFrame, labels: DataFrame, label: str = "toxic", most: int = MOST_LABELLED) -> list[Linear]:
    """What the chain is compared with: one model of the label on the same rows and features, without the kinds."""
    return pickle.loads(fit_in_task(labelled_sample(docs, labels, label, most), features, _fit_alone))


NAMES = tuple(f"p_{c}" for c in CHAIN)


def _scored(docs: DataFrame, chain: list[Linear], text: str, threshold: float) -> DataFrame:
    """``row`` (all columns as a struct), the chain's probabilities and ``rejected``; a text without a word is never rejected."""
    blob, names = pickle.dumps(chain), NAMES[-len(chain) :]
    rows = docs.select(packed(docs).alias("row"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        models = pickle.loads(blob)
        for part in pieces(batches, "text", 4 << 20):
            found = [features(x)[:2] for x in utf8(part.column("text"))]
            p = predict_chain(models, Rows.of(found))
            any_word = np.array([len(i) > 0 for i, _ in found])
            yield pa.RecordBatch.from_arrays([part.column("row"), *(pa.array(p[:, k], pa.float64()) for k in range(len(names))), pa.array((p[:, -1] >= threshold) & any_word)], ["row", *names, "rejected"])

    kind = T.StructType([rows.schema["row"], *(T.StructField(n, T.DoubleType()) for n in names), T.StructField("rejected", T.BooleanType())])
    return rows.mapInArrow(run, kind)


def classify(docs: DataFrame, chain: list[Linear], text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """``row`` (all columns of ``docs`` as a struct, whatever they are called), ``p_kind1..p_toxic`` and ``rejected``, row by row.

    Null and empty texts hold no word and are kept; no rows give none.
    """
    return _scored(docs, chain, text, threshold)


def measure(scored: DataFrame, labels: DataFrame, label: str = "toxic", doc_id: str = "doc_id") -> DataFrame:
    """One row on the labelled rows of the held-out fold: ``n, caught, left_alone, log_loss`` of ``classify``'s ``p_toxic`` and ``rejected``."""
    y = labels.where(held_out(F.col(doc_id)) & F.col(label).isNotNull()).select(F.col(doc_id).cast("long").alias("_id"), F.col(label).cast("int").alias("_y"))
    rows = scored.join(y, F.col("row")[doc_id].cast("long") == F.col("_id"))
    p = F.greatest(F.lit(1e-6), F.least(F.lit(1 - 1e-6), F.when(F.col("_y") == 1, F.col("p_toxic")).otherwise(1 - F.col("p_toxic"))))
    hit = F.col("rejected").cast("double")
    return rows.agg(F.count(F.lit(1)).alias("n"), F.avg(F.when(F.col("_y") == 1, hit)).alias("caught"), F.avg(F.when(F.col("_y") == 0, 1 - hit)).alias("left_alone"), F.avg(-F.log(p)).alias("log_loss"))


def keep_clean(docs: DataFrame, labels: DataFrame, text: str = "text", source: DataFrame | None = None) -> DataFrame:
    """The rows of ``docs`` that the chain, learnt from ``source`` (``docs`` if none), doesn't reject."""
    chain = train(docs if source is None else source, labels)
    return _scored(docs, chain, text, THRESHOLD).where(~F.col("rejected")).select("row.*")
