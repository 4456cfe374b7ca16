"""Sparse rows, logistic models and the bounded labelled sample that they are fitted on."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from leakaudit.llm.common import lean, pieces, utf8

#: Labelled rows that a model is fitted on, the bound of the sample.
MOST_LABELLED = 8_000
BATCH = 128
FOLDS = 5


def held_out(doc_id: Column) -> Column:
    """The fold no model learns from: crc32 of the doc_id as text is a multiple of five; a null doc_id is held out."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % FOLDS == 0, F.lit(True))


@dataclass
class Rows:
    """Compressed sparse rows."""

    index: np.ndarray
    value: np.ndarray
    bounds: np.ndarray

    @classmethod
    def of(cls, rows: list[tuple[np.ndarray, np.ndarray]]) -> Rows:
        sizes = [len(i) for i, _ in rows]
        none = np.zeros(0)
        return cls(np.concatenate([none.astype(np.int64), *(i for i, _ in rows)]).astype(np.int64), np.concatenate([none, *(v for _, v in rows)]).astype(np.float32), np.concatenate(([0], np.cumsum(sizes, dtype=np.int64))))

    def __len__(self) -> int:
        return len(self.bounds) - 1

    def take(self, which: np.ndarray) -> Rows:
        size = self.bounds[which + 1] - self.bounds[which]
        upto = np.cumsum(size)
        at = np.repeat(self.bounds[which] - (upto - size), size) + np.arange(int(upto[-1]) if len(upto) else 0)
        return Rows(self.index[at], self.value[at], np.concatenate(([0], upto)))

    def owner(self) -> np.ndarray:
        return np.repeat(np.arange(len(self)), np.diff(self.bounds))

    def sums(self, each: np.ndarray) -> np.ndarray:
        """Per row the sum of ``each`` (one value or vector an entry)."""
        if each.ndim == 1:
            return np.bincount(self.owner(), each, len(self))
        return np.stack([np.bincount(self.owner(), each[:, k], len(self)) for k in range(each.shape[1])], axis=1)


    def only(self, keep: np.ndarray) -> Rows:
        """The rows without the features that ``keep`` marks false."""
        at = keep[self.index]
        return Rows(self.index[at], self.value[at], np.concatenate(([0], np.cumsum(at)))[self.bounds])


def telling(rows: Rows, y: np.ndarray, size: int, least: float = 4.0) -> np.ndarray:
    """Features whose share among the positive rows differs from that among the others by ``least`` standard errors."""
    pos, neg = max(1.0, float(y.sum())), max(1.0, float(len(y) - y.sum()))
    on = np.bincount(rows.index, y[rows.owner()], size)
    off = np.bincount(rows.index, minlength=size) - on
    every = (on + off + 1) / (pos + neg + 2)
    return np.abs(on / pos - off / neg) >= least * np.sqrt(every * (1 - np.minimum(every, 0.999)) * (1 / pos + 1 / neg))


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


@dataclass
class Linear:
    """A logistic model: a weight per hashed feature, and a few dense inputs."""

    weight: np.ndarray
    dense: np.ndarray
    bias: float

    def predict(self, rows: Rows, dense: np.ndarray) -> np.ndarray:
        return sigmoid(self.bias + rows.sums(rows.value * self.weight[rows.index]) + dense @ self.dense)


def fit_linear(rows: Rows, dense: np.ndarray, y: np.ndarray, size: int, epochs: int = 8, rate: float = 0.3, decay: float = 1e-4, seed: int = 1) -> Linear:
    """Mini-batches with per-weight steps (squared gradients summed)."""
    rng, w, d, b = np.random.default_rng(seed), np.zeros(size), np.zeros(dense.shape[1]), 0.0
    gw, gd, gb = np.full(size, 1e-6), np.full(dense.shape[1], 1e-6), 1e-6
    for _ in range(epochs):
        order = rng.permutation(len(rows))
        for at in range(0, len(order), BATCH):
            some = order[at : at + BATCH]
            part, x = rows.take(some), dense[some]
            e = sigmoid(b + part.sums(part.value * w[part.index]) + x @ d) - y[some]
            g = np.bincount(part.index, part.value * e[part.owner()], size) / len(some) + decay * w
            gw += g * g
            w -= rate * g / np.sqrt(gw)
            g = x.T @ e / len(some) + decay * d
            gd += g * g
            d -= rate * g / np.sqrt(gd)
            gb += e.mean() ** 2
            b -= rate * e.mean() / np.sqrt(gb)
    return Linear(w.astype(np.float32), d, b)


@dataclass
class Machine:
    """A factorisation machine: pairwise weights of rank k, scored in time linear in the entries."""

    weight: np.ndarray
    factor: np.ndarray
    bias: float

    def margin(self, rows: Rows) -> np.ndarray:
        vx = self.factor[rows.index] * rows.value[:, None]
        total = rows.sums(vx)
        # the sum over pairs is half of (square of the sum less sum of the squares)
        return self.bias + rows.sums(rows.value * self.weight[rows.index]) + 0.5 * (total**2 - rows.sums(vx**2)).sum(axis=1)

    def predict(self, rows: Rows) -> np.ndarray:
        return sigmoid(self.margin(rows))


def fit_machine(rows: Rows, y: np.ndarray, size: int, rank: int = 8, epochs: int = 8, rate: float = 0.1, decay: float = 1e-4, seed: int = 1) -> Machine:
    rng = np.random.default_rng(seed)
    m = Machine(np.zeros(size), rng.normal(0, 0.02, (size, rank)), 0.0)
    gw, gf, gb = np.full(size, 1e-4), np.full((size, rank), 1e-4), 1e-4
    for _ in range(epochs):
        order = rng.permutation(len(rows))
        for at in range(0, len(order), BATCH):
            some = order[at : at + BATCH]
            part = rows.take(some)
            vx = m.factor[part.index] * part.value[:, None]
            total = part.sums(vx)
            e = (m.predict(part) - y[some]) / len(some)
            owner = part.owner()
            ex = e[owner] * part.value
            g = np.bincount(part.index, ex, size) + decay * m.weight
            gw += g * g
            m.weight -= rate * g / np.sqrt(gw)
            slope = ex[:, None] * (total[owner] - vx)
            g = np.stack([np.bincount(part.index, slope[:, k], size) for k in range(rank)], axis=1) + decay * m.factor
            gf += g * g
            m.factor -= rate * g / np.sqrt(gf)
            gb += e.sum() ** 2
            m.bias -= rate * e.sum() / np.sqrt(gb)
    m.weight, m.factor = m.weight.astype(np.float32), m.factor.astype(np.float32)
    return m


def metadata(names: tuple[str, ...]) -> Column:
    """The named columns as an array of strings, ``name=value``; numbers by the power of two that they reach, nulls as such."""
    size = lambda c: F.floor(F.log2(F.greatest(c.try_cast("double"), F.lit(0.0)) + 1)).cast("string")
    return F.array(*[F.concat(F.lit(f"{n}="), F.coalesce(size(F.col(n)), F.col(n).cast("string"), F.lit(""))) for n in names]).cast("array<string>")


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, most: int = MOST_LABELLED, doc_id: str = "doc_id", text: str = "text", meta: tuple[str, ...] = ()) -> DataFrame:
    """``doc_id, text, meta, label`` of at most ``most`` labelled rows outside the held-out fold.

    Rows are taken in hash order of the doc_id, so the sample is the same in every
    run; ids with two different labels, null labels and null ids are left out.
    """
    one = labels.where(F.col(doc_id).isNotNull() & F.col(label).isNotNull() & ~held_out(F.col(doc_id)))
    one = one.groupBy(F.col(doc_id).cast("long").alias("_id")).agg(F.min(label).cast("int").alias("label"), F.max(label).cast("int").alias("_other")).where("label = _other")
    # bounded by ``most`` rows
    few = F.broadcast(one.orderBy(F.xxhash64("_id"), "_id").limit(most).select("_id", "label"))
    return docs.join(few, F.col(doc_id).cast("long") == few["_id"]).select(F.col("_id").alias("doc_id"), F.col(text).cast("string").alias("text"), metadata(meta).alias("meta"), "label")


def fit_in_task(sample: DataFrame, extract: Callable[[bytes, list[str]], tuple], fit: Callable[[list, list[int]], bytes]) -> bytes:
    """Features are taken where the rows are; one task fits the bounded sample; the model's bytes come back."""

    @lean
    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in pieces(batches, "text"):
            found = [extract(x, m) for x, m in zip(utf8(part.column("text")), part.column("meta").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id"), part.column("label"), *(pa.array([x[k] for x in found], pa.list_(kind)) for k, kind in enumerate((pa.int32(), pa.float32(), pa.int32())))],
                ["doc_id", "label", "index", "value", "extra"])

    @lean
    def train(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, label, seen = [], [], []
        for b in batches:
            lists = [b.column(c) for c in ("index", "value", "extra")]
            for k in range(b.num_rows):
                rows.append(tuple(x[k].values.to_numpy(zero_copy_only=False) for x in lists))
            label += b.column("label").to_pylist()
            seen += b.column("doc_id").to_pylist()
        order = sorted(range(len(seen)), key=lambda k: (seen[k], len(rows[k][0])))
        yield pa.RecordBatch.from_arrays([pa.array([fit([rows[k] for k in order], [label[k] for k in order])], pa.binary())], ["model"])

    table = sample.mapInArrow(features, "doc_id long, label int, index array<int>, value array<float>, extra array<int>")
    return bytes(table.repartition(1).mapInArrow(train, "model binary").first()[0])
