"""White-box targets with dense layers: a small numpy network, and an adapter for ONNX files."""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from leakaudit.operators.rows import SAMPLES_AT_ONCE
from leakaudit.operators.scores import BY
from leakaudit.runtime import batch_rows, materialise

SCHEMA = "sample_id long, pos int, layer int, logp double, mu double, sigma double, z double, entropy double, act array<double>"


def statistics(logits: np.ndarray, true: np.ndarray, moments: str = "uniform", entropy: bool = True) -> tuple[np.ndarray, ...]:
    """Per row of ``logits``: log-probability of the true token, mean and deviation of all logits, Z-score and entropy.

    ``moments``: over the vocabulary alike, or weighted by the model's own
    probabilities. Where all logits are equal the Z-score is 0. Without ``entropy`` that is none.
    """
    top = logits.max(axis=1, keepdims=True)
    e = np.exp(logits - top)
    p = e / e.sum(axis=1, keepdims=True)
    each = np.arange(len(true))
    logp = np.log(np.maximum(p, 1e-300)) if entropy else None
    own = logits[each, true]
    if moments == "uniform":
        mu, sigma = logits.mean(axis=1), logits.std(axis=1)
    else:
        mu = (p * logits).sum(axis=1)
        sigma = np.sqrt(np.maximum(0, (p * (logits - mu[:, None]) ** 2).sum(axis=1)))
    z = np.where(sigma > 1e-12, (own - mu) / np.where(sigma > 1e-12, sigma, 1), 0)
    if not entropy:
        return np.log(np.maximum(p[each, true], 1e-300)), mu, sigma, z, None
    return logp[each, true], mu, sigma, z, -(p * logp).sum(axis=1)


@dataclass
class NumpyTarget:
    """Hashed tokens, three positions of context, layers of fixed random weights, and an output layer that learns.

    ``half`` rounds weights and activations to float16 and back.
    """

    size: int = 512
    width: int = 32
    layers: int = 6
    seed: int = 5
    half: bool = False
    output: np.ndarray | None = None

    def __post_init__(self):
        rng = np.random.default_rng(self.seed)
        self.embedding = rng.normal(0, 1, (self.size, self.width))
        self.hidden = [rng.normal(0, (3 * self.width if k == 0 else self.width) ** -0.5, (3 * self.width if k == 0 else self.width, self.width)) for k in range(self.layers)]
        if self.output is None:
            self.output = np.zeros((self.width * self.layers + 1, self.size))

    def _round(self, x: np.ndarray) -> np.ndarray:
        return x.astype(np.float16).astype(np.float64) if self.half else x

    def ids(self, tokens: list[str]) -> np.ndarray:
        return np.fromiter((zlib.crc32(t.encode()) % self.size for t in tokens), np.int64, len(tokens))

    def forward(self, ids: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        """Logits for each position given the three before it, and each layer's activations."""
        padded = np.concatenate((np.zeros(3, np.int64), ids))
        x = np.concatenate([self._round(self.embedding)[padded[3 - b : len(padded) - b]] for b in (1, 2, 3)], axis=1)
        acts = []
        for w in self.hidden:
            x = self._round(np.tanh(x @ self._round(w)))
            acts.append(x)
        return np.concatenate([*acts, np.ones((len(ids), 1))], axis=1) @ self._round(self.output), acts

    def fit(self, sequences: list[list[str]], epochs: int = 3, rate: float = 0.5) -> NumpyTarget:
        """Cross-entropy on a bounded list of member sequences; only the output layer moves."""
        for _ in range(epochs):
            for tokens in sequences:
                ids = self.ids(tokens)
                if not len(ids):
                    continue
                logits, acts = self.forward(ids)
                p = np.exp(logits - logits.max(axis=1, keepdims=True))
                p /= p.sum(axis=1, keepdims=True)
                p[np.arange(len(ids)), ids] -= 1
                self.output -= rate / len(ids) * np.concatenate([*acts, np.ones((len(ids), 1))], axis=1).T @ p
        return self


def _run(open_: Callable, moments: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = open_()
        for batch in batches:
            for sample, keys in zip(batch.column("sample_id").to_pylist(), batch.column("keys").to_pylist(), strict=True):
                if not keys:
                    continue
                ids = model.ids(keys)
                logits, acts = model.forward(ids)
                stats = statistics(np.asarray(logits, np.float64), ids, moments)
                n, k = len(ids), len(acts)
                columns = [pa.array([sample] * n * k, pa.int64()), pa.array(np.tile(np.arange(1, n + 1), k), pa.int32()), pa.array(np.repeat(np.arange(k), n), pa.int32()), *(pa.array(np.tile(s, k)) for s in stats)]
                flat = np.concatenate([np.asarray(a, np.float64) for a in acts])
                columns.append(pa.FixedSizeListArray.from_arrays(pa.array(flat.ravel()), flat.shape[1]).cast(pa.list_(pa.float64())))
                yield pa.RecordBatch.from_arrays(columns, ["sample_id", "pos", "layer", "logp", "mu", "sigma", "z", "entropy", "act"])

    return run


def _sequences(tokens: DataFrame) -> DataFrame:
    """``sample_id, keys``: a sample's scored tokens in order; whole texts unless the token table was cut by ``max_tokens``."""
    return tokens.groupBy("sample_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("t", "key"))), lambda x: x["key"]).alias("keys"))


def train(tokens: DataFrame, most: int = 200, **options) -> NumpyTarget:
    """A numpy target fitted on at most ``most`` member samples, in hash order."""
    some = _sequences(tokens.where("is_member")).orderBy(F.xxhash64("sample_id")).limit(most)
    return NumpyTarget(**options).fit([r.keys for r in some.collect()])


def forward(tokens: DataFrame, target: NumpyTarget, moments: str = "uniform") -> DataFrame:
    """Token statistics and activations of every layer, one pass, no gradient; a vocabulary-wide vector lives inside a batch only."""
    blob = pickle.dumps(target)
    return _sequences(tokens).mapInArrow(_run(lambda: pickle.loads(blob), moments), SCHEMA)


#: So many positions of a text have their logits at once.
POSITIONS = 1024


def train_rows(table: DataFrame, most: int = 200, **options) -> NumpyTarget:
    """``train`` of a table of rows (``operators.rows``): ids alone are ordered, the driver gets the chosen rows only."""
    members, at = table.where("is_member and size(key) > 0"), F.xxhash64("sample_id")
    ids = [r.sample_id for r in members.select("sample_id").orderBy(at).limit(most).collect()]
    chosen = members.where(F.col("sample_id").isin(ids)).select(at.alias("at"), "key").collect() if ids else []
    return NumpyTarget(**options).fit([r.key for r in sorted(chosen, key=lambda r: r["at"])])


def per_sample(table: DataFrame, target: NumpyTarget) -> DataFrame:
    """``BY, loss, weighted_z`` of a table of rows: a text's logits are worked out some positions at a time, and only its sums leave the worker."""
    blob = pickle.dumps(target)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = pickle.loads(blob)
        for batch in batches:
            loss, weighted, of = [], [], []
            for row, (keys, weights) in enumerate(zip(batch.column("key"), batch.column("weight"), strict=True)):
                if not len(keys):
                    continue
                ids, w = model.ids(keys.as_py()), weights.values.to_numpy(zero_copy_only=False)
                total = np.zeros(2)
                for a in range(0, len(ids), POSITIONS):
                    # a position depends on the three tokens before it
                    skip, to = min(3, a), a + POSITIONS
                    logits = model.forward(ids[a - skip : to])[0][skip:]
                    logp, _, _, z, _ = statistics(logits, ids[a:to], entropy=False)
                    total += logp.sum(), (w[a:to] / (1 + np.exp(-z))).sum()
                of.append(row)
                loss.append(total[0] / len(ids))
                weighted.append(total[1] / w.sum())
            yield pa.RecordBatch.from_arrays([*(batch.column(c).take(pa.array(of, pa.int64())) for c in BY), pa.array(loss, pa.float64()), pa.array(weighted, pa.float64())], [*BY, "loss", "weighted_z"])

    out = T.StructType([*(table.schema[c] for c in BY), T.StructField("loss", T.DoubleType()), T.StructField("weighted_z", T.DoubleType())])
    with batch_rows(table.sparkSession, SAMPLES_AT_ONCE):
        return materialise(table.select(*BY, "key", "weight").mapInArrow(run, out), "dense")


@dataclass
class OnnxTarget:
    """A user's ONNX file: an input of ids (1, n), an output of logits (1, n, size), further outputs taken as layers.

    The logits at a position predict the next one, so they are moved by one place;
    the first token is predicted by none and gets the mean of all logits.
    """

    model: bytes
    tokenizer: Callable[[list[str]], np.ndarray]
    logits: str = "logits"

    def __post_init__(self):
        self._session = None

    def __getstate__(self):
        return self.__dict__ | {"_session": None}

    def ids(self, tokens: list[str]) -> np.ndarray:
        return self.tokenizer(tokens)

    def forward(self, ids: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        if self._session is None:
            import onnxruntime

            options = onnxruntime.SessionOptions()
            options.intra_op_num_threads = 1
            self._session = onnxruntime.InferenceSession(self.model, options, providers=["CPUExecutionProvider"])
        names = [o.name for o in self._session.get_outputs()]
        found = dict(zip(names, self._session.run(names, {self._session.get_inputs()[0].name: ids[None].astype(np.int64)}), strict=True))
        logits = found.pop(self.logits)[0]
        moved = np.concatenate((np.zeros_like(logits[:1]), logits[:-1]))
        return moved, [a[0] for a in found.values()]


def forward_onnx(tokens: DataFrame, target: OnnxTarget, moments: str = "uniform") -> DataFrame:
    """As ``forward``, one session per worker."""
    from pyspark import cloudpickle

    blob = cloudpickle.dumps(target)
    return _sequences(tokens).mapInArrow(_run(lambda: pickle.loads(blob), moments), SCHEMA)
