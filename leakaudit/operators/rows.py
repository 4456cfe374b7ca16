"""The audit with a sample's tokens in its row: tokens stay where their text is read, and the dictionary and the target come to them.

For dictionaries and targets of bounded size, which each worker reads from the shared
folder and holds as arrays. Larger ones take ``tokens`` and ``target``, which give
the same figures by shuffled joins.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterable, Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs
import pyarrow.parquet as pq
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from leakaudit.functions import lexer, lexing
from leakaudit.functions.weights import Scheme
from leakaudit.operators import activation, scores, target
from leakaudit.operators.tokens import CONTEXTS, KEEP, OVERLAYS, SEPARATOR, _listed, _numbers, _slices, _upto
from leakaudit.runtime import batch_rows, materialise, trim

#: Most words of a dictionary, and most pairs of context and token of one layer of a target, that a worker holds.
WORDS, PAIRS = 2_000_000, 8_000_000
#: Samples that an Arrow batch holds: tokens are worked on in smaller slices, but a batch crosses whole.
SAMPLES_AT_ONCE = 256


def _search(ordered: np.ndarray, some: np.ndarray) -> np.ndarray:
    """``np.searchsorted``, in order: each search then begins in memory that the one before has touched."""
    order, at = np.argsort(some), np.empty(len(some), np.int64)
    at[order] = np.searchsorted(ordered, some[order])
    return at


class Index:
    """Distinct strings and their places, found by digest and then compared, in some 16 bytes a string besides its own."""

    def __init__(self, values: pa.Array):
        digest = self._digests(values)
        order = np.argsort(digest, kind="stable")
        self.digest, self.values, self.order, self.df = digest[order], values.take(pa.array(order)).cast(pa.large_string()), order, None

    @staticmethod
    def _digests(values: pa.Array) -> np.ndarray:
        # by way of numpy: a list of Arrow's own makes an object for each element first
        return np.fromiter(map(xxhash.xxh3_64_intdigest, values.to_numpy(zero_copy_only=False).tolist()), np.uint64, len(values))

    def __len__(self) -> int:
        return len(self.values)

    def distinct(self, some: pa.Array) -> np.ndarray:
        """The place of each, -1 where it isn't there."""
        found = np.full(len(some), -1, np.int64)
        if not len(self) or not len(some):
            return found
        digest, left = self._digests(some), np.arange(len(some))
        at = _search(self.digest, digest)
        while len(left):  # equal digests stand side by side
            left = left[at[left] < len(self)]
            left = left[self.digest[at[left]] == digest[left]]
            same = pc.equal(self.values.take(pa.array(at[left])), some.take(pa.array(left)).cast(pa.large_string())).to_numpy(zero_copy_only=False).astype(bool)
            found[left[same]] = at[left[same]]
            left = left[~same]
            at[left] += 1
        return found

    def find(self, some: pa.Array) -> np.ndarray:
        coded = some.dictionary_encode()
        return self.distinct(coded.dictionary)[_numbers(coded.indices)] if len(some) else np.zeros(0, np.int64)


def _opened(uri: str) -> tuple[pa.fs.FileSystem, str]:
    return pa.fs.FileSystem.from_uri(re.sub("^file:/*", "file:///", uri))


def _read(files: tuple[str, ...]) -> Iterator[pa.Table]:
    for store, path in map(_opened, files):
        yield pq.read_table(path, filesystem=store, use_threads=False)


class Written:
    """What ``make`` makes of written tables, ``value`` of a broadcast without the driver: a worker reads the files when it first asks, and keeps the last value."""

    kept: tuple = (None, None)

    def __init__(self, make: Callable, *files: tuple[str, ...]):
        self.make, self.files = make, files

    @property
    def value(self):
        if Written.kept[0] != self.files:
            Written.kept = (None, None)  # the one before goes first
            pa.set_memory_pool(pa.system_memory_pool())
            Written.kept = (self.files, self.make(*map(_read, self.files)))  # file by file
            trim()
        return Written.kept[1]


def _sent(make: Callable, *tables: DataFrame):
    """``Written``; a broadcast, made on the driver, where the shared folder is in a store that Arrow doesn't open."""
    try:
        files = [tuple(sorted(t.inputFiles())) for t in tables]
        for some in files:
            _opened(some[0])
    except (pa.ArrowException, ValueError, OSError):
        return tables[0].sparkSession.sparkContext.broadcast(make(*([t.toArrow()] for t in tables)))
    return Written(make, *files)


def _word_index(words: Iterable[pa.Table]) -> Index:
    found = pa.concat_tables(words)
    index = Index(pa.concat_arrays(found.column("word").chunks or [pa.array([], pa.string())]))
    if "df" in found.column_names:
        index.df = found.column("df").to_numpy()[index.order]
    return index


def _string_index(strings: Iterable[pa.Table]) -> Index:
    return Index(pa.concat_arrays([c for t in strings for c in t.column("s").chunks] or [pa.array([], pa.string())]))


def _coded_model(strings: Iterable[pa.Table], coded: Iterable[pa.Table], size: int, v: int, alpha: float) -> Model:
    code, n, at = np.empty(size, np.int64), np.empty(size, np.int32), 0
    for t in coded:
        code[at : at + len(t)], n[at : at + len(t)], at = t.column("code").to_numpy(), t.column("n").to_numpy(), at + len(t)
    return Model(_string_index(strings), code, n, v, alpha)


def dictionary(words: DataFrame):
    """The words (``word``, a written table, and ``df`` if it is there) for the workers; none if they are more than ``WORDS``."""
    return None if words.limit(WORDS + 1).count() > WORDS else _sent(_word_index, words)


def _weights(scheme: Scheme, ident: np.ndarray, known: np.ndarray, size: np.ndarray, tag: np.ndarray, covered: list[np.ndarray]) -> np.ndarray:
    """``tokens.weighed`` over arrays."""
    comment, literal, lint = covered
    long = (size >= scheme.long_min) & ("long" in scheme.weights)
    weight = np.where(~ident, scheme["boilerplate"], np.where(long, scheme["long"], scheme["standard"])).astype(np.float64)
    for name, on in (("lint", lint), ("literal", literal), ("slippage", ident & ~known), ("comment", comment)):
        if name in scheme.weights:
            weight = np.where(on, np.maximum(weight, float(scheme[name])), weight)
    return np.where(tag, float(scheme["tag"]), weight) if "tag" in scheme.weights else weight


def _mean_weights(scheme: Scheme, own: np.ndarray, piece: lexer.Pieces, spans: list[tuple[str, int, int, int]], tag: np.ndarray) -> np.ndarray:
    """``mask.project_mean`` of ``own`` weights and ``mask.runs`` over arrays: spans and tags cover code points, tokens take the mean of what is added to theirs."""
    size, start, stop = int(piece.first[-1]), piece.first[piece.row] + piece.start, piece.first[piece.row] + piece.stop

    def over(first: np.ndarray, last: np.ndarray) -> np.ndarray:
        return np.cumsum(np.bincount(first, minlength=size + 1) - np.bincount(last, minlength=size + 1))[:size] > 0

    weight = np.zeros(size)
    for kind in OVERLAYS:
        some = np.array([(piece.first[row] + a, piece.first[row] + b) for k, row, a, b in spans if k == kind], np.int64).reshape(-1, 2)
        if len(some) and kind in scheme.weights:
            weight = np.where(over(some[:, 0], some[:, 1]), np.maximum(weight, float(scheme[kind])), weight)
    if tag.any():
        weight[over(start[tag], stop[tag])] = float(scheme["tag"])
    gain = np.zeros(len(own))
    for w in np.unique(weight[weight > 0]):
        upto = np.concatenate(([0], np.cumsum(weight == w)))
        gain += (upto[stop] - upto[start]) * np.maximum(0.0, w - own)
    return own + gain / np.maximum(1, stop - start)


def _lower(some: pa.Array) -> pa.Array:
    low, wide = pc.ascii_lower(some), pc.not_equal(pc.binary_length(some), pc.utf8_length(some))
    return pc.replace_with_mask(low, wide, pa.array([x.lower() for x in some.filter(wide).to_pylist()], low.type))


class _Words:
    """The distinct tokens of some pieces: which each is, their keys, lengths, and whether they are identifiers."""

    def __init__(self, piece: lexer.Pieces, grammar: str | None = None):
        coded = piece.tok.dictionary_encode()
        self.of, self.tok = _numbers(coded.indices), coded.dictionary
        self.key, self.size, self.ident = _lower(self.tok), _numbers(pc.utf8_length(self.tok)), np.zeros(len(self.tok), bool)
        self.ident[self.of] = piece.kind == lexer.LETTER
        self.ident &= self.size >= 3
        if grammar and lexing.KEYWORDS[grammar]:
            self.ident &= ~pc.is_in(self.key, value_set=pa.array(lexing.KEYWORDS[grammar], self.key.type)).to_numpy(zero_copy_only=False).astype(bool)


def lexicon(samples: DataFrame, min_df: int = 3, slice: str | None = "en") -> DataFrame:
    """``tokens.lexicon``, counted where the texts are read: a worker sends a word once for each slice of texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in lexer.slices(batches):
            piece = lexer.pieces(part.column("text"))
            word = _Words(piece)
            keys = word.key.dictionary_encode()
            on = word.ident[word.of]
            both = np.unique(piece.row[on] * max(1, len(keys.dictionary)) + _numbers(keys.indices)[word.of[on]])
            which, n = np.unique(both % max(1, len(keys.dictionary)), return_counts=True)
            yield pa.RecordBatch.from_arrays([keys.dictionary.take(pa.array(which)).cast(pa.string()), pa.array(n, pa.int64())], ["word", "df"])

    with batch_rows(samples.sparkSession, SAMPLES_AT_ONCE):
        rows = (samples.where(F.col("slice") == slice) if slice else samples).select("text").mapInArrow(run, "word string, df long")
        return materialise(rows.groupBy("word").agg(F.sum("df").alias("df")).where(F.col("df") >= min_df), "dictionary")


class _Seen:
    """The tokens of some texts, and what their weights depend on besides the scheme."""

    def __init__(self, text: pa.Array, grammar: str, words):
        self.piece = lexer.pieces(text)
        self.word = word = _Words(self.piece, grammar)
        self.spans = lexer.marks(text, grammar, self.piece.faulty)
        self.covered = lexer.spread(self.piece, self.spans, OVERLAYS)
        tag = pc.is_in(word.tok, value_set=pa.array(lexing.TAGS, word.tok.type)).to_numpy(zero_copy_only=False).astype(bool)
        #: The place of each distinct token in the dictionary, -1 where it isn't there.
        self.found = np.zeros(len(word.tok), np.int64) if words is None else words.value.distinct(word.key)
        self.ident, self.size, self.tag = word.ident[word.of], word.size[word.of], tag[word.of]

    def weights(self, scheme: Scheme, known: np.ndarray) -> np.ndarray:
        """``known``: of each distinct token."""
        return _weights(scheme, self.ident, known[self.word.of], self.size, self.tag, self.covered)


def weighings(samples: DataFrame, grammar: str, words, schemes: dict[str, Scheme]) -> DataFrame:
    """``name, weight, n``: how many tokens weigh so much under each scheme, a slice of texts after the other: a few rows for each. ``words``: as in ``masked``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in lexer.slices(batches):
            seen = _Seen(part.column("text"), grammar, words)
            for name, scheme in schemes.items():
                weight, n = np.unique(seen.weights(scheme, seen.found >= 0), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(weight), pa.string()), pa.array(weight), pa.array(n.astype(np.int64))], ["name", "weight", "n"])

    with batch_rows(samples.sparkSession, SAMPLES_AT_ONCE):
        rows = samples.where("text is not null").select("text").mapInArrow(run, "name string, weight double, n long")
        return materialise(rows.groupBy("name", "weight").agg(F.sum("n").alias("n")), "weighings")


def masked(samples: DataFrame, grammar: str, words, scheme: Scheme | None = None, least: tuple[int, ...] = (), mean: Scheme | None = None) -> DataFrame:
    """``KEEP, key, step, weight``, the last three lists: the scored tokens of each sample, written once.

    With ``least``, for each of these numbers ``weight_<number>`` instead of ``weight``:
    under the dictionary of the words with such a ``df`` at least. With ``mean``, also
    ``weight_mean``: a token's own weight under that scheme, and the mean over its
    characters of what the spans of ``scheme`` add to it.

    ``words``: from ``dictionary``; without it nothing is slippage. ``step``: by how
    much a token's number among all pieces exceeds that of the one before. Texts are
    lexed in the worker, and a word is judged once for each slice of them.
    """
    scheme, keep = scheme or Scheme.default(), [c for c in KEEP if c in samples.columns]
    rows, names = samples.where("text is not null").select(*keep, "text"), [f"weight_{m}" for m in least] or ["weight"]
    names += ["weight_mean"] if mean else []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in lexer.slices(batches):
            seen = _Seen(part.column("text"), grammar, words)
            piece, word, found = seen.piece, seen.word, seen.found
            known = [(found >= 0) & (words.value.df[found] >= m) for m in least] or [found >= 0]
            first = np.searchsorted(piece.row, np.arange(part.num_rows + 1))
            step = np.diff(piece.pos, prepend=0)
            begins = first[:-1][first[:-1] < first[1:]]
            step[begins] = piece.pos[begins]
            at, made = pa.array(first.astype(np.int32)), [seen.weights(scheme, k) for k in known]
            if mean:
                made.append(_mean_weights(scheme, seen.weights(mean, known[0]), piece, seen.spans, seen.tag))
            weights = map(pa.array, made)
            lists = [pa.ListArray.from_arrays(at, x) for x in (word.key.cast(pa.string()).take(pa.array(word.of)), pa.array(step.astype(np.int32)), *weights)]
            yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), *lists], [*keep, "key", "step", *names])

    out = T.StructType([*(rows.schema[c] for c in keep), *(T.StructField(c, T.ArrayType(k)) for c, k in (("key", T.StringType()), ("step", T.IntegerType()), *((c, T.DoubleType()) for c in names)))])
    with batch_rows(samples.sparkSession, SAMPLES_AT_ONCE):
        return materialise(rows.mapInArrow(run, out), "rows", "zstd")


def _placed(part: pa.RecordBatch) -> tuple[np.ndarray, pa.Array, np.ndarray]:
    """Row, key and number among the pieces of each token."""
    row, key = _listed(part.column("key"))
    return row, key, _upto(_numbers(part.column("step").flatten()), row)


def _flat(part: pa.RecordBatch) -> tuple[np.ndarray, pa.Array, np.ndarray, np.ndarray]:
    """``_placed``, and the weight of each token."""
    return *_placed(part), part.column("weight").flatten().to_numpy(zero_copy_only=False)


def _parts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in _slices(pa.RecordBatch.from_arrays([*b.columns, b.column("key")], [*b.schema.names, "toks"]) for b in batches):
        if part.num_rows:
            yield part.drop_columns(["toks"])


def _contexts(layer: int, row: np.ndarray, key: pa.Array) -> pa.Array:
    """``tokens.context`` over arrays."""
    if not CONTEXTS[layer]:
        return pa.array([""]).take(pa.array(np.zeros(len(row), np.int64)))
    index = np.arange(len(row), dtype=np.int64)
    t = index - np.searchsorted(row, row) if len(row) else index
    back = [pc.fill_null(key.take(pa.array(index - k, mask=t < k)), "^") for k in CONTEXTS[layer]]
    return back[0] if len(back) == 1 else pc.binary_join_element_wise(*back, SEPARATOR)


def counted(table: DataFrame, layer: int = 1, sixteenths: int = 1, needed=None) -> DataFrame:
    """``ctx, tok, n`` of the members' shown chunks, as ``target.count_rows`` has them, written once; with ``needed``, from ``dictionary``, of those contexts only."""
    digits = "0123456789abcdef"[:sixteenths]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _parts(batches):
            row, key, pos = _placed(part)
            if not len(row):
                continue
            chunk = (pos - 1) // target.CHUNK
            fresh = np.flatnonzero(np.concatenate(([True], (np.diff(row) != 0) | (np.diff(chunk) != 0))))
            ids = part.column("sample_id").to_pylist()
            on = np.fromiter((hashlib.md5(f"{ids[r]}/{c}".encode()).hexdigest()[0] in digits for r, c in zip(row[fresh], chunk[fresh], strict=True)), bool, len(fresh))
            shown = pa.array(np.flatnonzero(np.repeat(on, np.diff(np.append(fresh, len(row))))))
            ctx, tok = _contexts(layer, row, key).take(shown), key.take(shown)
            if needed is not None:
                asked = pa.array(needed.value.find(ctx) >= 0)
                ctx, tok = ctx.filter(asked), tok.filter(asked)
            yield pa.RecordBatch.from_arrays([ctx, tok], ["ctx", "tok"])

    with batch_rows(table.sparkSession, SAMPLES_AT_ONCE):
        rows = table.where("is_member").select("sample_id", "key", "step").mapInArrow(run, "ctx string, tok string")
        return materialise(rows.groupBy("ctx", "tok").agg(F.count(F.lit(1)).alias("n")), "counts")


def vocabulary(table: DataFrame) -> int:
    """The members' distinct tokens at full exposure, plus one slot."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _parts(batches):
            yield pa.RecordBatch.from_arrays([part.column("key").flatten().unique()], ["key"])

    with batch_rows(table.sparkSession, SAMPLES_AT_ONCE):
        return table.where("is_member").select("key").mapInArrow(run, "key string").distinct().count() + 1


#: Pairs whose sums are worked out at a time.
PAIRS_AT_ONCE = 500_000


class Model:
    """One layer of the count target as arrays: strings, codes of the seen pairs in order with their counts, and the sums of each context."""

    def __init__(self, strings: Index, code: np.ndarray, n: np.ndarray, v: int, alpha: float):
        order = np.argsort(code)
        self.strings, self.code, self.n, self.v, self.alpha = strings, code[order], n[order], v, alpha
        del order
        size = max(1, len(strings))
        first = np.flatnonzero(np.concatenate(([True], self.code[1:] // size != self.code[:-1] // size))) if len(code) else np.zeros(0, np.int64)
        #: The row of ``sums`` of each string as a context, -1 where it is none.
        self.at, self.sums = np.full(len(strings), -1, np.int32), np.zeros((len(first), 7))
        self.at[self.code[first] // size] = np.arange(len(first))
        last, low = np.append(first[1:], len(code)), 0
        while low < len(first):  # whole contexts, so many that the temporary arrays stay small
            high = max(low + 1, int(np.searchsorted(last, first[low] + PAIRS_AT_ONCE, side="right")))
            many, begin = self.n[first[low] : last[high - 1]].astype(np.float64), first[low:high] - first[low]
            mass, d = many + alpha, np.log(many + alpha) - np.log(alpha)
            for k, x in enumerate((lambda: many, lambda: np.ones(len(many)), lambda: d, lambda: d * d, lambda: mass * d, lambda: mass * d * d, lambda: mass * np.log(mass))):  # noqa: B023
                self.sums[low:high, k] = np.add.reduceat(x(), begin)
            low = high

    def _found(self, row: np.ndarray, key: pa.Array, layer: int) -> tuple[np.ndarray, np.ndarray]:
        """Places of the tokens and of their contexts; a context of one token is a token that was found before."""
        tok, back = self.strings.find(key), CONTEXTS[layer]
        if len(back) > 1:
            return tok, self.strings.find(_contexts(layer, row, key))
        alone = self.strings.distinct(pa.array(["^" if back else ""]))[0]
        if not back or not len(row):
            return tok, np.full(len(row), alone)
        index = np.arange(len(row), dtype=np.int64)
        return tok, np.where(index - np.searchsorted(row, row) < back[0], alone, tok[index - back[0]])

    def stats(self, row: np.ndarray, key: pa.Array, layer: int) -> dict[str, np.ndarray]:
        """``target.forward`` over arrays: the same closed forms."""
        tok, ctx = self._found(row, key, layer)
        n, sums = np.zeros(len(row)), np.zeros((7, len(row)))
        if len(self.code):
            seen = np.where(ctx >= 0, self.at[ctx], -1)
            both = np.flatnonzero((tok >= 0) & (seen >= 0))
            code = ctx[both] * len(self.strings) + tok[both]
            at = np.minimum(_search(self.code, code), len(self.code) - 1)
            n[both] = np.where(self.code[at] == code, self.n[at], 0)
            sums = np.where(seen >= 0, self.sums[seen].T, 0.0)
        n_c, d_c, s1, s2, e1, e2, plogp = sums
        a, v = self.alpha, float(self.v)
        delta, whole = np.log(n + a) - np.log(a), n_c + a * v
        logp = np.log(n + a) - np.log(whole)
        variance = np.maximum(0.0, s2 / v - (s1 / v) ** 2)
        mean_m = e1 / whole
        variance_m = np.maximum(0.0, e2 / whole - mean_m * mean_m)
        ratio = lambda up, low: np.where(low > 1e-12, up / np.sqrt(np.where(low > 1e-12, low, 1.0)), 0.0)
        z, z_model = ratio(delta - s1 / v, variance), ratio(delta - mean_m, variance_m)
        entropy = -((plogp - (n_c + a * d_c) * np.log(whole)) / whole) - (v - d_c) * (a / whole) * np.log(a / whole)
        act = (delta, np.log(n_c + 1), logp, z, entropy, (n > 0).astype(np.float64), (n_c > 0).astype(np.float64), np.log(d_c + 1))
        return {"logp": logp, "z": z, "z_model": z_model, "entropy": entropy, "act": act}


def trained(table: DataFrame, layer: int = 1, sixteenths: int = 1, alpha: float = target.ALPHA):
    """The target of one layer for the workers; none if it has more than ``PAIRS`` pairs. Strings and codes are written, and each worker makes the same arrays of them."""
    counts = counted(table, layer, sixteenths)
    size = counts.limit(PAIRS + 1).count()
    if size > PAIRS:
        return None
    strings = materialise(counts.select(F.explode(F.array("ctx", "tok")).alias("s")).distinct(), "strings")
    held = _sent(_string_index, strings)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            code = held.value.find(b.column("ctx")) * len(held.value) + held.value.find(b.column("tok"))
            yield pa.RecordBatch.from_arrays([pa.array(code), b.column("n").cast(pa.int32())], ["code", "n"])

    coded = materialise(counts.mapInArrow(run, "code long, n int"), "codes")
    return _sent(partial(_coded_model, size=size, v=vocabulary(table), alpha=alpha), strings, coded)


#: What ``scores.per_sample`` has besides the sample's own columns.
SCORED = ("n_tokens", "loss", "loss_sum", "unweighted_z", "weighted_z", "weighted_z_model", "weighted_z_max", "weighted_loss", "mean_weight", "distinct_ratio", "lowest_k", "surprise", "perplexity")


def _lowest(logp: np.ndarray, k: float) -> float:
    m = max(1, int(len(logp) * k // 100))
    return float(np.partition(logp, m - 1)[:m].sum() / m)


def _surprise(logp: np.ndarray, entropy: np.ndarray, entropy_q: float = 0.5, logp_q: float = 0.5) -> float:
    e, p = np.round(entropy, 9), np.round(logp, 9)
    cut = lambda x, q: np.partition(x, int(q * (len(x) - 1)))[int(q * (len(x) - 1))]
    chosen = logp[(e <= cut(e, entropy_q)) & (p <= cut(p, logp_q))]
    return float(chosen.mean() if len(chosen) else logp.mean())


def per_sample(table: DataFrame, model, layer: int = 1, k: float = 20.0) -> DataFrame:
    """``scores.per_sample`` of the forward pass, one row a sample, written once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _parts(batches):
            row, key, _, w = _flat(part)
            if not len(row):
                continue
            s = model.value.stats(row, key, layer)
            first = np.flatnonzero(np.diff(row, prepend=-1))
            size = np.diff(np.append(first, len(row)))
            total = lambda x: np.add.reduceat(x, first)  # noqa: E731, B023
            z, z_m, logp, n, w_sum = 1 / (1 + np.exp(-s["z"])), 1 / (1 + np.exp(-s["z_model"])), s["logp"], size.astype(np.float64), total(w)
            codes = _numbers(key.dictionary_encode().indices)
            distinct = np.bincount(np.unique(row * (codes.max() + 1) + codes) // (codes.max() + 1), minlength=part.num_rows)[row[first]]
            ends = list(zip(first, first + size, strict=True))
            loss = total(logp) / n
            made = {
                "n_tokens": size, "loss": loss, "loss_sum": total(logp), "unweighted_z": total(z) / n, "weighted_z": total(w * z) / w_sum, "weighted_z_model": total(w * z_m) / w_sum,
                "weighted_z_max": total(w * z) / np.maximum.reduceat(w, first) / n, "weighted_loss": total(w * logp) / w_sum, "mean_weight": w_sum / n, "distinct_ratio": distinct / n,
                "lowest_k": np.array([_lowest(logp[i:j], k) for i, j in ends]), "surprise": np.array([_surprise(logp[i:j], s["entropy"][i:j]) for i, j in ends]), "perplexity": -np.exp(-loss)}
            of = pa.array(row[first])
            yield pa.RecordBatch.from_arrays([*(part.column(c).take(of) for c in scores.BY), *(pa.array(made[c]) for c in SCORED)], [*scores.BY, *SCORED])

    out = T.StructType([*(table.schema[c] for c in scores.BY), *(T.StructField(c, T.LongType() if c == "n_tokens" else T.DoubleType()) for c in SCORED)])
    with batch_rows(table.sparkSession, SAMPLES_AT_ONCE):
        return materialise(table.mapInArrow(run, out), "scored")


def weighted(table: DataFrame, model, names: dict[str, str], layer: int = 1) -> DataFrame:
    """``BY, method, score``: the weighted Z-score under each of several columns of weights (method: column), from one pass, written once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _parts(batches):
            row, key = _listed(part.column("key"))
            if not len(row):
                continue
            z = 1 / (1 + np.exp(-model.value.stats(row, key, layer)["z"]))
            first = np.flatnonzero(np.diff(row, prepend=-1))
            of = pa.array(row[first])
            for method, name in names.items():
                w = part.column(name).flatten().to_numpy(zero_copy_only=False)
                score = np.add.reduceat(w * z, first) / np.add.reduceat(w, first)
                yield pa.RecordBatch.from_arrays([*(part.column(c).take(of) for c in scores.BY), pa.array([method] * len(first), pa.string()), pa.array(score)], [*scores.BY, "method", "score"])

    out = T.StructType([*(table.schema[c] for c in scores.BY), T.StructField("method", T.StringType()), T.StructField("score", T.DoubleType())])
    with batch_rows(table.sparkSession, SAMPLES_AT_ONCE):
        return materialise(table.mapInArrow(run, out), "scored")


def pooled(table: DataFrame, model, layer: int, how: str = "both") -> DataFrame:
    """``activation.pool`` of one layer's forward pass, written once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _parts(batches):
            row, key, _, w = _flat(part)
            if not len(row):
                continue
            first = np.flatnonzero(np.diff(row, prepend=-1))
            total, n = (lambda x: np.add.reduceat(x, first)), np.diff(np.append(first, len(row)))  # noqa: B023
            act = model.value.stats(row, key, layer)["act"]
            plain, weighted = [total(x) / n for x in act], [total(x * w) / total(w) for x in act]
            each = np.stack({"mean": plain, "weighted": weighted, "both": plain + weighted}[how], axis=1)
            of = pa.array(row[first])
            features = pa.ListArray.from_arrays(pa.array(np.arange(0, each.size + 1, each.shape[1], dtype=np.int32)), pa.array(each.ravel()))
            yield pa.RecordBatch.from_arrays([*(part.column(c).take(of) for c in activation.BY), pa.array(np.full(len(first), layer, np.int32)), features], [*activation.BY, "layer", "features"])

    out = T.StructType([*(table.schema[c] for c in activation.BY), T.StructField("layer", T.IntegerType()), T.StructField("features", T.ArrayType(T.DoubleType()))])
    with batch_rows(table.sparkSession, SAMPLES_AT_ONCE):
        return materialise(table.mapInArrow(run, out), "pooled")


def stats(table: DataFrame, model, layer: int, names: tuple[str, ...] = ("logp", "z", "z_model", "entropy")) -> DataFrame:
    """``sample_id, pos`` and the named statistics of every token, written once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _parts(batches):
            row, key, pos = _placed(part)
            if len(row):
                s = model.value.stats(row, key, layer)
                yield pa.RecordBatch.from_arrays([part.column("sample_id").take(pa.array(row)), pa.array(pos.astype(np.int32)), *(pa.array(s[c]) for c in names)], ["sample_id", "pos", *names])

    out = T.StructType([table.schema["sample_id"], T.StructField("pos", T.IntegerType()), *(T.StructField(c, T.DoubleType()) for c in names)])
    with batch_rows(table.sparkSession, SAMPLES_AT_ONCE):
        return materialise(table.select("sample_id", "key", "step").mapInArrow(run, out), "stats", "zstd")


def contexts(counts: DataFrame, layer: int, alpha: float = target.ALPHA) -> DataFrame:
    """``target.moments`` of one layer's counts."""
    return target.moments(counts.select(F.lit(layer).alias("layer"), "ctx", "tok", "n"), alpha)


def unfolded(table: DataFrame) -> DataFrame:
    """The rows as a token table, for targets that are too large to broadcast: ``KEEP, pos, t, key, prev1..prev4, weight``."""
    keep = [c for c in KEEP if c in table.columns]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _parts(batches):
            row, key, pos, w = _flat(part)
            index = np.arange(len(row), dtype=np.int64)
            t = index - np.searchsorted(row, row) + 1 if len(row) else index
            back = [pc.fill_null(key.take(pa.array(index - b, mask=t <= b)), "^") for b in range(1, 5)]
            columns = [*(part.column(c).take(pa.array(row)) for c in keep), *(pa.array(x.astype(np.int32)) for x in (pos, t)), key, *back, pa.array(w)]
            yield pa.RecordBatch.from_arrays(columns, [*keep, "pos", "t", "key", "prev1", "prev2", "prev3", "prev4", "weight"])

    kinds = {"pos": T.IntegerType(), "t": T.IntegerType(), **dict.fromkeys(("key", "prev1", "prev2", "prev3", "prev4"), T.StringType()), "weight": T.DoubleType()}
    return table.mapInArrow(run, T.StructType([*(table.schema[c] for c in keep), *(T.StructField(c, k) for c, k in kinds.items())]))
