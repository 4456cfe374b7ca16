"""Texts lexed in the worker against the engine's patterns, and how long and how large that may be."""

import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from leakaudit.functions import lexer, lexing
from leakaudit.operators import rows, tokens
from leakaudit.plans import audit
from leakaudit.sources import catalog


def _odd(n):
    rng = random.Random(3)
    some = " \n\t,.ab_ZéΣİß日²12½٣Ⅷ\"'#%=<!->\x1f\x85 \U0001f600\U0001d4b3"
    return ["", " ", "a", "é", "12ab3 9_", '"a', "<!-- x -->"] + ["".join(rng.choice(some) for _ in range(rng.randrange(40))) for _ in range(n)]


@pytest.mark.parametrize("grammar", ["prose", "html", "go"])
def test_tokens_and_overlays_are_those_of_the_engine(spark, grammar):
    texts = _odd(600)
    frame = spark.createDataFrame(list(enumerate(texts)), "sample_id long, text string").withColumn("slice", F.lit("x")).repartition(1)
    want = {(r.sample_id, r.pos): (r.tok, r.start, r.stop, r._comment, r._literal, r._lint, r.key, r._ident) for r in tokens.flagged(frame, grammar).collect()}
    piece = lexer.pieces(pa.array(texts))
    covered = lexer.spread(piece, lexer.marks(pa.array(texts), grammar, piece.faulty), tokens.OVERLAYS)
    word = rows._Words(piece, grammar)
    columns = (piece.tok.to_pylist(), piece.start.tolist(), piece.stop.tolist(), *(x.tolist() for x in covered), word.key.take(pa.array(word.of)).to_pylist(), word.ident[word.of].tolist())
    assert dict(zip(zip(piece.row.tolist(), piece.pos.tolist(), strict=True), zip(*columns, strict=True), strict=True)) == want and len(want) > 1000


def test_slices_and_nulls_change_nothing():
    texts = [None, *_odd(300), "x" * 500]
    batch = pa.RecordBatch.from_arrays([pa.array(texts)], ["text"])
    found = [t for part in lexer.slices([batch.slice(0, 150), batch.slice(150)], 64) for t in lexer.pieces(part.column("text")).tok.to_pylist()]
    assert found == lexer.pieces(batch.column("text")).tok.to_pylist()


def test_the_engine_lexes_no_text(spark, sf, monkeypatch):
    """A pattern in the engine took most of the time of every query that scores by rows."""
    monkeypatch.setattr(lexing, "stretches", lambda *a: pytest.fail("lexed by the engine"))
    monkeypatch.setattr(lexing, "cut", lambda *a: pytest.fail("lexed by the engine"))
    assert audit.sample_scores(spark, sf).count() > 0


def test_the_dictionary_is_the_engine_s(spark, sf):
    some = catalog.samples(spark, sf, "documents")
    for slice_ in ("en", None):
        want, got = ({r.word: r.df for r in df.collect()} for df in (tokens.lexicon(some, 2, slice_), rows.lexicon(some, 2, slice_)))
        assert got == want and len(want) > 10


def test_sums_are_worked_out_in_bounded_pieces(monkeypatch):
    strings = rows.Index(pa.array([f"w{i}" for i in range(50)]))
    code = np.unique(np.random.default_rng(1).integers(0, 2500, 900))
    n = (code % 7 + 1).astype(np.int32)
    whole = rows.Model(strings, code, n, 51, 0.01)
    monkeypatch.setattr(rows, "PAIRS_AT_ONCE", 20)
    some = rows.Model(strings, code, n, 51, 0.01)
    assert np.allclose(whole.sums, some.sums, rtol=1e-12, atol=0) and whole.sums[:, 0].sum() == n.sum() and (whole.at >= 0).sum() == len(whole.sums)
    assert np.array_equal(np.bincount(code // 50, n)[code[np.flatnonzero(np.diff(code // 50, prepend=-1))] // 50], some.sums[:, 0])
