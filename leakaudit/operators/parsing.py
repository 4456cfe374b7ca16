"""Mask spans by real lexers, beside the native patterns."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from leakaudit.functions import lexing
from leakaudit.functions.surface import parser_spans

SCHEMA = "sample_id long, kind string, start int, stop int"


def languages() -> tuple[str, ...]:
    """The grammars that a real lexer is at hand for: Python by the standard library, the others where Pygments is installed."""
    try:
        import pygments  # noqa: F401
    except ImportError:
        return ("python",)
    return ("python", "java", "go", "ruby", "rust", "html")


def spans(samples: DataFrame, names: tuple[str, ...] | None = None) -> DataFrame:
    """``sample_id, kind, start, stop``: comments and literals of the samples of these grammars, in code points.

    Texts are lexed one by one in Arrow batches where they are; a text that doesn't
    parse gives what was read before the fault. Null texts have none.
    """
    names = names or languages()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [
                (k, *s) for k, g, text in zip(*(c.to_pylist() for c in batch.columns), strict=True) for s in parser_spans(text or "", g) if s[0] in ("comment", "literal")]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.string(), pa.int32(), pa.int32()), strict=True)], ["sample_id", "kind", "start", "stop"])

    some = samples.select(F.col("sample_id").cast("long"), lexing.grammar_of(None).alias("g"), "text").where(F.col("g").isin(*names))
    return some.mapInArrow(run, SCHEMA)
