"""From samples to weighted tokens: lexing, spans, mask overlay, projection."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from leakaudit.functions import lexing
from leakaudit.functions.weights import Scheme
from leakaudit.runtime import lookup, materialise

KEEP = ("sample_id", "slice", "is_member", "role")
#: Contexts, by layer: how many tokens back each part looks. Layer 1, the previous token, is the usual one.
CONTEXTS: tuple[tuple[int, ...], ...] = ((), (1,), (2, 1), (3, 2, 1), (2,), (3,), (4,), (3, 1), (3, 2), (4, 3, 2, 1))
SMALL, LARGE = (0, 1, 2), tuple(range(len(CONTEXTS)))
SEPARATOR = "\x01"


def _ordered(stretches: Column, stream: str) -> Column:
    return F.transform(stretches, lambda t, i: F.struct(F.lit(stream).alias("stream"), (i + 1).alias("pos"), t.alias("tok")))


def placed(samples: DataFrame, grammar: str | None = "prose", streams: tuple[str, ...] = ("piece",), extra: tuple[str, ...] = ()) -> DataFrame:
    """``KEEP, stream, pos, tok, start, stop`` of the streams ``piece`` (or ``token``: pieces without white space), ``syntax`` and ``lint``.

    Without a ``grammar`` each row's slice tells it. Of ``syntax`` and ``lint`` every second stretch is a mark.

    Texts are dealt by sample once; explosion and the windows over a sample's
    stretches then need no other shuffle. Offsets count code points, stop exclusive.
    """
    none = F.array().cast("array<struct<stream:string,pos:int,tok:string>>")
    made = {
        "piece": lambda: _ordered(lexing.stretches(F.col("text"), lexing.PIECE), "piece"), "token": lambda: _ordered(lexing.stretches(F.col("text"), lexing.TOKEN), "piece"),
        "lint": lambda: _ordered(lexing.cut(F.col("text"), lexing.LINT_MARKS), "lint"),
        "syntax": lambda: lexing.by_grammar(grammar, lambda g: _ordered(lexing.cut(F.col("text"), lexing.MARKS[g]), "syntax"), none),
    }
    arrays = F.concat(*[made[s]() for s in streams])
    keep = [c for c in (*KEEP, *extra) if c in samples.columns]
    rows = samples.repartition("sample_id").select(*keep, F.explode(arrays).alias("s")).select(*keep, "s.stream", "s.pos", "s.tok")
    upto = Window.partitionBy("sample_id", "stream").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumn("stop", F.sum(F.length("tok")).over(upto).cast("int"))
    if "token" not in streams:
        return rows.withColumn("start", (F.col("stop") - F.length("tok")).cast("int"))
    # a stretch of a token and the blanks behind it is two pieces; blanks alone, at the start of a text, are one and go
    bare = F.when(F.col("stream") == "piece", F.rtrim("tok", F.lit(lexing.BLANKS))).otherwise(F.col("tok"))
    both = ((F.col("_bare") != "") & (F.length("_bare") < F.length("tok"))).cast("int")
    rows = rows.withColumn("_bare", bare).withColumn("start", (F.col("stop") - F.length("tok")).cast("int"))
    rows = rows.withColumn("_pieces", F.sum(1 + both).over(upto)).withColumn("pos", F.when(F.col("stream") == "piece", F.col("_pieces") - both).otherwise(F.col("pos")).cast("int"))
    rows = rows.withColumn("tok", F.col("_bare")).withColumn("stop", (F.col("start") + F.length("_bare")).cast("int")).drop("_bare", "_pieces")
    return rows.where("stream <> 'piece' or tok <> ''")


def _begun(grammar: str | None, tok: Column) -> Column:
    """What a mark of the stream ``syntax`` is, by how it begins: comment, literal, or null."""
    begins = lambda starts: lexing.by_grammar(grammar, lambda g: tok.rlike(starts[g]) if starts[g] else None, F.lit(False))
    return F.when(begins(lexing.COMMENT_STARTS), "comment").when(begins(lexing.LITERAL_STARTS), "literal")


def span_kind(grammar: str | None) -> Column:
    """The overlay kind of a stretch: comment, literal, lint, or null."""
    mark = F.col("pos") % 2 == 0
    return F.when((F.col("stream") == "lint") & mark, "lint").when((F.col("stream") == "syntax") & mark, _begun(grammar, F.col("tok")))


def spans(samples: DataFrame, grammar: str | None = "prose") -> DataFrame:
    """``sample_id, slice, kind, start, stop`` of comments, literals, format errors and tags."""
    rows = placed(samples, grammar, ("token", "syntax", "lint"))
    kind = F.when((F.col("stream") == "piece") & F.col("tok").isin(*lexing.TAGS), "tag").otherwise(span_kind(grammar))
    return rows.withColumn("kind", kind).where("kind is not null").select("sample_id", "slice", "kind", "start", "stop")


def lexicon(samples: DataFrame, min_df: int = 3, slice: str | None = "en") -> DataFrame:
    """``word, df``: lower-cased identifiers of at least ``min_df`` samples of ``slice`` (none: of all). It stands for an English dictionary."""
    pieces = lexing.stretches(F.col("text"), lexing.PIECE)
    words = F.array_distinct(F.transform(F.filter(pieces, lexing.is_identifier), lambda t: F.lower(t)))
    return (samples.where(F.col("slice") == slice) if slice else samples).select(F.explode(words).alias("word")).groupBy("word").agg(F.count(F.lit(1)).alias("df")).where(F.col("df") >= min_df)


#: The parts of a compound identifier: camel-case humps, stretches between underscores and digits.
PART = r"\p{Lu}+(?!\p{Ll})|\p{Lu}?[\p{Ll}\p{Lo}\p{Lm}\p{Lt}]+"


def compound_words(samples: DataFrame, words: DataFrame, min_part: int = 3) -> DataFrame:
    """``word``: the dictionary, and the samples' compound identifiers (camelCase, snake_case) all of whose parts are in it.

    Parts of fewer than ``min_part`` letters don't count. Slippage then means a
    foreign part, not a name that no dictionary has as a whole.
    """
    parts = F.filter(F.transform(F.regexp_extract_all("tok", F.lit(PART), F.lit(0)), lambda p: F.lower(p)), lambda p: F.length(p) >= min_part)
    toks = samples.select(F.explode(F.array_distinct(F.filter(lexing.stretches(F.col("text"), lexing.PIECE), lexing.is_identifier))).alias("tok")).distinct()
    each = toks.select(F.lower("tok").alias("word"), F.explode(F.array_distinct(parts)).alias("part"))
    known = materialise(words.select(F.col("word").alias("part"), F.lit(1).alias("_known")), "parts")
    found = lookup(each, known, ["part"], "left").groupBy("word").agg(F.count(F.lit(1)).alias("n"), F.count("_known").alias("k")).where("n = k").select("word")
    return found.union(words.select("word")).distinct()


#: Kinds that come from spans, and the code of each between the engine and the workers.
OVERLAYS = ("comment", "literal", "lint")
_SPANS = "array<struct<n:int,kind:string>>"
#: Tokens that a worker works on at a time, one sample at least.
TOKENS_AT_ONCE = 100_000
#: Offsets of a sample stay below; sample k's are raised by k times as much, so that one search serves all samples.
_ROOM = 1 << 32


def _slices(batches: Iterator[pa.RecordBatch], most: int = TOKENS_AT_ONCE) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sizes, at, held = pc.fill_null(pc.list_value_length(batch.column("toks")), 0).to_numpy(zero_copy_only=False), 0, 0
        for i, n in enumerate(sizes):
            if i > at and held + n > most:
                yield batch.slice(at, i - at)
                at, held = i, 0
            held += int(n)
        yield batch.slice(at)


def _listed(column: pa.Array) -> tuple[np.ndarray, pa.Array]:
    """The row of each element of a list column, and the elements."""
    sizes = pc.fill_null(pc.list_value_length(column), 0).to_numpy(zero_copy_only=False)
    return np.repeat(np.arange(len(column), dtype=np.int64), sizes), column.flatten()


def _numbers(column: pa.Array) -> np.ndarray:
    return column.to_numpy(zero_copy_only=False).astype(np.int64)


def _upto(values: np.ndarray, row: np.ndarray) -> np.ndarray:
    """Running sums that begin anew in each row."""
    whole = np.cumsum(values)
    return whole - (whole - values)[np.searchsorted(row, row)] if len(row) else whole


def laid(part: pa.RecordBatch) -> tuple:
    """Of rows of samples with their stretches: row, stretch, place, number and text of each token, and which kinds of span overlap it."""
    row, stretch = _listed(part.column("toks"))
    bare = pc.utf8_rtrim(stretch, characters=lexing.BLANKS)
    size, own = _numbers(pc.utf8_length(stretch)), _numbers(pc.utf8_length(bare))
    # a stretch of a token and the blanks behind it is two pieces; blanks alone, at the start of a text, are one and go
    both = (own > 0) & (own < size)
    start, pos = _upto(size, row) - size, _upto(1 + both, row) - both
    kept = np.flatnonzero(own > 0)
    row, start, pos, own, tok = row[kept], start[kept], pos[kept], own[kept], bare.take(pa.array(kept))
    stop, t = start + own, _upto(np.ones(len(row), np.int64), row)
    at: dict[str, list[tuple[np.ndarray, np.ndarray, np.ndarray]]] = {kind: [] for kind in OVERLAYS}
    for stream in ("syntax", "lint", "more"):
        of, marks = _listed(part.column(stream))
        kinds = marks.field("kind")
        if stream == "more":
            first, last = _numbers(marks.field("start")), _numbers(marks.field("stop"))
        else:
            last = _upto(_numbers(marks.field("n")), of)
            first = last - _numbers(marks.field("n"))
        for kind in OVERLAYS:
            on = np.flatnonzero(pc.fill_null(pc.equal(kinds, kind), False).to_numpy(zero_copy_only=False))
            at[kind].append((of[on], first[on], last[on]))
    covered = []
    for kind in OVERLAYS:
        of, first, last = (np.concatenate(x) for x in zip(*at[kind], strict=True))
        first, last = of * _ROOM + first, of * _ROOM + last
        order = np.argsort(first, kind="stable")
        # of the spans that start before a token's end, the largest end; ends of earlier samples lie below
        first, end = first[order], np.maximum.accumulate(last[order])
        before = np.searchsorted(first, row * _ROOM + stop - 1, side="right")
        covered.append((before > 0) & (np.concatenate(([-1], end))[before] > row * _ROOM + start))
    return row, kept, pos, start, stop, t, tok, covered


def _overlaid(keep: list[str]):
    """Rows of samples with their stretches -> rows of tokens: place, number, tokens before, and which kinds of span overlap them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _slices(batches):
            row, _, pos, start, stop, t, tok, covered = laid(part)
            index = np.arange(len(row), dtype=np.int64)
            back = [pc.fill_null(tok.take(pa.array(index - k, mask=t <= k)), "^") for k in range(1, 5)]
            whole = pa.array(row)
            columns = [part.column(c).take(whole) for c in keep]
            columns += [pa.array(x.astype(np.int32)) for x in (pos, start, stop, t)] + [tok, *back] + [pa.array(x) for x in covered]
            yield pa.RecordBatch.from_arrays(columns, [*keep, *_PLACES])

    return run


_PLACES = ("pos", "start", "stop", "t", "tok", "prev1", "prev2", "prev3", "prev4", "_comment", "_literal", "_lint")


def overlaid(samples: DataFrame, grammar: str | None = "prose", extra: DataFrame | None = None, native: dict[str, tuple[str, ...]] | None = None) -> DataFrame:
    """``KEEP, pos, start, stop, t, tok, key, prev1..prev4, _comment, _literal, _lint``: the scored tokens and what overlaps them.

    A sample's stretches stay together in its row, where offsets are running
    lengths; a token overlaps a span iff, of the spans that start before its end,
    the largest end lies beyond its start. No shuffle, sort or window: a task holds
    a batch of texts and one slice of their tokens.
    """
    rows = stretched(samples, grammar, extra, native)
    keep = [c for c in KEEP if c in samples.columns]
    kinds = {**dict.fromkeys(_PLACES[:4], T.IntegerType()), **dict.fromkeys(_PLACES[4:9], T.StringType()), **dict.fromkeys(_PLACES[9:], T.BooleanType())}
    out = T.StructType([*[T.StructField(c, rows.schema[c].dataType) for c in keep], *[T.StructField(c, k) for c, k in kinds.items()]])
    lower = {f"prev{back}": F.lower(f"prev{back}") for back in range(1, 5)}
    return rows.mapInArrow(_overlaid(keep), out).withColumns({"key": F.lower("tok"), **lower})


def stretched(samples: DataFrame, grammar: str | None = "prose", extra: DataFrame | None = None, native: dict[str, tuple[str, ...]] | None = None) -> DataFrame:
    """``KEEP, toks, syntax, lint, more``: a sample's stretches, marks and further spans in its row, as ``laid`` takes them."""
    native = native or {}
    none = F.array().cast(_SPANS)
    sized = lambda marks, kind: F.transform(lexing.cut(F.col("text"), marks), lambda x, i: F.struct(F.length(x).alias("n"), F.when(i % 2 == 1, kind(x)).alias("kind")))
    made = {
        "syntax": lexing.by_grammar(grammar, lambda g: sized(lexing.MARKS[g], lambda x: _begun(g, x)), none),
        "lint": sized(lexing.LINT_MARKS, lambda x: F.lit("lint")),
    }
    for stream, names in native.items():
        made[stream] = F.when(lexing.grammar_of(grammar).isin(*names), made[stream]).otherwise(none)
    keep = [c for c in KEEP if c in samples.columns]
    if extra is None:
        rows, more = samples, F.array().cast("array<struct<kind:string,start:int,stop:int>>")
    else:
        each = extra.where("start is not null and stop is not null").select("sample_id", F.struct(F.col("kind").cast("string").alias("kind"), F.col("start").cast("int").alias("start"), F.col("stop").cast("int").alias("stop")).alias("s"))
        rows, more = samples.join(each.groupBy("sample_id").agg(F.collect_list("s").alias("_more")), "sample_id", "left"), F.col("_more")
    return rows.where("text is not null").select(*keep, lexing.stretches(F.col("text"), lexing.TOKEN).alias("toks"), *[made[s].cast(_SPANS).alias(s) for s in made], more.alias("more"))


def identifier(grammar: str | None, tok: Column, key: Column) -> Column:
    """Whether a token is an identifier and no keyword of its grammar."""
    keyword = lexing.by_grammar(grammar, lambda g: key.isin(*lexing.KEYWORDS[g]) if lexing.KEYWORDS[g] else None, F.lit(False))
    return tok.rlike(lexing.IDENTIFIER) & ~keyword


def flagged(samples: DataFrame, grammar: str | None = "prose", words: DataFrame | None = None, max_tokens: int | None = None, extra: DataFrame | None = None, native: dict[str, tuple[str, ...]] | None = None) -> DataFrame:
    """``overlaid`` with ``_ident`` and ``_known``: all that a weight depends on besides the scheme."""
    rows = overlaid(samples, grammar, extra, native)
    if max_tokens:
        rows = rows.where(F.col("t") <= max_tokens)
    rows = rows.withColumn("_ident", identifier(grammar, F.col("tok"), F.col("key")))
    return rows.withColumn("_known", F.lit(True)) if words is None else known(rows, words)


def known(rows: DataFrame, words: DataFrame) -> DataFrame:
    """``rows`` with ``_known``, null where ``key`` isn't in the dictionary."""
    return lookup(rows, words.select(F.col("word").alias("key"), F.lit(True).alias("_known")), ["key"], "left")


def weighed(scheme: Scheme) -> tuple[Column, Column]:
    """``(kind, weight)`` of a row of ``flagged``: the largest of the kinds that cover it; a tag assigns its own."""
    base = F.when(~F.col("_ident"), "boilerplate").when((F.length("tok") >= scheme.long_min) & F.lit("long" in scheme.weights), "long").otherwise("standard")
    weigh = lambda kind: F.lit(float(scheme[kind]))
    own = F.when(base == "boilerplate", weigh("boilerplate")).when(base == "long", weigh("long")).otherwise(weigh("standard"))
    slip = F.col("_ident") & F.col("_known").isNull()
    named = [("comment", F.col("_comment")), ("slippage", slip), ("literal", F.col("_literal")), ("lint", F.col("_lint"))]
    weight, kind = own, base
    for name, on in reversed(named):
        if name in scheme.weights:
            kind = F.when(on & (weigh(name) >= weight), name).otherwise(kind)
            weight = F.when(on, F.greatest(weight, weigh(name))).otherwise(weight)
    if "tag" in scheme.weights:
        tag = F.col("tok").isin(*lexing.TAGS)
        kind, weight = F.when(tag, "tag").otherwise(kind), F.when(tag, weigh("tag")).otherwise(weight)
    return kind, weight


def tokens(samples: DataFrame, grammar: str | None = "prose", words: DataFrame | None = None, scheme: Scheme | None = None, max_tokens: int | None = None, extra: DataFrame | None = None, native: dict[str, tuple[str, ...]] | None = None) -> DataFrame:
    """Scored tokens with kind and weight: ``KEEP, pos, tok, start, stop, t, prev1..prev4, kind, weight``.

    ``t`` numbers the scored tokens (no white space) from 1. ``words`` is the
    dictionary, best a written table, for it is counted; without it nothing is slippage. ``max_tokens`` cuts each sample.
    ``extra`` (sample_id, kind, start, stop) are spans from elsewhere, a parser or
    linter; ``native`` says for which grammars the streams ``syntax`` and ``lint``
    still count, all if it doesn't name the stream.
    """
    rows = flagged(samples, grammar, words, max_tokens, extra, native)
    kind, weight = weighed(scheme or Scheme.default())
    keep = [c for c in KEEP if c in rows.columns]
    return rows.select(*keep, "pos", "tok", "key", "start", "stop", "t", "prev1", "prev2", "prev3", "prev4", kind.alias("kind"), weight.alias("weight"))


def context(layer: int) -> Column:
    """The context key of a layer: the tokens it looks back to, joined by a character that no token holds."""
    parts = [F.col(f"prev{back}") for back in CONTEXTS[layer]]
    return F.concat_ws(SEPARATOR, *parts) if parts else F.lit("")
