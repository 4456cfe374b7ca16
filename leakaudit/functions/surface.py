"""The SQL surface: scalar functions that Catalyst inlines, and a table function for source code."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from leakaudit.functions.weights import DEFAULT


def register(spark: SparkSession) -> None:
    """Temporary functions ``sigmoid(z)``, ``token_class(tok)``, ``class_weight(kind)`` and the table function ``lex_spans(text, lang)``."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sigmoid(z DOUBLE) RETURNS DOUBLE RETURN 1 / (1 + exp(-z))")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION token_class(tok STRING) RETURNS STRING RETURN CASE "
        "WHEN NOT rlike(tok, '^[\\\\p{L}_][\\\\p{L}\\\\p{N}_]{2,}$') THEN 'boilerplate' WHEN tok IN ('TODO', 'FIXME') THEN 'tag' WHEN length(tok) >= 10 THEN 'long' ELSE 'standard' END")
    cases = " ".join(f"WHEN '{k}' THEN {w}D" for k, w in DEFAULT.items())
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION class_weight(kind STRING) RETURNS DOUBLE RETURN CASE kind {cases} END")
    spark.udtf.register("lex_spans", LexSpans)


@udtf(returnType="kind string, start int, stop int")
class LexSpans:
    """Spans of a source text by a real lexer: Python by the standard library, other languages by Pygments where it is installed."""

    def eval(self, text: str, lang: str) -> Iterator[tuple[str, int, int]]:
        if text:
            yield from parser_spans(text, lang)


def parser_spans(text: str, lang: str) -> list[tuple[str, int, int]]:
    """``(kind, start, stop)`` of comments, literals and keywords, in code points. A text that doesn't parse gives what was read before the fault."""
    if lang == "python":
        return list(_python(text))
    from pygments import lexers, token

    lexer, out, at = lexers.get_lexer_by_name(lang, stripnl=False, ensurenl=True), [], 0
    for kind, value in lexer.get_tokens(text):
        name = "comment" if kind in token.Comment else "literal" if kind in token.String else "keyword" if kind in token.Keyword else None
        # the lexers want a last line feed, which is no part of the text
        stop = min(at + len(value), len(text))
        if name and out and out[-1][0] == name and out[-1][2] == at and name != "keyword":
            out[-1] = (name, out[-1][1], stop)
        elif name and stop > at:
            out.append((name, at, stop))
        at += len(value)
    return out


def _python(text: str) -> Iterator[tuple[str, int, int]]:
    import io
    import keyword
    import tokenize

    starts = [0]
    for line in text.splitlines(keepends=True):
        starts.append(starts[-1] + len(line))
    at = lambda place: starts[place[0] - 1] + place[1]
    open_at: list[int] = []
    try:
        for t in tokenize.generate_tokens(io.StringIO(text, newline="").readline):
            name = tokenize.tok_name[t.type]
            if name == "FSTRING_START":
                open_at.append(at(t.start))
            elif name == "FSTRING_END":
                yield "literal", open_at.pop(), at(t.end)
            elif open_at:
                continue
            elif t.type == tokenize.COMMENT:
                yield "comment", at(t.start), at(t.end)
            elif t.type == tokenize.STRING:
                yield "literal", at(t.start), at(t.end)
            elif t.type == tokenize.NAME and keyword.iskeyword(t.string):
                yield "keyword", at(t.start), at(t.end)
    except (tokenize.TokenError, IndentationError, SyntaxError):
        return
