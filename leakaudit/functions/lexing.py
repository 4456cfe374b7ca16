"""Total lexers: patterns whose matches, put together, are the text; offsets follow from running lengths."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

#: White space, identifiers, numbers, single characters. Understood alike by Java and RE2.
PIECE = r"(?s)\s+|[\p{L}_][\p{L}\p{N}_]*|\p{N}+|."
IDENTIFIER = r"^[\p{L}_][\p{L}\p{N}_]{2,}$"
BLANK = r"^\s+$"
TAGS = ("TODO", "FIXME")

_DOUBLE, _SINGLE = r'"(?:\\.|[^"\\\n])*"', r"'(?:\\.|[^'\\\n])*'"
#: Per grammar: comments and string literals; the first alternative that fits wins, so a comment mark in a string is no comment.
MARKS: dict[str, str] = {
    "prose": r'"[^"\n]*"',
    "html": r'<!--(?s:.*?)-->|"[^"\n]*"',
    "python": r'#[^\n]*|[rbfuRBFU]{0,2}(?:"""(?s:.*?)"""|' + r"'''(?s:.*?)'''|" + _DOUBLE + "|" + _SINGLE + ")",
    "java": r'//[^\n]*|/\*(?s:.*?)\*/|"""(?s:.*?)"""|' + _DOUBLE + "|" + _SINGLE,
    "go": r"//[^\n]*|/\*(?s:.*?)\*/|`[^`]*`|" + _DOUBLE + "|" + _SINGLE,
    "ruby": r"(?m:^=begin(?s:.*?)^=end)|#[^\n]*|" + _DOUBLE + "|" + _SINGLE,
    "rust": r'//[^\n]*|/\*(?s:.*?)\*/|r#"(?s:.*?)"#|' + _DOUBLE + r"""|'(?:\\.|[^'\\\n])'""",
}
#: The characters that a mark of the grammar can begin with; what stands between marks is a run of others, or one of them.
_BEGINS = {"prose": '"', "html": '"<', "python": "#\"'rbfuRBFU", "java": "/\"'", "go": "/\"'`", "ruby": "#\"'=", "rust": "/\"'r"}
#: Total patterns: a text's marks, and the rest in stretches.
GRAMMARS: dict[str, str] = {g: f"{marks}|[^{_BEGINS[g]}]+|[{_BEGINS[g]}]" for g, marks in MARKS.items()}
#: What marks a comment, and what a literal, at the start of a stretch.
COMMENT_STARTS = {
    "prose": None, "html": r"^<!--", "python": r"^#", "java": r"^(?://|/\*)", "go": r"^(?://|/\*)", "ruby": r"^(?:#|=begin)", "rust": r"^(?://|/\*)",
}
LITERAL_STARTS = {
    "prose": r'^"[^"\n]*"$', "html": r'^"[^"\n]*"$', "python": r"""^[rbfuRBFU]{0,2}["'](?s:.*)["']$""", "java": r"""^["'](?s:.*)["']$""",
    "go": r"""^["'`](?s:.*)["'`]$""", "ruby": r"""^["'](?s:.*)["']$""", "rust": r"""^(?:["']|r#")(?s:.+)["'#]$""",
}
#: Keywords are boilerplate (fixed values, public language knowledge).
KEYWORDS: dict[str, tuple[str, ...]] = {
    "prose": (),
    "html": tuple("html head body title meta link script style div span nav footer header main section article class href src img alt lang charset var let const function return".split()),
    "python": tuple("False None True and as assert async await break class continue def del elif else except finally for from global if import in is lambda nonlocal not or pass raise return try while with yield self".split()),
    "java": tuple("abstract boolean break byte case catch char class const continue default do double else enum extends final finally float for if implements import instanceof int interface long native new package private protected public return short static super switch synchronized this throw throws try void volatile while".split()),
    "go": tuple("break case chan const continue default defer else fallthrough for func go goto if import interface map package range return select struct switch type var nil".split()),
    "ruby": tuple("alias and begin break case class def defined do else elsif end ensure false for if in module next nil not or redo rescue retry return self super then true undef unless until when while yield".split()),
    "rust": tuple("as async await break const continue crate dyn else enum extern false fn for if impl in let loop match mod move mut pub ref return self static struct super trait true type unsafe use where while".split()),
}
#: Generic format rules: trailing blanks, blanks before a comma or full stop, tabs, runs of blanks, a comma without a
#: blank after it, and runs of three equal marks; and a total pattern of them.
LINT_MARKS = r" +\n| +[,.]|\t+| {2,}|,[\p{L}]|#{3,}|%{3,}|\*{3,}|\${3,}|&{3,}|={3,}"
LINT = LINT_MARKS + r"|[^ \t,#%*$&=]+|(?s:.)"
LINT_HIT = f"^(?:{LINT_MARKS})$"
#: Pieces that take the white space behind them along: half as many. Their own end is where the blanks begin.
TOKEN = r"(?s)(?:[\p{L}_][\p{L}\p{N}_]*|\p{N}+|\S)\s*|\s+"
BLANKS = " \t\n\x0b\f\r"
#: Stands round each mark while a text is cut; where the text has it, another control character is read.
CUT, OTHER = "\x1f", "\x1e"
#: The slices whose grammar isn't their name.
SLICE_GRAMMAR = {"en": "prose", "fr": "prose", "de": "prose", "es": "prose", "user": "prose", "assistant": "prose", "system": "prose"}


def stretches(text: Column, pattern: str) -> Column:
    """All matches in order; they join to ``text``."""
    return F.regexp_extract_all(text, F.lit(pattern), F.lit(0))


def cut(text: Column, marks: str) -> Column:
    """The text in stretches again, the marks at every second place: as many as there are marks, not as there are words.

    A mark begins only with characters that no run between marks holds, so the
    leftmost search finds what the total pattern finds.
    """
    return F.split(F.regexp_replace(F.translate(text, CUT, OTHER), f"(?:{marks})", f"{CUT}$0{CUT}"), CUT)


def is_identifier(tok: Column) -> Column:
    return tok.rlike(IDENTIFIER)


def grammar_of(grammar: str | None) -> Column:
    """The grammar's name: the given one, or each row's own by its ``slice`` (a slice of no known name is prose)."""
    if grammar:
        return F.lit(grammar)
    named = {**{g: g for g in GRAMMARS}, **SLICE_GRAMMAR}
    return F.coalesce(F.try_element_at(F.create_map(*[F.lit(x) for pair in named.items() for x in pair]), F.col("slice")), F.lit("prose"))


def by_grammar(grammar: str | None, value: Callable[[str], Column | None], otherwise: Column) -> Column:
    """``value`` of the grammar, or of each row's own; only the branch that a row takes is worked out."""
    if grammar:
        found = value(grammar)
        return otherwise if found is None else found
    out = None
    for name in GRAMMARS:
        found = value(name)
        if found is not None:
            on = grammar_of(None) == name
            out = F.when(on, found) if out is None else out.when(on, found)
    return otherwise if out is None else out.otherwise(otherwise)
