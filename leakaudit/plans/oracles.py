"""DuckDB SQL that computes the same results in another way: common table expressions, put together by name."""

from __future__ import annotations

from leakaudit.functions import lexing
from leakaudit.functions.weights import DEFAULT
from leakaudit.operators.around import LICENCES
from leakaudit.operators.tokens import CONTEXTS

ALPHA = 0.01


def q(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


def stretched(pattern: str, source: str = "smp") -> str:
    """Stretches with offsets: a running sum of lengths."""
    return (
        f"SELECT sample_id, pos, tok, CAST(stop - length(tok) AS INTEGER) AS start, CAST(stop AS INTEGER) AS stop FROM (SELECT *, sum(length(tok)) OVER (PARTITION BY sample_id ORDER BY pos) AS stop "
        f"FROM (SELECT sample_id, unnest(ps) AS tok, generate_subscripts(ps, 1) AS pos FROM (SELECT sample_id, regexp_extract_all(text, {q(pattern)}) AS ps FROM {source})))"
    )


def base(source: str = "documents", unique: bool = True, salt: str = "") -> str:
    raw = {
        "documents": "SELECT doc_id AS sample_id, lang AS slice, text FROM documents",
        "pages": "SELECT page_id AS sample_id, 'html' AS slice, html AS text FROM pages",
        "conversations": "SELECT conv_id * 1000 + turn AS sample_id, role AS slice, text FROM conversations",
    }[source]
    keep = "WHERE sample_id = low" if unique else ""
    return (
        f"smp AS (SELECT sample_id, slice, text, content_key, substr(content_key, 1, 1) < '8' AS is_member, CASE WHEN substr(content_key, 2, 1) < '8' THEN 'shadow' ELSE 'holdout' END AS role "
        f"FROM (SELECT *, md5({q(salt)} || text) AS content_key, min(sample_id) OVER (PARTITION BY text) AS low FROM ({raw}) WHERE length(text) > 0) {keep})"
    )


PCS = f"pcs AS ({stretched(lexing.PIECE)})"
TKS = (
    "tks AS (SELECT sample_id, pos, tok, lower(tok) AS key, start, stop, row_number() OVER w AS t, coalesce(lag(lower(tok), 1) OVER w, '^') AS prev1, coalesce(lag(lower(tok), 2) OVER w, '^') AS prev2, "
    "coalesce(lag(lower(tok), 3) OVER w, '^') AS prev3, coalesce(lag(lower(tok), 4) OVER w, '^') AS prev4 FROM pcs WHERE NOT regexp_matches(tok, '^\\s+$') WINDOW w AS (PARTITION BY sample_id ORDER BY pos))"
)
IDENT = f"regexp_matches(tok, {q(lexing.IDENTIFIER)})"


def lex(min_df: int = 3) -> str:
    """The dictionary, always from the documents."""
    inner = base("documents").replace("smp AS (", "", 1)[:-1]
    return (
        f"lexi AS (SELECT word, count(*) AS df FROM (SELECT DISTINCT sample_id, lower(tok) AS word FROM (SELECT sample_id, unnest(regexp_extract_all(text, {q(lexing.PIECE)})) AS tok FROM ({inner}) WHERE slice = 'en') WHERE {IDENT}) GROUP BY word HAVING count(*) >= {min_df})"
    )


def spn(grammar: str) -> str:
    comment, literal = lexing.COMMENT_STARTS[grammar], lexing.LITERAL_STARTS[grammar]
    c = f"WHEN regexp_matches(tok, {q(comment)}) THEN 'comment'" if comment else ""
    return (
        f"syn AS ({stretched(lexing.GRAMMARS[grammar])}), lnt AS ({stretched(lexing.LINT)}), "
        f"spn AS (SELECT * FROM (SELECT sample_id, CASE {c} WHEN regexp_matches(tok, {q(literal)}) THEN 'literal' END AS kind, start, stop FROM syn "
        f"UNION ALL SELECT sample_id, CASE WHEN regexp_matches(tok, {q(lexing.LINT_HIT)}) THEN 'lint' END, start, stop FROM lnt) WHERE kind IS NOT NULL)"
    )


def wts(grammar: str, weights: dict[str, float] | None = None, long_min: int = 10) -> str:
    """Kinds and weights by joining each token to the spans that overlap it."""
    w = DEFAULT if weights is None else weights
    keywords = ", ".join(map(q, lexing.KEYWORDS[grammar])) or "NULL"
    ident = f"({IDENT} AND key NOT IN ({keywords}))" if lexing.KEYWORDS[grammar] else IDENT
    long = f"length(tok) >= {long_min}" if "long" in w else "false"
    tags = "tok IN ('TODO', 'FIXME')" if "tag" in w else "false"
    cand = [f"CASE WHEN NOT {ident} THEN {w.get('boilerplate', 0)} WHEN {long} THEN {w.get('long', 0)} ELSE {w.get('standard', 0)} END"]
    cand += [f"CASE WHEN {cond} THEN {w[k]} END" for k, cond in (("comment", "cm"), ("literal", "li"), ("lint", "ln"), ("slippage", f"({ident} AND word IS NULL)")) if k in w]
    return (
        "flg AS (SELECT t.sample_id, t.pos, bool_or(s.kind = 'comment') AS cm, bool_or(s.kind = 'literal') AS li, bool_or(s.kind = 'lint') AS ln FROM tks t JOIN spn s ON s.sample_id = t.sample_id AND s.start < t.stop AND s.stop > t.start GROUP BY 1, 2), "
        f"wts AS (SELECT t.*, slice, is_member, role, {ident} AS ident, word IS NOT NULL AS known, coalesce(cm, false) AS cm, coalesce(li, false) AS li, coalesce(ln, false) AS ln, CAST(CASE WHEN {tags} THEN {w.get('tag', 0)} ELSE greatest({', '.join(cand)}) END AS DOUBLE) AS weight "
        "FROM tks t JOIN smp USING (sample_id) LEFT JOIN flg f ON f.sample_id = t.sample_id AND f.pos = t.pos LEFT JOIN lexi ON lexi.word = t.key)"
    )


KIND = (
    "CASE WHEN tok IN ('TODO', 'FIXME') THEN 'tag' WHEN cm THEN 'comment' WHEN ident AND NOT known THEN 'slippage' WHEN li THEN 'literal' WHEN ln THEN 'lint' "
    "WHEN NOT ident THEN 'boilerplate' WHEN length(tok) >= 10 THEN 'long' ELSE 'standard' END"
)


def ctx(layer: int) -> str:
    return " || chr(1) || ".join(f"prev{b}" for b in CONTEXTS[layer]) or "''"


def model(layers: tuple[int, ...] = (1,), exposure: int = 1, tokens: str = "wts") -> str:
    """Counts, contexts, vocabulary and the statistics of every token under each layer."""
    shown = "" if exposure >= 16 else f"AND substr(md5(CAST(sample_id AS VARCHAR) || '/' || CAST((pos - 1) // 16 AS VARCHAR)), 1, 1) < '{'0123456789abcdef'[exposure]}'"
    counted = " UNION ALL ".join(f"SELECT {k} AS layer, {ctx(k)} AS ctx, key AS tok, count(*) AS n FROM {tokens} WHERE is_member {shown} GROUP BY ALL" for k in layers)
    asked = " UNION ALL ".join(f"SELECT {k} AS layer, {ctx(k)} AS ctx, sample_id, slice, is_member, role, pos, t, key, weight FROM {tokens}" for k in layers)
    d = f"(ln(n + {ALPHA}) - ln({ALPHA}))"
    return (
        f"cnt AS ({counted}), cxs AS (SELECT layer, ctx, sum(n) AS n_c, count(*) AS d_c, sum({d}) AS s1, sum({d} * {d}) AS s2, sum((n + {ALPHA}) * {d}) AS e1, sum((n + {ALPHA}) * {d} * {d}) AS e2 FROM cnt GROUP BY 1, 2), "
        f"voc AS (SELECT count(DISTINCT key) + 1 AS v FROM {tokens} WHERE is_member), asked AS ({asked}), "
        f"raw AS (SELECT a.*, coalesce(c.n, 0) AS n, coalesce(x.n_c, 0) AS n_c, coalesce(x.d_c, 0) AS d_c, coalesce(s1, 0) / v AS m, greatest(0, coalesce(s2, 0) / v - (coalesce(s1, 0) / v) ** 2) AS var, "
        f"coalesce(e1, 0) / (coalesce(x.n_c, 0) + {ALPHA} * v) AS mm, coalesce(e2, 0) / (coalesce(x.n_c, 0) + {ALPHA} * v) AS sm, v, ln(coalesce(c.n, 0) + {ALPHA}) - ln({ALPHA}) AS delta "
        f"FROM asked a LEFT JOIN cnt c ON c.layer = a.layer AND c.ctx = a.ctx AND c.tok = a.key LEFT JOIN cxs x ON x.layer = a.layer AND x.ctx = a.ctx CROSS JOIN voc), "
        f"sts AS (SELECT *, ln(n + {ALPHA}) - ln(n_c + {ALPHA} * v) AS logp, CASE WHEN var > 1e-12 THEN (delta - m) / sqrt(var) ELSE 0 END AS z, CASE WHEN sm - mm * mm > 1e-12 THEN (delta - mm) / sqrt(sm - mm * mm) ELSE 0 END AS z_model FROM raw)"
    )


#: Entropy from the counts themselves, term by term, where the engine uses sums of each context.
ENTROPY = (
    f"ent AS (SELECT c.layer, c.ctx, -sum(((n + {ALPHA}) / (n_c + {ALPHA} * v)) * ln((n + {ALPHA}) / (n_c + {ALPHA} * v))) - (any_value(v) - count(*)) * ({ALPHA} / any_value(n_c + {ALPHA} * v)) * ln({ALPHA} / any_value(n_c + {ALPHA} * v)) AS h "
    "FROM cnt c JOIN cxs USING (layer, ctx) CROSS JOIN voc GROUP BY 1, 2), "
    "ste AS (SELECT s.*, coalesce(h, ln(v)) AS entropy FROM sts s LEFT JOIN ent USING (layer, ctx))"
)
SIG = "1 / (1 + exp(-z))"


def lowest(k: int = 20) -> str:
    return (
        f"low AS (SELECT sample_id, slice, is_member, role, avg(logp) AS score FROM (SELECT *, row_number() OVER (PARTITION BY sample_id ORDER BY logp, pos) AS r, count(*) OVER (PARTITION BY sample_id) AS c FROM sts) "
        f"WHERE r <= greatest(1, floor(c * {k} / 100)) GROUP BY ALL)"
    )


SURPRISE = (
    "qs AS (SELECT *, count(*) OVER (PARTITION BY sample_id) AS c, row_number() OVER (PARTITION BY sample_id ORDER BY entropy) AS re, row_number() OVER (PARTITION BY sample_id ORDER BY logp) AS rp FROM ste), "
    "cut AS (SELECT sample_id, max(CASE WHEN re - 1 = floor(0.5 * (c - 1)) THEN entropy END) AS ce, max(CASE WHEN rp - 1 = floor(0.5 * (c - 1)) THEN logp END) AS cp FROM qs GROUP BY 1), "
    "sur AS (SELECT sample_id, slice, is_member, role, coalesce(avg(logp) FILTER (round(entropy, 9) <= round(ce, 9) AND round(logp, 9) <= round(cp, 9)), avg(logp)) AS score FROM qs JOIN cut USING (sample_id) GROUP BY ALL)"
)


def simple(expr: str, name: str) -> str:
    return f"SELECT sample_id, slice, is_member, role, '{name}' AS method, {expr} AS score FROM sts GROUP BY ALL"


METHOD_SQL = {
    "loss": "avg(logp)", "unweighted_z": f"avg({SIG})", "weighted_z": f"sum(weight * {SIG}) / sum(weight)", "weighted_loss": "sum(weight * logp) / sum(weight)",
}


def area(rows: str, by: str) -> str:
    """AUC by average ranks of all rows, where the engine sums over distinct scores."""
    return (
        f"SELECT {by}, n_pos, n_neg, round((rs - n_pos * (n_pos + 1) / 2) / nullif(n_pos * n_neg, 0), 6) AS auc FROM (SELECT {by}, count(*) FILTER (is_member) AS n_pos, count(*) FILTER (NOT is_member) AS n_neg, sum(CASE WHEN is_member THEN rk END) AS rs FROM "
        f"(SELECT *, rank() OVER (PARTITION BY {by} ORDER BY sc) + (count(*) OVER (PARTITION BY {by}, sc) - 1) / 2.0 AS rk FROM (SELECT *, round(score, 9) AS sc FROM {rows} WHERE score IS NOT NULL)) GROUP BY {by})"
    )


def document_chain(source: str = "documents", layers: tuple[int, ...] = (1,), exposure: int = 1, weights: dict[str, float] | None = None, min_df: int = 3, unique: bool = True) -> str:
    grammar = "html" if source == "pages" else "prose"
    return ", ".join([base(source, unique), PCS, TKS, lex(min_df), spn(grammar), wts(grammar, weights), model(layers, exposure)])


def scored(source: str = "documents", **options) -> str:
    """``scr``: all methods of the holdout in long form."""
    parts = " UNION ALL ".join([simple(e, n) for n, e in METHOD_SQL.items()] + ["SELECT sample_id, slice, is_member, role, 'lowest_k' AS method, score FROM low", "SELECT sample_id, slice, is_member, role, 'surprise' AS method, score FROM sur"])
    return f"{document_chain(source, **options)}, {ENTROPY}, {lowest()}, {SURPRISE}, scr AS (SELECT * FROM ({parts}) WHERE role = 'holdout')"


def licences() -> str:
    """``l``: a row for each class of licence line that a sample holds, or ``none``."""
    each = ", ".join(f"CASE WHEN contains(text, {q(line)}) THEN {q(name)} END" for name, line in LICENCES.items())
    return f"h AS (SELECT sample_id, unnest([{each}]) AS licence FROM smp), l AS (SELECT * FROM h WHERE licence IS NOT NULL UNION ALL SELECT sample_id, 'none' FROM h GROUP BY sample_id HAVING count(licence) = 0)"
