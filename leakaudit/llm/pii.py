"""Personal data: base patterns, and further spans by weak supervision."""

from __future__ import annotations

import bisect
import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from leakaudit.llm.common import lean, pieces

KINDS = ("email", "ip", "card", "phone")
#: The base patterns (fixed values), in forms that take linear time: a match starts where its run starts.
DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DIGIT = re.compile(r"[0-9]")


def luhn(digits: str) -> bool:
    total = sum(map(int, digits[-1::-2])) + sum(sum(divmod(2 * int(d), 10)) for d in digits[-2::-2])
    return total % 10 == 0


def emails(text: str) -> Iterator[tuple[int, int]]:
    """Leftmost matches, found from each at-sign: the local part is the run before it, back to the last match at most."""
    end, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > end and text[start - 1] in LOCAL:
            start -= 1
        if start < at and (m := DOMAIN.match(text, at + 1)):
            yield start, m.end()
            end = m.end()
        at = text.find("@", max(at + 1, end))


def matches(text: str) -> tuple[dict[str, list[tuple[int, int]]], dict[str, list[tuple[int, int]]]]:
    """Start and end (code points, end exclusive) of each kind's base matches, and of those that fail their test: these are dropped, not tried again."""
    found: dict[str, list[tuple[int, int]]] = {"email": list(emails(text)), "ip": [], "card": [], "phone": []}
    missed: dict[str, list[tuple[int, int]]] = {"ip": [], "card": [], "phone": []}
    if DIGIT.search(text):
        for m in IP.finditer(text):
            good = all(len(x.lstrip("0")) <= 3 and int(x.lstrip("0") or 0) <= 255 for x in m.group().split("."))
            (found if good else missed)["ip"].append(m.span())
        for m in CARD.finditer(text):
            digits = m.group().replace(" ", "").replace("-", "")
            if 16 <= len(digits) <= 19:
                (found if luhn(digits) else missed)["card"].append(m.span())
        if "+" in text:
            for m in PHONE.finditer(text):
                (found if 8 <= sum("0" <= c <= "9" for c in m.group()) <= 15 else missed)["phone"].append(m.span())
    return found, missed


def base_spans(text: str) -> dict[str, list[tuple[int, int]]]:
    return matches(text)[0]


# --- further spans -----------------------------------------------------------

#: What else may be personal: kind -> (cheap tests of which one must hold, pattern). Fixed values; each is wide, the labelers and the classifier decide.
CANDIDATES: dict[str, tuple[tuple[str, ...], re.Pattern]] = {
    "secret": ((), re.compile(r"(?<![\w-])[A-Za-z0-9_\-]{16,}+(?![\w-])")),
    "email": ((" at ", "(at)", "[at]"), re.compile(r"(?<![A-Za-z0-9._-])[A-Za-z0-9._-]{2,64} ?[\[(]?at[\])]? ?[A-Za-z0-9-]{2,40} ?[\[(]?dot[\])]? ?[A-Za-z]{2,10}(?![A-Za-z])")),
    "phone": (("0", "1", "2", "3", "4", "5", "6", "7", "8", "9"), re.compile(r"(?<![0-9+(-])(?:\([0-9]{3}\) ?|[0-9]{3}[-.])[0-9]{3}[-.][0-9]{4}(?![0-9-])")),
    "id": (("-",), re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")),
    "account": (("0", "1", "2", "3", "4", "5", "6", "7", "8", "9"), re.compile(r"(?<![A-Z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")),
}
EXTRA = ("secret", "id", "account", "email", "ip", "card", "phone")
LABELERS = ("pattern", "check", "gazetteer", "context", "variety")
#: Word lists of the gazetteer and context labelers (fixed values).
ENDINGS = frozenset("com org net edu gov info io biz co me de fr es it nl uk eu us ca au jp".split())
KEY_HEADS = ("ghp_", "gho_", "glpat-", "sk-", "sk_", "pk_", "rk_", "AKIA", "ASIA", "AIza", "xox", "eyJ")
VERBS = frozenset("look looking arrive arrived meet stay stayed good work works aim aimed point laugh be is was are were".split())
CALLING = frozenset("1 7 20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98".split())
SERVICE = frozenset("800 833 844 855 866 877 888 900".split())
IBAN_SIZES = {"AT": 20, "BE": 16, "CH": 21, "CZ": 24, "DE": 22, "DK": 18, "ES": 24, "FI": 18, "FR": 27, "GB": 22, "GR": 27, "HU": 28, "IE": 22, "IT": 27, "LU": 20, "NL": 18, "NO": 15, "PL": 28, "PT": 25, "RO": 24, "SE": 24}
SHOWN_IDS = frozenset(("078-05-1120", "219-09-9999", "123-45-6789"))
_AFTER = r"\W{0,3}(?:\w+\W{1,3}){0,2}\Z"
CUES = {
    "secret": re.compile(r"(?:token|secret|passw(?:or)?d|api[_ -]?key|access[_ -]?key|bearer|credential)\W{0,4}\Z", re.I),
    "email": re.compile(r"(?:e-?mail|contact|write|reach|address)" + _AFTER, re.I),
    "phone": re.compile(r"(?:phone|tel|call|fax|mobile|cell|contact)" + _AFTER, re.I),
    "id": re.compile(r"(?:ssn|social|security|number|no|id)" + _AFTER, re.I),
    "account": re.compile(r"(?:iban|account|bank|acct)" + _AFTER, re.I),
    "ip": re.compile(r"(?:ip|host|server|address|addr|ping|port|login)" + _AFTER, re.I),
    "card": re.compile(r"(?:card|visa|credit|debit|payment|pan)" + _AFTER, re.I),
}
AGAINST = re.compile(r"(?:version|page|isbn|chapter|fig|table|section|release|commit|sha1|digest|checksum|order|invoice|tracking|serial|v)\W{0,2}\Z", re.I)
QUOTES = "\"'`"


def _entropy(text: str) -> float:
    return -sum(n / len(text) * math.log2(n / len(text)) for n in Counter(text).values())


def _sign(good: bool, bad: bool = True) -> int:
    return 1 if good else -1 if bad else 0


def _votes(kind: str, text: str, start: int, end: int) -> tuple[int, ...]:
    """Each labeler's vote on a candidate, the base kinds' matches among them: 1 personal, -1 not, 0 abstains."""
    span, before = text[start:end], text[max(0, start - 40) : start]
    plain = "".join(c for c in span if "0" <= c <= "9")
    if kind == "secret":
        turns = sum(a.isdigit() != b.isdigit() for a, b in zip(span, span[1:], strict=False))
        letters = max(map(len, re.findall(r"[A-Za-z]+", span)), default=0)
        mixed = bool(plain) and (len(span) >= 32 and re.fullmatch(r"[0-9a-f]+|[0-9A-F]+", span) is not None and len(plain) < len(span) or (not span.islower() and not span.isupper() and letters > 0))
        pattern, check = _sign(mixed, span.isalpha() or len(plain) == len(span)), _sign(turns >= 4, turns <= 1)
        gazetteer = _sign(span.startswith(KEY_HEADS), letters >= 8)
        variety = _sign(len(plain) >= 3 and _entropy(span) > 3.0, not plain or _entropy(span) < 2.5)
    elif kind == "email":
        local, _, host = re.split(r"(@| ?[\[(]?at[\])]? ?)", span, maxsplit=1) if "@" in span or "at" in span else (span, "", "")
        pattern = _sign("@" in span or re.search(r"[\[(](?:at|dot)[\])]", span) is not None, False)
        check = _sign(sum(c.isalpha() for c in local) >= 2 and len(host) >= 5)
        gazetteer = _sign(re.split(r"[ .\])]", host.rstrip("])"))[-1].lower() in ENDINGS)
        variety = _sign("." in local or any(c.isdigit() for c in local), local.lower() in VERBS)
    elif kind == "account":
        code = span.replace(" ", "")
        pattern, gazetteer = _sign(IBAN_SIZES.get(code[:2]) == len(code)), _sign(code[:2] in IBAN_SIZES)
        check = _sign(int("".join(str(int(c, 36)) for c in code[4:] + code[:4])) % 97 == 1)
        variety = _sign(len(plain) >= 8)
    elif kind == "card":
        pattern, check = _sign(re.fullmatch(r"[0-9]{16}|[0-9]{4}([ -]?[0-9]{4}){3}", span) is not None, False), _sign(luhn(plain))
        gazetteer = _sign(plain[0] == "4" or "51" <= plain[:2] <= "55" or "2221" <= plain[:4] <= "2720" or plain[:4] == "6011" or plain[:2] in ("35", "62", "65"))
        variety = _sign(len(set(plain)) >= 5, len(set(plain)) <= 2)
    elif kind == "ip":
        parts = span.split(".")
        pattern, check = _sign(all(p == "0" or p[0] != "0" for p in parts)), _sign(all(len(p) <= 3 and int(p) <= 255 for p in parts))
        gazetteer = _sign(parts[0] not in ("0", "255") and not (len(parts[0]) == 3 and parts[0] >= "240"))
        variety = _sign(len(set(plain)) >= 3)
    elif kind == "phone":
        pattern = _sign(re.search(r"\([0-9]{3}\) ?[0-9]{3}-[0-9]{4}\Z", span) is not None, False)
        if span[0] == "+":
            check, gazetteer = _sign(8 <= len(plain) <= 15), _sign(any(plain[:n] in CALLING for n in (1, 2)))
        else:
            check, gazetteer = _sign(plain[0] not in "01" and plain[3] not in "01"), _sign(False, plain[:3] in SERVICE)
        variety = _sign(len(set(plain)) >= 4)
    else:
        pattern, check = 1, _sign(plain[:3] not in ("000", "666") and plain[0] != "9" and plain[3:5] != "00" and plain[5:] != "0000")
        gazetteer, variety = _sign(False, span in SHOWN_IDS), _sign(len(set(plain)) >= 4)
    prose = kind == "secret" and before[-1:] in ("", " ", "\n") and text[end : end + 1] in ("", " ", "\n", ".", ",")
    context = _sign(CUES[kind].search(before) is not None, AGAINST.search(before) is not None or prose)
    return pattern, check, gazetteer, context, variety


def _look(text: str, start: int, end: int) -> int:
    """What the classifier sees of a span besides the votes: a bin of its length, its share of digits, quotes round it."""
    digits = sum("0" <= c <= "9" for c in text[start:end])
    share = 0 if not digits else 3 if digits == end - start else 1 if 3 * digits < end - start else 2
    return 8 * min(7, int(math.log2(max(1, end - start)))) + 2 * share + (text[start - 1 : start] in QUOTES and text[end : end + 1] in QUOTES and start > 0)


class _Taken:
    """Disjoint spans in order, asked for overlaps by bisection."""

    def __init__(self, spans: list[tuple[int, int]]):
        self.starts, self.stops = [], []
        for a, b in sorted(spans):
            if self.stops and a < self.stops[-1]:
                self.stops[-1] = max(self.stops[-1], b)
            else:
                self.starts.append(a)
                self.stops.append(b)

    def meets(self, a: int, b: int) -> bool:
        k = bisect.bisect_left(self.starts, b)
        return k > 0 and self.stops[k - 1] > a

    def add(self, a: int, b: int) -> None:
        k = bisect.bisect_left(self.starts, a)
        self.starts.insert(k, a)
        self.stops.insert(k, b)


#: (kind, start, end, votes, look).
Candidate = tuple[str, int, int, tuple[int, ...], int]


def candidates(text: str, base: dict[str, list[tuple[int, int]]], missed: dict[str, list[tuple[int, int]]]) -> list[Candidate]:
    """Further candidate spans with their votes: wider patterns, and matches of the base patterns that failed their test (``missed``).

    Those that overlap a base span aren't any.
    """
    taken, found = _Taken([x for spans in base.values() for x in spans]), [(kind, a, b) for kind, spans in missed.items() for a, b in spans]
    for kind, (needs, pattern) in CANDIDATES.items():
        if not needs or any(n in text for n in needs):
            found += [(kind, *m.span()) for m in pattern.finditer(text)]
    return [(kind, a, b, _votes(kind, text, a, b), _look(text, a, b)) for kind, a, b in found if not taken.meets(a, b)]


#: How often (kind, votes, look, whether it is a base match) occurs.
Patterns = dict[tuple[str, tuple[int, ...], int, bool], int]


def estimate(patterns: Patterns, rounds: int = 30) -> dict[str, np.ndarray]:
    """Expectation-maximisation over vote patterns and their counts: per kind, the prior and each labeler's P(vote | class).

    Base matches stay in any case: they count as personal throughout and so anchor
    the labelers of their kinds, but not the prior, which is of the other candidates. Every labeler starts better than chance, and checks
    (sums and rules of validity) as hardly ever against a personal span; counts are
    smoothed, so a kind seen once keeps that start. Result: per kind an array
    (class, labeler, vote + 1), with the log prior added as one more row.
    """
    found = {}
    for kind in EXTRA:
        rows = [(votes, n, base) for (k, votes, _, base), n in patterns.items() if k == kind]
        start = np.empty((2, len(LABELERS), 3))
        start[1], start[0] = (0.05, 0.35, 0.6), (0.45, 0.45, 0.1)
        start[1, LABELERS.index("check")] = (0.001, 0.349, 0.65)
        table, prior = start.copy(), 0.5
        if rows:
            votes, n, base = np.array([r[0] for r in rows]) + 1, np.array([r[1] for r in rows], float), np.array([r[2] for r in rows], bool)
            for _ in range(rounds):
                like = np.stack([np.log(table[c][np.arange(len(LABELERS)), votes]).sum(axis=1) for c in (0, 1)]) + np.log([[1 - prior], [prior]])
                p = np.where(base, 1.0, 1 / (1 + np.exp(np.clip(like[0] - like[1], -50, 50))))
                prior = float(((n * p)[~base].sum() + 5) / (n[~base].sum() + 10))
                for c, w in ((0, n * (1 - p)), (1, n * p)):
                    counts = np.stack([np.bincount(votes[:, k], w, 3) for k in range(len(LABELERS))])
                    table[c] = (counts + 20 * start[c]) / (counts.sum(axis=1, keepdims=True) + 20)
        found[kind] = np.concatenate([np.log(table).reshape(2, -1), np.log([[1 - prior], [prior]])], axis=1)
    return found


def posterior(table: np.ndarray, votes: tuple[int, ...]) -> float:
    at = [3 * k + v + 1 for k, v in enumerate(votes)]
    gap = table[0][at].sum() + table[0][-1] - table[1][at].sum() - table[1][-1]
    return float(1 / (1 + np.exp(np.clip(gap, -50, 50))))


#: Inputs of the classifier: per kind a constant, each labeler's vote for and against, and the share of digits; the length bin and quotes for all.
PER_KIND = 1 + 2 * len(LABELERS) + 4
WIDTH = len(EXTRA) * PER_KIND + 8 + 1


def _inputs(kind: str, votes: tuple[int, ...], look: int) -> list[int]:
    """The places of the inputs that are one."""
    first = EXTRA.index(kind) * PER_KIND
    on = [first, *(first + 1 + 2 * k + (v < 0) for k, v in enumerate(votes) if v), first + 1 + 2 * len(LABELERS) + (look >> 1) % 4, WIDTH - 9 + (look >> 3)]
    return on + [WIDTH - 1] * (look & 1)


def fit_classifier(patterns: Patterns, tables: dict[str, np.ndarray], rounds: int = 500, rate: float = 0.5) -> np.ndarray:
    """A logistic span classifier fitted to the estimated posteriors of all candidates at once (equal ones weighted, each kind with the same whole weight)."""
    w = np.zeros(WIDTH)
    if not patterns:
        return w - 10
    x = np.zeros((len(patterns), WIDTH))
    for row, (k, v, look, _) in zip(x, patterns, strict=True):
        row[_inputs(k, v, look)] = 1
    y = np.array([1.0 if base else posterior(tables[k], v) for k, v, _, base in patterns])
    whole = Counter()
    for (k, *_), c in patterns.items():
        whole[k] += c
    n = np.array([c / whole[k] for (k, *_), c in patterns.items()])
    n /= n.sum()
    square = np.full(WIDTH, 1e-6)
    for _ in range(rounds):
        g = x.T @ (n * (1 / (1 + np.exp(-np.clip(x @ w, -30, 30))) - y)) + 1e-5 * w
        square += g * g
        w -= rate * g / np.sqrt(square)
    return w


def survey(docs: DataFrame, text: str = "text") -> Patterns:
    """How often each (kind, votes, look, base) occurs in all texts: as many rows as there are such patterns, whatever the input, reach the driver."""

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()
        for part in pieces(batches, "text"):
            for t in part.column("text").to_pylist():
                if t:
                    base, missed = matches(t)
                    seen.update((k, v, look, False) for k, _, _, v, look in candidates(t, base, missed))
                    seen.update((k, _votes(k, t, a, b), _look(t, a, b), True) for k, spans in base.items() for a, b in spans)
        if seen:
            kind, votes, look, base = zip(*seen, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(kind), pa.array([",".join(map(str, v)) for v in votes]), pa.array(look, pa.int32()), pa.array(base, pa.bool_()), pa.array(list(seen.values()), pa.int64())], ["kind", "votes", "look", "base", "n"])

    rows = docs.select(F.col(text).cast("string").alias("text")).mapInArrow(run, "kind string, votes string, look int, base boolean, n long")
    found = rows.groupBy("kind", "votes", "look", "base").agg(F.sum("n").alias("n")).collect()
    return {(r.kind, tuple(map(int, r.votes.split(","))), r.look, r.base): r.n for r in sorted(found)}


def chosen(found: list[Candidate], weights: np.ndarray, threshold: float) -> list[tuple[str, int, int]]:
    """The candidates that the classifier takes; of overlapping ones the likelier, then the first."""
    scored = [(float(weights[_inputs(k, v, look)].sum()), k, a, b) for k, a, b, v, look in found]
    taken, out = _Taken([]), []
    for z, k, a, b in sorted(scored, key=lambda r: (-r[0], r[2], r[1])):
        if z >= math.log(threshold / (1 - threshold)) and not taken.meets(a, b):
            taken.add(a, b)
            out.append((k, a, b))
    return sorted(out, key=lambda r: (r[1], r[2], r[0]))


def find(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", threshold: float = 0.5) -> DataFrame:
    """``doc_id, base, extra`` of every row: arrays of ``struct<kind, start, stop>``, base spans by kind and start, extra ones by start.

    Candidates of all texts are counted by how the labelers vote; from the counts
    expectation-maximisation estimates each labeler's reliability, and the span
    classifier learns the resulting probabilities. A null text is an empty one;
    repeated rows each get theirs; no rows give none.
    """
    patterns = survey(docs, text)
    weights = fit_classifier(patterns, estimate(patterns))

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        span = pa.struct([("kind", pa.string()), ("start", pa.int32()), ("stop", pa.int32())])
        for part in pieces(batches, "text"):
            base, extra = [], []
            for t in part.column("text").to_pylist():
                found, missed = matches(t or "")
                base.append([{"kind": k, "start": a, "stop": b} for k in KINDS for a, b in found[k]])
                extra.append([{"kind": k, "start": a, "stop": b} for k, a, b in chosen(candidates(t or "", found, missed), weights, threshold)])
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(base, pa.list_(span)), pa.array(extra, pa.list_(span))], ["doc_id", "base", "extra"])

    kind = "array<struct<kind:string,start:int,stop:int>>"
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    return rows.mapInArrow(run, f"doc_id long, base {kind}, extra {kind}")


def measure(found: DataFrame, truth: DataFrame) -> DataFrame:
    """``kind, n_true, n_found, n_right, precision, recall`` of the added spans of ``find`` against ``truth`` (doc_id, kind, start, stop)."""
    mine = found.select("doc_id", F.explode("extra").alias("s")).select("doc_id", "s.*").distinct().withColumn("_found", F.lit(1))
    both = mine.join(truth.select("doc_id", "kind", "start", "stop").distinct().withColumn("_true", F.lit(1)), ["doc_id", "kind", "start", "stop"], "full")
    rows = both.groupBy("kind").agg(F.count("_true").alias("n_true"), F.count("_found").alias("n_found"), F.count(F.col("_true") + F.col("_found")).alias("n_right"))
    return rows.select("*", (F.col("n_right") / F.nullif("n_found", F.lit(0))).alias("precision"), (F.col("n_right") / F.nullif("n_true", F.lit(0))).alias("recall"))


def listed(spans) -> str:
    return ",".join(f"{s['kind']}:{s['start']}:{s['stop']}" for s in spans)


def digest(spans) -> str:
    return hashlib.sha256(listed(spans).encode()).hexdigest()
