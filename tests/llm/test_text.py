import hashlib
import random
import re
import textwrap

import numpy as np
import pytest
from pyspark.sql import functions as F

from leakaudit.llm import bpe, licences, pii, substring
from leakaudit.llm.fm import Index, matching_statistics
from leakaudit.llm.queries import tokenizer_path
from tests.llm.common import edge, edge_texts, empty


def test_bpe_equals_the_tokenizer_and_decodes(spark):
    tokenizers = pytest.importorskip("tokenizers")
    real = tokenizers.Tokenizer.from_file(tokenizer_path())
    v = bpe.Vocabulary(tokenizer_path())
    odd = ["a<|endoftext|>b !!<|endoftext|>  <|endoftext|>", "x  y\n\n z\t\t", "don't WE'LL I'm 12½ ²x", "\U0001f600\U0001f44d\U0001f3fd é́", "a\x85b \x1c\x1d x", "日本語 テ", "\x1f", "a\x1fb \x1e!\x1e%\x1f# <|endoftext|>\x1f", "é" * 3000 + " é日" * 2000, "#" * 5000 + " " * 5000, "<|endoftext", "﻿hi​᠎ x　y"]
    texts = [*edge_texts(), *((100 + k, t) for k, t in enumerate(odd))]
    df = spark.createDataFrame(texts, "doc_id long, text string")
    want = sorted(repr((k, real.encode(t or "", add_special_tokens=False).ids)) for k, t in texts)
    encoded = bpe.encode(df, v)
    assert sorted(repr((r.doc_id, r.ids)) for r in encoded.collect()) == want
    text = lambda t: real.decode(real.encode(t or "", add_special_tokens=False).ids, skip_special_tokens=False)
    assert sorted(repr((r.doc_id, r.text)) for r in bpe.decode(encoded, v).collect()) == sorted(repr((k, text(t))) for k, t in texts)
    rows = bpe.digests(edge(spark), v).collect()
    ids = lambda t: np.array(real.encode(t or "", add_special_tokens=False).ids, "<u4")
    assert sorted(repr(tuple(r)) for r in rows) == sorted(repr((k, len(ids(t)), hashlib.sha256(ids(t).tobytes()).hexdigest(), hashlib.sha256(text(t).encode()).hexdigest())) for k, t in edge_texts())
    assert bpe.digests(empty(spark), v).count() == 0
    some = spark.createDataFrame([(1, [0, 50_000_000, -7, 1]), (2, None), (None, []), (3, [0] * 5000)], "doc_id long, ids array<int>")
    piece = v.pieces()
    assert {r.doc_id: r.text for r in bpe.decode(some, v).collect()} == {1: (piece[0] + piece[1]).decode(), 2: "", None: "", 3: piece[0].decode() * 5000}
    plan = bpe.digests(edge(spark), v)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "LeftOuter" in plan


def test_pieces_cross_in_small_batches(spark, monkeypatch):
    held, write = [], bpe.materialise
    monkeypatch.setattr(bpe, "materialise", lambda df, tag: held.append(int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch"))) or write(df, tag))
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    long = "ab cd " * (bpe.PIECE * bpe.PIECES_AT_ONCE // 5)
    rows = bpe.digests(spark.createDataFrame([(1, long), (2, "x"), (3, None)], "doc_id long, text string"), bpe.Vocabulary(tokenizer_path())).collect()
    assert held == [bpe.PIECES_AT_ONCE] and spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == before
    assert {r.doc_id: r.decoded_sha256 for r in rows} == {k: hashlib.sha256(x.encode()).hexdigest() for k, x in ((1, long), (2, "x"), (3, ""))}


def test_blocks_of_many_ids_are_decoded_slice_by_slice(spark):
    tokenizers = pytest.importorskip("tokenizers")
    real = tokenizers.Tokenizer.from_file(tokenizer_path())
    v, rng = bpe.Vocabulary(tokenizer_path()), random.Random(8)
    texts = [(k, " ".join(rng.choice(("alpha", "Beta", "g7", "naïve", "zz9;", "\n")) for _ in range(n))) for k, n in enumerate([90_000, 3, 0, 60_000, 120_000, 1, 80_000])]
    rows = {r.doc_id: r for r in bpe.digests(spark.createDataFrame(texts, "doc_id long, text string").coalesce(1), v).collect()}
    assert sum(r.n_tokens for r in rows.values()) > 2 * bpe.IDS
    for k, t in texts:
        ids = real.encode(t, add_special_tokens=False).ids
        assert (rows[k].n_tokens, rows[k].ids_sha256) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest())
        assert rows[k].decoded_sha256 == hashlib.sha256(t.encode()).hexdigest()


def test_packed_numbers_come_back():
    rng = np.random.default_rng(1)
    for _ in range(20):
        v = np.concatenate([rng.integers(0, b, 40) for b in (128, 20_000, 200_000, 5_000_000, 2**32)])
        rng.shuffle(v)
        raw = b"zz" + bpe._pack(v) + bpe._pack(v[:3])
        got, at = bpe._unpack(raw, 2)
        assert (got == v).all() and (bpe._unpack(raw, at)[0] == v[:3]).all()


def brute_strike(docs, window):
    first = {}
    split = [(k, (t or "").encode().split()) for k, t in docs]
    key = lambda k: (k is not None, k or 0)
    for k, w in split:
        for i in range(len(w) - window + 1):
            s = tuple(w[i : i + window])
            first[s] = min(first.get(s, key(k)), key(k))
    out = []
    for k, w in split:
        gone = set()
        for i in range(len(w) - window + 1):
            if first[tuple(w[i : i + window])] < key(k):
                gone.update(range(i, i + window))
        kept = b" ".join(x for i, x in enumerate(w) if i not in gone)
        out.append((k, len(w), len(gone), hashlib.sha256(kept).hexdigest()))
    return sorted(map(repr, out))


def test_repeated_passages_equal_brute_force(spark):
    rng = random.Random(6)
    words = [f"w{k}" for k in range(60)]
    passages = [[rng.choice(words) for _ in range(rng.randint(12, 40))] for _ in range(6)]
    docs = []
    for k in range(60):
        parts = [rng.choice(words) for _ in range(rng.randint(0, 30))]
        for _ in range(rng.randint(0, 3)):
            p = rng.choice(passages)
            a = rng.randrange(len(p) // 2)
            parts += p[a:] + [rng.choice(words) for _ in range(rng.randint(0, 9))]
        docs.append((k, " ".join(parts)))
    docs += [(60, "z " * 300), (61, "z " * 40), (62, docs[3][1]), (62, docs[3][1]), (None, docs[5][1]), (63, docs[5][1])]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    for shard_words in (300_000, 120):  # 120: hot anchors are dealt into chunks of an index each
        got = substring.strike(df, window=10, shard_words=shard_words).collect()
        assert sorted(repr(tuple(r)) for r in got) == brute_strike(docs, 10)


def test_windows_beyond_the_usual_depth(spark):
    rng = random.Random(2)
    passage = [rng.choice("abcdef") for _ in range(170)]
    fill = lambda n: [f"x{rng.random()}" for _ in range(n)]
    docs = [(k, " ".join(fill(9) + passage[a:b] + fill(9))) for k, (a, b) in enumerate([(0, 170), (0, 170), (40, 125), (0, 70), (90, 170), (10, 89), (10, 90)])]
    docs += [(10, " ".join(passage[:79] + ["other"] + passage[80:])), (11, " ".join(fill(3) + passage[1:79] + ["other"] + passage[80:165]))]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    for window in (80, 130):
        assert sorted(repr(tuple(r)) for r in substring.strike(df, window=window).collect()) == brute_strike(docs, window)


def test_repeated_passages_on_edge_rows(spark):
    assert sorted(repr(tuple(r)) for r in substring.strike(edge(spark)).collect()) == brute_strike(edge_texts(), 50)
    assert substring.strike(empty(spark)).count() == 0
    kept = {r.doc_id: r.kept for r in substring.kept_texts(edge(spark)).collect()}
    assert kept[12] == "tail" and kept[6] == ""


def test_matching_statistics_equal_brute_force():
    rng = np.random.default_rng(0)
    for _ in range(40):
        n, s = int(rng.integers(1, 150)), int(rng.integers(1, 6))
        text = rng.integers(1, s + 1, n)
        index, most = Index(text), int(rng.integers(1, 30))
        patterns = [np.where(p > text.max(), 0, p) for p in ([rng.integers(0, s + 2, int(rng.integers(1, 40))) for _ in range(6)] + [text[: max(1, n // 2)]])]
        t = text.tolist()
        for which, start, low, high, length in matching_statistics(index, patterns, most):
            for k in range(len(which)):
                p = patterns[which[k]].tolist()[start[k] :]
                best = max((m for m in range(1, min(most, len(p)) + 1) if any(t[i : i + m] == p[:m] for i in range(n - m + 1))), default=0)
                assert length[k] == best
                if best:
                    assert set(index.suffixes[low[k] : high[k]].tolist()) == {i for i in range(n) if t[i : i + best] == p[:best]}


BASE = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def brute_pii(text):
    out = []
    for kind, pattern in BASE.items():
        for m in re.finditer(pattern, text or ""):
            digits = re.sub("[^0-9]", "", m.group())
            total = sum(int(d) if k % 2 == 0 else sum(divmod(2 * int(d), 10)) for k, d in enumerate(digits[::-1]))
            if kind == "email" or kind == "ip" and all(int(x) <= 255 for x in m.group().split(".")) or kind == "card" and 16 <= len(digits) <= 19 and total % 10 == 0 or kind == "phone" and 8 <= len(digits) <= 15:
                out.append((kind, *m.span()))
    return out


def test_base_spans_equal_the_plain_patterns():
    rng = random.Random(3)
    pieces = ["a@b.c", "x.y+z@mail-1.example.com", "@", "..", "1.2.3.4", "256.1.1.1", "1.2.3.4.5.6.7.8", "4111 1111 1111 1111", "4111-1111-1111-1112", "+1 (555) 123-4567", "+49 30 1", " ", "a", "9", "-", ".", "+", "(", "é", "١"]
    for _ in range(3000):
        text = "".join(rng.choice(pieces) for _ in range(rng.randint(1, 12)))
        got = [(k, a, b) for k, spans in pii.base_spans(text).items() for a, b in spans]
        assert got == brute_pii(text), text


def private_texts(n, seed):
    """Texts with planted personal spans and look-alikes, and the truth: secrets with and without a cue, obfuscated addresses, national numbers, ids, accounts."""
    rng, texts, truth = random.Random(seed), [], []
    hexes = lambda k: "".join(rng.choice("0123456789abcdef") for _ in range(k))
    digits = lambda k: "".join(rng.choice("0123456789") for _ in range(k))
    word = lambda: "".join(rng.choice(("ba", "do", "ki", "lu", "mer", "sto", "tan")) for _ in range(rng.randint(1, 4)))
    def account():
        body = digits(18)
        return next(f"DE{c:02d}{body}" for c in range(98) if int(body + "1314" + f"{c:02d}") % 97 == 1)
    def card(good):
        while True:
            d = "4" + digits(15)
            if pii.luhn(d) == good:
                return d
    makers = [
        ("secret", lambda: (rng.choice(['token = "', "api_key: ", "password="]), hexes(40), rng.choice(['"', " "]))), ("secret", lambda: ("", hexes(40), "")),
        ("email", lambda: ("write to ", f"{word()}.{word()} (at) {word()}ix (dot) com", "")), ("phone", lambda: ("call ", f"({rng.randint(201, 799)}) {rng.randint(201, 999)}-{digits(4)}", "")),
        ("account", lambda: ("iban ", account(), "")), ("id", lambda: ("ssn ", f"{rng.randint(101, 599)}-{rng.randint(11, 99)}-{rng.randint(1000, 9999)}", "")),
        (None, lambda: ("", "un" + "".join(word() for _ in range(9)), "")), (None, lambda: ("order ", digits(20), "")), (None, lambda: ("", card(False), "")), (None, lambda: ("version ", f"{rng.randint(300, 999)}.{digits(2)}.{digits(2)}.{digits(3)}", "")),
        (None, lambda: ("", f"DE{digits(2)}{digits(5)}XX{digits(11)}", "")), (None, lambda: ("page ", f"000-{digits(2)}-{digits(4)}", "")), (None, lambda: ("look at ", f"{word()} dot {word()}", "")),
        ("base", lambda: ("", card(True), "")), ("base", lambda: ("", f"{word()}.12@mail{digits(1)}.example.com", "")), ("base", lambda: ("", f"{rng.randint(1, 239)}.{digits(2)}.7.{digits(2)}", "")),
    ]
    for k in range(n):
        text = ""
        for _ in range(rng.randint(0, 6)):
            text += " ".join(word() for _ in range(rng.randint(1, 12))) + " "
            kind, make = rng.choice(makers)
            before, span, after = make()
            if kind not in (None, "base"):
                truth.append((k, kind, len(text) + len(before), len(text) + len(before) + len(span)))
            text += before + span + after + " "
        texts.append((k, text))
    return texts, truth


def test_weak_supervision_adds_spans_and_keeps_the_base(spark):
    texts, truth = private_texts(600, 1)
    texts += [(k + 1000, t) for k, t in edge_texts() if k is not None and k >= 0]
    found = pii.find(spark.createDataFrame(texts, "doc_id long, text string")).cache()
    got, by = {r.doc_id: r for r in found.collect()}, dict(texts)
    for k, r in got.items():
        assert [(s.kind, s.start, s.stop) for s in r.base] == brute_pii(by[k])
    rows = {r.kind: r for r in pii.measure(found, spark.createDataFrame(truth, "doc_id long, kind string, start int, stop int")).collect()}
    assert set(rows) == {"secret", "email", "phone", "id", "account"}
    assert all(r.precision >= 0.95 and r.recall >= 0.95 for r in rows.values()), rows
    assert not any(r.extra for k, r in got.items() if k >= 1000)
    assert pii.find(edge(spark)).count() == len(edge_texts()) and pii.find(empty(spark)).count() == 0


def test_labelers_disagree_on_the_given_tables_and_planted_secrets_are_found(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    patterns = pii.survey(docs)
    assert len({v for k, v, _, _ in patterns if k == "secret"}) > 5 and len({v for k, v, _, _ in patterns if k == "card"}) > 2
    planted = docs.where(F.col("text").rlike('(?i)token = "[0-9a-f]{40}"')).select("doc_id", "text").collect()
    truth = [(r.doc_id, "secret", m.start(1), m.end(1)) for r in planted for m in re.finditer('(?i)token = "([0-9a-f]{40})"', r.text)]
    rows = {r.kind: r for r in pii.measure(pii.find(docs), spark.createDataFrame(truth, "doc_id long, kind string, start int, stop int")).collect()}
    assert set(rows) == {"secret"} and rows["secret"].precision == rows["secret"].recall == 1


def test_estimation_learns_which_labeler_to_trust():
    rng, patterns = random.Random(1), {}
    for _ in range(4000):
        truth = rng.random() < 0.4
        votes = tuple((1 if truth == (rng.random() < p) else -1) for p in (0.95, 0.9, 0.5, 0.85, 0.5))
        patterns[("secret", votes, 5, False)] = patterns.get(("secret", votes, 5, False), 0) + 1
    table = np.exp(pii.estimate(patterns)["secret"])
    right = [(table[1][3 * k + 2] + table[0][3 * k]) / 2 for k in range(5)]
    assert right[0] > 0.85 and right[1] > 0.8 and right[3] > 0.75 and abs(right[2] - 0.5) < 0.12 and 0.3 < table[1][-1] < 0.5


def test_many_candidates_in_one_text_take_linear_time():
    import time

    def took(n):
        text = " ".join(f"10.0.{k % 250}.1 token = \"{k:040x}\"" for k in range(n))
        began = time.process_time()
        pii.candidates(text, *pii.matches(text))
        return time.process_time() - began

    took(500)
    assert took(8000) < 10 * took(2000)  # 16 times if it were quadratic


def test_licences_are_found_by_wording(spark):
    t = licences.TEMPLATES
    texts = [(k, f"Some prose before.\n{text}\nAnd after.") for k, text in enumerate(x for xs in t.values() for x in xs)]
    want = [n for n, xs in t.items() for _ in xs]
    near = t["MIT"][1].replace("free of charge", "without charge")
    texts += [(100, near), (101, "We need a licence to drive, and permission from nobody."), (102, None), (103, ""), (104, "word " * 20_000 + t["Apache-2.0"][0] + " word" * 20_000)]
    got = {r.doc_id: r.found for r in licences.scan(spark.createDataFrame(texts, "doc_id long, text string")).collect()}
    assert [got[k][0].licence for k in range(len(want))] == want and all(got[k][0].missing == 0 and got[k][0].gain > 0.2 for k in range(len(want)))
    assert got[100][0].licence == "MIT" and got[100][0].missing > 0
    assert not got[101] and not got[102] and not got[103] and got[104][0].licence == "Apache-2.0"
    assert licences.scan(edge(spark)).where(F.size("found") > 0).count() == 0 and licences.scan(empty(spark)).count() == 0


def test_all_licences_of_a_block_are_found(spark):
    t = licences.TEMPLATES
    short = [(n, xs[0]) for n, xs in t.items()]
    texts = [
        (1, "Copyright 2020 A. All rights reserved.\nReleased under the MIT License."), (2, t["MIT"][1] + "\n" + t["Apache-2.0"][1]), (3, "\n".join([t["MIT"][0]] * 3)),
        (4, " ".join(x for _, x in short)), (5, t["Apache-2.0"][1].replace("compliance", "keeping")), (6, "All rights reserved. " * 40),
    ]
    got = {r.doc_id: [(f.licence, f.missing) for f in r.found] for r in licences.scan(spark.createDataFrame(texts, "doc_id long, text string")).collect()}
    assert got[1] == [("Proprietary", 0), ("MIT", 0)] and got[2] == [("MIT", 0), ("Apache-2.0", 0)] and got[3] == [("MIT", 0)] * 3
    assert got[4] == [(n, 0) for n, _ in short] and got[5] == [("Apache-2.0", 1)] and len(got[6]) == 40


def test_wrapped_licences_are_found(spark, monkeypatch):
    every = [(n, x) for n, xs in licences.TEMPLATES.items() for x in xs]
    wrapped = lambda x, width, sign: "\n".join(sign + line for line in textwrap.wrap(x, width))
    texts = [(n, f"int a;\n/*\n{wrapped(x, width, sign)}\n*/\nint b;") for n, x in every for width in (72, 24) for sign in ("", "# ", " * ", "// ")]
    rows = spark.createDataFrame([(k, t) for k, (_, t) in enumerate(texts)], "doc_id long, text string")
    got = {r.doc_id: [(f.licence, f.missing) for f in r.found] for r in licences.scan(rows).collect()}
    assert [got[k] for k in range(len(texts))] == [[(n, 0)] for n, _ in texts]
    scanner = licences.Scanner()
    assert all(sum(bool(licences.CUE.search(w)) for w in x.words) > x.most for x in scanner.each)
    long = "All rights reserved. " * 500 + "\n" + "see the licence file\n" * 150 + wrapped(every[1][1], 72, "# ") + "\nsee the licence file" * 300 + " word" * 5000 + "\n" + wrapped(every[5][1], 72, "") + " word" * 200
    found = scanner.scan(long)
    assert [f["licence"] for f in found] == ["Proprietary"] * 500 + ["MIT", "GPL-3.0"] and not any(f["missing"] for f in found)
    monkeypatch.setattr(licences, "RUN", 30)
    assert scanner.scan(long) == found


def test_compression_tells_where_words_are_compared(monkeypatch):
    """Knowing the template must shrink a place, or its words aren't compared; places with words changed or put between theirs lose none."""
    rng, scanner = random.Random(5), licences.Scanner()
    prose = [f"{a}{b}{c}" for a in ("st", "ma", "lo", "ter") for b in ("ran", "vi", "ped", "un") for c in ("ge", "le", "t", "son", "")]
    for wording in scanner.each * 4:
        words = [rng.choice(prose) if i in rng.sample(range(len(wording.words)), wording.most) else w for i, w in enumerate(wording.words)]
        for _ in range(rng.choice((0, len(words) // 4 + 2))):
            words.insert(rng.randrange(1, len(words)), rng.choice(prose))
        words = rng.choices(prose, k=120) + words + rng.choices(prose, k=120)
        if list(wording.places(words, len(words))):
            text = " ".join(words)
            assert scanner.each.index(wording) in {k for k, *_ in scanner.places([m.span() for m in licences.WORDS.finditer(text)], text, len(words))}
    monkeypatch.setattr(licences.Wording, "places", lambda self, words, upto: pytest.fail("compared without a gain"))
    monkeypatch.setattr(licences, "LEAST_SAVED", 10**9)
    assert licences.Scanner().scan(licences.TEMPLATES["MIT"][1]) == []
