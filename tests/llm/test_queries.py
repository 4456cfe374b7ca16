"""Every registered query's own columns over sf0.001, against plain Python over the same rows."""

import hashlib
import json
import re
import struct
import zlib

import numpy as np
import pytest
import xxhash

from leakaudit.llm import licences, multiset, queries
from tests.llm.test_dedup import brute_fingerprint, brute_groups
from tests.llm.test_mix_and_hash import brute_targets
from tests.llm.test_text import brute_pii, brute_strike


@pytest.fixture(scope="module")
def docs(spark, sf):
    return {r.doc_id: r for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}


def by_id(spark, sf, name):
    rows = queries.QUERIES[name](spark, sf).collect()
    found = {r.doc_id: r for r in rows}
    assert len(found) == len(rows)
    return found


def sha(text):
    return hashlib.sha256(text if isinstance(text, bytes) else text.encode()).hexdigest()


def test_op1(spark, sf, docs):
    got = by_id(spark, sf, "op1_mix")
    assert set(got) == set(docs)
    sizes, taken = {}, {}
    for k, r in got.items():
        assert r.size == len(re.findall(r"[^\x20\x09-\x0D]+", docs[k].text or "")) and 0 <= r.taken <= 2 * r.size
        sizes[docs[k].source] = sizes.get(docs[k].source, 0) + r.size
        taken[docs[k].source] = taken.get(docs[k].source, 0) + r.taken
    want = brute_targets(sizes)
    for k, r in got.items():
        assert r.source_size == sizes[docs[k].source] and r.target == pytest.approx(want[docs[k].source])
    assert all(abs(taken[s] - want[s]) <= 1 for s in sizes)


def test_op2(spark, sf, docs):
    got = by_id(spark, sf, "op2_simhash")
    fps = [(k, brute_fingerprint(d.text)) for k, d in docs.items()]
    groups = brute_groups(fps, 4)
    assert {k: (r.fingerprint, r.component_id) for k, r in got.items()} == {k: (f"{f:016x}", groups[f]) for k, f in fps}


def test_op3(spark, sf, docs):
    got = by_id(spark, sf, "op3_pii")
    assert set(got) == set(docs)
    order = ("email", "ip", "card", "phone", "secret", "id", "account")
    for k, r in got.items():
        base = brute_pii(docs[k].text)
        assert {x: getattr(r, f"n_{x}") for x in order[:4]} == {x: sum(s[0] == x for s in base) for x in order[:4]}
        assert r.base_sha256 == sha(",".join(f"{x}:{a}:{b}" for x, a, b in base))
        spans = [(x, int(a), int(b)) for x, a, b in (s.split(":") for s in r.spans.split(",") if s)]
        assert spans == sorted(spans, key=lambda s: (order.index(s[0]), s[1])) and set(base) <= set(spans)
        assert all(0 <= a < b <= len(docs[k].text or "") for _, a, b in spans)


def test_op4(spark, sf, docs):
    got = by_id(spark, sf, "op4_quality")
    assert set(got) == set(docs)
    for k, r in got.items():
        assert r.held_out == (zlib.crc32(str(k).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3)
    same = {}
    for k, d in docs.items():  # neither doc_id nor source nor language take part
        same.setdefault(d.text, set()).add(got[k].score)
    assert all(len(s) == 1 for s in same.values())


def test_op6(spark, sf, docs):
    got = by_id(spark, sf, "op6_toxicity")
    assert set(got) == set(docs)
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    for k, r in got.items():
        assert r.held_out == (zlib.crc32(str(k).encode()) % 5 == 0) and r.predicted == int(r.p_toxic >= 0.5 and bool((docs[k].text or "").split()))
        assert all(0 <= p <= 1 for p in (r.p_kind1, r.p_kind2, r.p_kind3, r.p_toxic))
    seen = [(labels[k], r.predicted) for k, r in got.items() if labels.get(k) is not None and not r.held_out]
    assert sum(y == p for y, p in seen) / len(seen) > 0.9


def test_op7(spark, sf, docs):
    tokenizers = pytest.importorskip("tokenizers")
    real = tokenizers.Tokenizer.from_file(queries.tokenizer_path())
    got = by_id(spark, sf, "op7_bpe")
    assert set(got) == set(docs)
    for k, r in got.items():
        ids = real.encode(docs[k].text or "", add_special_tokens=False).ids
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), sha(struct.pack(f"<{len(ids)}I", *ids)), sha(real.decode(ids, skip_special_tokens=False)))


def test_op5_and_op8(spark, sf, docs):
    got = by_id(spark, sf, "op5_exact_dedup")
    content = {k: re.sub(r"[\x20\x09-\x0D]", "", d.text or "") for k, d in docs.items()}
    groups = {}
    for k, c in content.items():
        groups.setdefault(c, []).append(k)
    for k, r in got.items():
        mine = groups[content[k]]
        keep = min(mine, key=lambda x: (-len(docs[x].text or ""), x))
        assert (r.keep_id, r.group_size, r.kept, r.text_sha256) == (keep, len(mine), k == keep, sha(content[k]))
    rows = queries.QUERIES["op8_substring"](spark, sf).select("doc_id", "n_words", "n_removed", "kept_sha256").collect()
    assert sorted(repr(tuple(r)) for r in rows) == brute_strike([(k, d.text) for k, d in docs.items()], 50)


def lanes(text):
    """The multiset hash of a text: units counted for the narrow lanes, paragraphs summed for the wide ones."""
    first = struct.pack("<i", 1)
    hashes = lambda part: (xxhash.xxh64_intdigest(part.encode(), 42), xxhash.xxh64_intdigest(part.encode(), xxhash.xxh64_intdigest(first, 42)))
    wide, narrow, n = [0] * 4, np.zeros(128, np.int64), 0
    for p in re.findall(multiset.PARAGRAPH, text):
        a, b = hashes("\n" + p)
        wide = [(w + x) % 2**32 for w, x in zip(wide, (a % 2**32, a >> 32, b % 2**32, b >> 32), strict=True)]
    for u in re.findall(multiset.UNIT, text):
        n += 1
        for k, h in enumerate(hashes(u)):
            narrow[64 * k : 64 * k + 64] += [h >> j & 1 for j in range(64)]
    return wide, narrow, n


def shown(h):
    wide, narrow, _ = h
    fields = []
    for k in range(2):
        for j in range(0, 32, 2):
            four = [narrow[64 * k + x] % 2**16 for x in (j, j + 32, j + 1, j + 33)]
            fields.append("".join(f"{x:04x}" for x in four[::-1]))
    return "".join(f"{w:08x}" for w in wide) + "".join(fields)


def like(a, b):
    if a[0] == b[0] and a[2] == b[2] and (a[1] == b[1]).all():
        return 1.0
    x, y = (2 * h[1] - h[2] for h in (a, b))
    return min(1.0, max(0.0, 2 * float(x @ y) / max(1.0, float(x @ x + y @ y))))


def test_op9(spark, sf, docs):
    got = by_id(spark, sf, "op9_fingerprint")
    ids = sorted(docs)
    hashes = {k: lanes(docs[k].text or "") for k in ids}
    exact = []
    for i, k in enumerate(ids):
        text, following = docs[k].text or "", docs[ids[(i + 1) % len(ids)]].text or ""
        half = len(text) // 2
        new = text[: len(text) - half] + following[:half]
        changed = lanes(new)
        r = got[k]
        assert (r.n_chars, r.edited_sha256, r.fingerprint, r.edited_fingerprint) == (len(text), sha(new), shown(hashes[k]), shown(changed))
        assert r.near_edited == pytest.approx(like(hashes[k], changed)) and r.near_next == pytest.approx(like(hashes[k], hashes[ids[(i + 1) % len(ids)]]))
        units = [multiset_of(re.findall(multiset.UNIT, t)) for t in (text, new)]
        exact.append((r.near_edited, 2 * product(*units) / max(1, product(units[0], units[0]) + product(units[1], units[1]))))
    assert np.mean([abs(a - b) for a, b in exact]) < 0.12  # the estimate against the exact likeness of the multisets of units
    assert np.mean([r.near_edited > r.near_next for r in got.values()]) > 0.95


def multiset_of(units):
    found = {}
    for u in units:
        found[u] = found.get(u, 0) + 1
    return found


def product(a, b):
    return sum(n * b.get(u, 0) for u, n in a.items())


def test_op10(spark, sf, docs):
    """All templates at every word of every text, without cues, blocks or shortcuts."""
    got = by_id(spark, sf, "op10_licences")
    scanner = licences.Scanner()
    for k, d in docs.items():
        words = [(m.start(), licences.PARTED.sub("-", m.group()).lower()) for m in licences.WORDS.finditer(d.text or "")]
        found = set()
        for w in scanner.each:
            need = len(w.words) - w.most
            known = set(w.words)
            for i in range(len(words)):
                if words[i][1] in w.first and sum(x in known for _, x in words[i : i + w.reach]) >= need and subsequence(w.words, [x for _, x in words[i : i + w.reach]]) >= need:
                    found.add(w.name)
        assert set(got[k].licences.split(",")) - {""} <= found
        # a notice that is the start of a longer wording gives way to it: what is reported can be fewer names, never none
        assert bool(found) == bool(got[k].n_found) and got[k].n_exact <= got[k].n_found and (got[k].best_reduction is None) == (not found)


def subsequence(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        last = row
        row = [0]
        for j, y in enumerate(b):
            row.append(last[j] + 1 if x == y else max(last[j + 1], row[j]))
    return row[-1]


def test_vocabulary_is_not_in_the_repository():
    assert json.loads(open(queries.tokenizer_path()).read())["model"]
