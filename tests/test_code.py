"""Audits of source code: grammar by slice, linter and parser in the mask, subwords."""

import pytest
from pyspark.sql import functions as F

from leakaudit.functions.weights import Scheme
from leakaudit.operators import linting, parsing, subword, tokens
from leakaudit.plans import audit
from leakaudit.sources import catalog
from leakaudit.sources.examples import CODE_SAMPLES


def frame(spark, rows):
    return spark.createDataFrame(rows, "sample_id long, slice string, text string")


@pytest.fixture(scope="module")
def code(spark):
    return [(k, s, t) for k, (s, t, _) in enumerate(CODE_SAMPLES)]


@pytest.mark.parametrize("parser", [False, True])
def test_the_mask_of_mixed_languages_follows_the_hand_written_spans(spark, code, parser):
    if parser and len(parsing.languages()) == 1:
        pytest.skip("no lexers but Python's")
    rows = audit.mask_table(frame(spark, code), audit.Config(slippage=False, parser=parser)).collect()
    for k, _, text in code:
        spans = [(kind, text.index(x), text.index(x) + len(x)) for kind, x in CODE_SAMPLES[k][2]]
        for r in (r for r in rows if r.sample_id == k):
            assert text[r.start : r.stop] == r.tok
            inside = [kind for kind, a, b in spans if a < r.stop and r.start < b]
            if r.tok in ("TODO", "FIXME"):
                assert r.kind == "tag"
            elif "comment" in inside:
                assert (r.kind, r.weight) == ("comment", 10.0), (text, r)
            elif "literal" in inside:
                # marks that a generic format rule covers weigh the same five
                assert r.weight == 5.0 and r.kind in ("literal", "lint"), (text, r)
            else:
                assert r.kind in ("boilerplate", "standard", "long", "lint"), (text, r)


def test_python_slices_take_the_line_rules_and_others_the_generic_ones(spark):
    text = "value=compute(first,second)\nif value :\n   go()  \n"
    rows = audit.mask_table(frame(spark, [(1, "python", text), (2, "java", text)]), audit.Config(slippage=False)).collect()
    hit = {k: {r.start for r in rows if r.sample_id == k and r.kind == "lint"} for k in (1, 2)}
    faults = linting.lint_python(frame(spark, [(1, "python", text)])).collect()
    want = {r.start for r in rows if r.sample_id == 1 and any(f.start < r.stop and r.start < f.stop for f in faults)}
    assert {f.rule for f in faults} == {"E231", "E203", "E111", "W291"} and hit[1] == want
    assert hit[2] == {text.index(",")} | {r.start for r in rows if r.sample_id == 2 and r.tok == "second"}


def test_compound_names_are_known_by_their_parts(spark):
    words = spark.createDataFrame([("read",), ("file",), ("name",), ("http",)], "word string")
    text = "readFileName read_file HTTPName readZorgle zorgle file2name xy_name"
    some = frame(spark, [(1, "en", text)])
    known = {r.word for r in tokens.compound_words(some, words).collect()}
    assert known == {"read", "file", "name", "http", "readfilename", "read_file", "httpname", "file2name", "xy_name"}
    got = {r.tok: r.kind for r in audit.mask_table(some, audit.Config(compounds=True), words).collect()}
    assert {t for t, k in got.items() if k == "slippage"} == {"readZorgle", "zorgle"}


@pytest.mark.parametrize("how", ["max", "mean"])
def test_subwords_take_the_mask_of_their_characters(spark, how):
    tokenizers = pytest.importorskip("tokenizers")
    P = pytest.importorskip("public_tokenizers")
    path = P.path("byte_bpe_50k.json")
    texts = [(1, "python", "compute_total(a, b)  # naïve TODO\n"), (2, "en", "Hello \U0001f600\U0001f44d \"quoted thing\" x"), (3, "en", "z")]
    some = frame(spark, texts).withColumn("is_member", F.lit(True)).withColumn("role", F.lit("holdout"))
    masked = tokens.tokens(some, None)
    rows = subword.weighted(some, masked, open(path).read(), how).collect()
    real, lexed = tokenizers.Tokenizer.from_file(path), masked.collect()
    for k, _, text in texts:
        chars = [0.1] * len(text)
        for r in lexed:
            if r.sample_id == k:
                chars[r.start : r.stop] = [max(0.1, r.weight)] * (r.stop - r.start)
        e = real.encode(text, add_special_tokens=False)
        mine = sorted((r for r in rows if r.sample_id == k), key=lambda r: r.pos)
        assert [r.key for r in mine] == [str(i) for i in e.ids] and [r.t for r in mine] == list(range(1, len(e.ids) + 1))
        for r, (a, b) in zip(mine, e.offsets, strict=True):
            each = chars[a:b]
            assert r.weight == pytest.approx(max(each) if how == "max" else sum(each) / len(each))
        assert [r.prev1 for r in mine] == ["^", *[r.key for r in mine[:-1]]]


def test_an_audit_of_any_code(spark, sf):
    some = catalog.code_from_parts(spark, sf)
    assert {r.slice for r in some.select("slice").distinct().collect()} == set(catalog.CODE)
    extra = spark.createDataFrame([(10**6, "python", None, True), (10**6 + 1, "go", "", False)], "sample_id long, slice string, text string, is_member boolean")
    result = audit.audit(some.drop("role").unionByName(extra, allowMissingColumns=True), audit.Config(layers=(0, 1, 4), probe="linear", copies=1, max_tokens=20))
    table = {(r.slice, r.method): r.auc for r in result.table.collect()}
    assert {s for s, _ in table} == {*catalog.CODE, "overall"} and {"composite", "loss", "lowest_k", "neighbour"} <= {m for _, m in table}
    assert result.costs["rejected"] == 2 and result.costs["truncated_tokens"] > 0 and result.costs["samples"] == some.count()
    with pytest.raises(ValueError, match="is_member"):
        audit.audit(some.drop("is_member"))


def test_files_keep_their_last_line_feed(spark, tmp_path):
    (tmp_path / "a.py").write_bytes(b"x = 1\n")
    (tmp_path / "b.rs").write_bytes("fn main() {} // café ".encode() + b"\xff")
    got = {r.slice: r.text for r in catalog.code_files(spark, str(tmp_path)).collect()}
    assert got["python"] == "x = 1\n" and got["rust"].startswith("fn main() {} // café ")
    assert linting.lint_python(catalog.code_files(spark, str(tmp_path)).where("slice = 'python'")).count() == 0


def test_a_scheme_without_a_kind_still_lexes_by_slice(spark, code):
    rows = audit.mask_table(frame(spark, code), audit.Config(slippage=False, scheme=Scheme.default().without("comment"))).collect()
    assert not any(r.kind == "comment" for r in rows) and any(r.kind == "literal" for r in rows)
