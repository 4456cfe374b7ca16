import pytest
from pyspark.sql import functions as F

from leakaudit.functions import lexing, surface
from leakaudit.functions.weights import DEFAULT, Scheme
from leakaudit.operators import linting, mask, subword, tokens
from tests.fixtures.code_samples import CODE_SAMPLES, LINT_CASES


def frame(spark, rows):
    return spark.createDataFrame(rows, "sample_id long, slice string, text string")


@pytest.mark.parametrize("grammar", list(lexing.GRAMMARS))
def test_stretches_join_to_the_text_and_spans_are_as_expected(spark, grammar):
    mine = [(k, s, t) for k, (s, t, _) in enumerate(CODE_SAMPLES) if s == grammar]
    rows = tokens.placed(frame(spark, mine), grammar, ("piece", "syntax", "lint")).collect()
    for k, _, text in mine:
        for stream in ("piece", "syntax", "lint"):
            parts = sorted((r.pos, r.tok, r.start, r.stop) for r in rows if r.sample_id == k and r.stream == stream)
            assert "".join(p[1] for p in parts) == text
            assert all(text[a:b] == tok for _, tok, a, b in parts)
    found = tokens.spans(frame(spark, mine), grammar).where("kind in ('comment', 'literal')").collect()
    for k, _, text in mine:
        assert sorted((r.start, r.kind, text[r.start : r.stop]) for r in found if r.sample_id == k) == sorted((text.index(x), kind, x) for kind, x in CODE_SAMPLES[k][2])


def test_offsets_are_code_points(spark):
    text = "e\u0301 \U0001f600 na\u00efve\r\nx"
    rows = tokens.placed(frame(spark, [(1, "en", text)])).orderBy("pos").collect()
    assert "".join(r.tok for r in rows) == text
    assert all(text[r.start : r.stop] == r.tok for r in rows)


def test_length_bounds_keywords_and_empty_text(spark):
    text = "ab abc " + "x" * 9 + " " + "y" * 10 + " " + "z" * 11 + " return"
    got = {r.tok: r.weight for r in tokens.tokens(frame(spark, [(1, "python", text), (2, "python", "")]), "python").collect()}
    assert got == {"ab": 0.1, "abc": 1.0, "x" * 9: 1.0, "y" * 10: 3.0, "z" * 11: 3.0, "return": 0.1}


def test_overlapping_kinds_take_the_largest_and_a_tag_overrides(spark):
    words = spark.createDataFrame([("known", 3)], "word string, df long")
    text = 'known foreign "known text" TODO'
    low = Scheme({**DEFAULT, "tag": 0.5})
    got = {(r.pos, r.tok): (r.kind, r.weight) for r in tokens.tokens(frame(spark, [(1, "en", text)]), words=words, scheme=low).collect()}
    assert got[(1, "known")] == ("standard", 1.0)
    assert got[(3, "foreign")] == ("slippage", 10.0)
    assert got[(6, "known")] == ("literal", 5.0)
    assert got[(8, "text")] == ("slippage", 10.0)
    assert got[(11, "TODO")] == ("tag", 0.5)


def test_runs_equal_a_mask_of_single_characters(spark):
    import random

    rng = random.Random(1)
    spans = [("literal", 0, 10), ("comment", 5, 15), ("tag", 8, 12), ("lint", 14, 20), ("literal", 30, 31)]
    spans += [(rng.choice(["literal", "comment", "lint", "tag"]), a, a + rng.randint(1, 9)) for a in (rng.randint(40, 90) for _ in range(12))]
    scheme = Scheme({**DEFAULT, "tag": 2.0})
    rows = spark.createDataFrame([(1, k, a, b) for k, a, b in spans], "sample_id long, kind string, start int, stop int")
    got = sorted((r.start, r.stop, r.weight) for r in mask.runs(rows, scheme).collect())
    assert all(a[1] <= b[0] for a, b in zip(got, got[1:], strict=False))
    for at in range(110):
        cover = [k for k, a, b in spans if a <= at < b]
        want = None if not cover else 2.0 if "tag" in cover else max(scheme[k] for k in cover)
        assert next((w for a, b, w in got if a <= at < b), None) == want


def test_projection_to_subwords(spark):
    rows = spark.createDataFrame([(1,)], "id int").select(
        F.expr("array(named_struct('start', 0, 'stop', 4), named_struct('start', 4, 'stop', 8), named_struct('start', 9, 'stop', 9))").alias("t"),
        F.expr("array(named_struct('start', 2, 'stop', 6, 'weight', 10D), named_struct('start', 6, 'stop', 7, 'weight', 5D))").alias("r"))
    high = rows.select(subword.project(F.col("t"), F.col("r"))).first()[0]
    mean = rows.select(subword.project(F.col("t"), F.col("r"), how="mean")).first()[0]
    assert high == [10.0, 10.0, 0.1]
    assert [round(x, 6) for x in mean] == [5.05, 6.275, 0.1]


def test_subword_offsets_cover_the_text(spark):
    P = pytest.importorskip("public_tokenizers")
    text = "Naïve café: 12 déjà-vu"
    rows = subword.encode(frame(spark, [(1, "fr", text), (2, "fr", "")]), open(P.path("byte_bpe_50k.json")).read(), 8).collect()
    got = {r.sample_id: r.tokens for r in rows}
    assert len(got[1]) == 8 and got[2] == []
    assert got[1][0].start == 0 and all(t.start < t.stop <= len(text) for t in got[1])


def test_normalised_weights_sum_to_one(spark):
    row = spark.range(1).select(mask.normalise(F.array(F.lit(10.0), F.lit(0.1))).alias("a"), mask.normalise(F.array(F.lit(10.0), F.lit(0.1)), "max").alias("b")).first()
    assert abs(sum(row.a) - 1) < 1e-12 and row.b == [1.0, 0.01]


@pytest.mark.parametrize("rule,bad,good,line,column", LINT_CASES)
def test_lint_rules_fire_where_they_should(spark, rule, bad, good, line, column):
    rows = linting.lint_python(frame(spark, [(1, "python", bad), (2, "python", good)])).where(F.col("rule") == rule).collect()
    assert [(r.sample_id, r.line, r.column) for r in rows] == [(1, line, column)]
    starts = [0]
    for x in bad.split("\n"):
        starts.append(starts[-1] + len(x) + 1)
    assert rows[0].start == starts[line - 1] + column - 1 and rows[0].stop > rows[0].start


def test_every_fault_of_a_line_is_found(spark):
    text = "f(a,b,c,d)  \nx  = 1 ; y  = 2\n\x1ff(a,b)\n"
    rows = linting.lint_python(frame(spark, [(1, "python", text)])).collect()
    got = sorted((r.rule, r.line, r.column, text[r.start : r.stop]) for r in rows)
    assert got == [("E203", 2, 7, " "), ("E221", 2, 2, "  "), ("E221", 2, 11, "  "), ("E231", 1, 4, ","), ("E231", 1, 6, ","), ("E231", 1, 8, ","), ("E231", 3, 5, ","), ("W291", 1, 11, "  ")]


def test_mean_projection_equals_single_characters(spark):
    import random

    rng = random.Random(4)
    toks, runs = [], []
    for sample in (1, 2, 3):
        for out, kind in ((toks, "t"), (runs, "r")):
            at, pos = 0, 0
            while at < 120 and not (kind == "r" and sample == 3):
                a = at + rng.randint(0, 3)
                at, pos = a + rng.randint(1, 9), pos + 1
                out.append((sample, pos, a, at, float(rng.choice([0.1, 1, 3, 5, 10]))) if kind == "t" else (sample, a, at, float(rng.choice([2, 5, 10]))))
    toks.append((3, 999, 500, 500, 1.0))
    got = mask.project_mean(spark.createDataFrame(toks, "sample_id long, pos int, start int, stop int, weight double"), spark.createDataFrame(runs, "sample_id long, start int, stop int, weight double"))
    got = {(r.sample_id, r.pos): r.weight for r in got.collect()}
    assert len(got) == len(toks)
    for sample, pos, a, b, w in toks:
        each = [max([w, *(x for s, c, d, x in runs if s == sample and c <= at < d)]) for at in range(a, b)] or [w]
        assert abs(got[(sample, pos)] - sum(each) / len(each)) < 1e-9


def test_sql_functions_and_parser_spans(spark):
    surface.register(spark)
    row = spark.sql("SELECT sigmoid(0D) AS s, token_class('a_longer_name') AS c, class_weight(token_class('TODO')) AS w").first()
    assert (row.s, row.c, row.w) == (0.5, "long", 10.0)
    text = 'x = f"a{b}c"  # note\nreturn'
    rows = spark.sql("SELECT * FROM lex_spans('" + text.replace("\n", "\\n") + "', 'python')").collect()
    assert {(r.kind, text[r.start : r.stop]) for r in rows} == {("literal", 'f"a{b}c"'), ("comment", "# note"), ("keyword", "return")}
    pytest.importorskip("pygments")
    code = 'class A { String s = "x"; // c\n}'
    assert ("comment", code.index("//"), code.index("\n")) in [(k, a, len(code[:b].rstrip())) for k, a, b in surface.parser_spans(code, "java")]


def test_tokens_take_no_window_and_no_sort(spark):
    """A chain of windows and sorts in one task ran out of memory at 0.1 GB; nulls, blanks and long texts are as before."""
    texts = [(1, "en", None), (2, "en", "  \n "), (3, "en", "\t lead \"in  quotes\" x ,y"), (4, "en", "ab " * 150_000), (5, "en", "ÄÖ ’x"), (6, "en", "")]
    rows = tokens.tokens(frame(spark, texts))
    plan = rows._jdf.queryExecution().executedPlan().toString()
    assert "Window" not in plan and "Sort" not in plan
    got = rows.where("sample_id <> 4").orderBy("sample_id", "pos").collect()
    assert [(r.sample_id, r.pos, r.tok, r.start, r.stop, r.t, r.prev1, r.kind) for r in got if r.sample_id == 3] == [
        (3, 2, "lead", 2, 6, 1, "^", "standard"), (3, 4, '"', 7, 8, 2, "lead", "literal"), (3, 5, "in", 8, 10, 3, '"', "literal"), (3, 7, "quotes", 12, 18, 4, "in", "literal"),
        (3, 8, '"', 18, 19, 5, "quotes", "literal"), (3, 10, "x", 20, 21, 6, '"', "boilerplate"), (3, 12, ",", 22, 23, 7, "x", "lint"), (3, 13, "y", 23, 24, 8, ",", "boilerplate")]
    assert [(r.tok, r.start, r.key) for r in got if r.sample_id == 5] == [("ÄÖ", 0, "äö"), ("’", 3, "’"), ("x", 4, "x")]
    assert {r.sample_id for r in got} == {3, 5}
    assert rows.where("sample_id = 4").selectExpr("count(*) as n", "max(t) as t", "max(stop) as stop", "max(pos) as pos").first()[:] == (150_000, 150_000, 449_999, 299_999)
