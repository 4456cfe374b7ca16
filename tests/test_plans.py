import os

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as driver
from leakaudit.functions.weights import Scheme
from leakaudit.operators import metrics, scores
from leakaudit.plans import audit, queries

DUCK = [
    "lex_coverage", "token_class_counts", "comment_spans_html", "mask_runs", "token_weights_mean", "split_overlap", "context_moments", "token_zscore", "context_entropy",
    "score_surprise", "score_neighbour", "pooled_concat", "auc_binned", "roc_points", "attack_table", "benchmark_contamination", "asof_target", "near_copies", "sql_surface", "event_sequence_scores",
]


@pytest.fixture(scope="module")
def duck(sf):
    duckdb = pytest.importorskip("duckdb")
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        path = f"{sf}/{t}.parquet"
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return c


def plain(v):
    if v is None or v != v:
        return None
    if isinstance(v, float):
        return round(v, 6) + 0.0
    return v.isoformat() if hasattr(v, "isoformat") else int(v) if isinstance(v, bool) else v


@pytest.mark.parametrize("name", DUCK)
def test_queries_equal_their_sql(spark, sf, duck, name):
    got = driver.queries()[name](spark, sf)
    cursor = duck.execute(driver.oracle_sql()[name])
    columns = [c[0] for c in cursor.description]
    assert sorted(got.columns) == sorted(columns)
    want = sorted(repr([plain(r[columns.index(c)]) for c in sorted(columns)]) for r in cursor.fetchall())
    assert sorted(repr([plain(r[c]) for c in sorted(columns)]) for r in got.collect()) == want


def test_texts_of_over_8196_tokens_are_read_whole(spark, tmp_path):
    duckdb = pytest.importorskip("duckdb")
    long = " ".join(f"word{k % 700} \"said {k}\"" for k in range(4000))
    rows = [(k, long + f" end{k}" if k < 3 else f"word{k} word{k + 1} is short", "en" if k % 2 else "de") for k in range(40)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    assert audit.token_table(spark, str(tmp_path)).agg(F.max("t")).first()[0] > 8196
    c = duckdb.connect()
    c.sql(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    for name in ("token_class_counts", "score_weighted_z"):
        test_queries_equal_their_sql(spark, str(tmp_path), c, name)


def test_mean_weights_cover_every_page(spark, tmp_path):
    from leakaudit.operators import tokens
    from leakaudit.sources import catalog

    pages = [(k, "u", f"<p class=\"c{k}\">word{k} shared</p><!-- note {k} -->tail{k % 3}") for k in range(12)]
    spark.createDataFrame(pages, "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    spark.createDataFrame([(k, "shared word", "en") for k in range(3)], "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    some = catalog.samples(spark, str(tmp_path), "pages")
    over = {}
    for r in tokens.spans(some, "html").collect():
        for at in range(r.start, r.stop):
            over[r.sample_id, at] = max(over.get((r.sample_id, at), 0), Scheme.default().weights[r.kind])
    own = Scheme({k: w for k, w in Scheme.default().weights.items() if k not in ("comment", "literal", "lint")})
    rows = tokens.tokens(some, "html", tokens.lexicon(catalog.samples(spark, str(tmp_path), "documents")), own).collect()
    want = {(r.sample_id, r.pos): round(sum(max(r.weight, over.get((r.sample_id, at), 0)) for at in range(r.start, r.stop)) / (r.stop - r.start), 6) for r in rows}
    got = {(r.sample_id, r.pos): r.weight for r in queries.token_weights_mean(spark, str(tmp_path)).collect()}
    assert got == pytest.approx(want) and {k for k, _ in got} == set(range(12))


@pytest.mark.parametrize("name", ["token_weights_max", "token_logp", "full_outer_targets", "licence_slices", "ngram_counts", "slippage_words", "split_balance"])
def test_whole_queries_equal_their_sql(spark, sf, duck, name):
    test_queries_equal_their_sql(spark, sf, duck, name)


def test_dense_scores_cover_every_sample(spark, tmp_path):
    rows = [(k, f"word{k} shared text of sample {k}", "en fr de es".split()[k % 4]) for k in range(24)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    got = queries.dense_target_scores(spark, str(tmp_path)).collect()
    assert {r.sample_id for r in got} == set(range(24)) and {r.slice for r in got} == {"en", "fr", "de", "es"}


def test_every_registered_query_has_a_stable_name():
    assert len(queries.QUERIES) >= 85 and set(queries.ORACLES) <= set(queries.QUERIES)
    assert set(driver.oracle_sql()) <= set(driver.queries())


def test_blind_scores_and_a_null_target_tell_nothing(spark):
    """Over several salts: what never consults the target, and a target trained regardless of membership, stay near one half."""
    found = {"blind": [], "weighted": [], "null": []}
    for k in range(4):
        table = audit.token_table(spark, "/root/testdata/sf0.01", salt=str(k), config=audit.Config(slippage=False))
        rows = audit.probability_scores(table).where("role = 'holdout'")
        areas = {r.method: r.auc for r in metrics.auc(scores.long_form(rows, ("mean_weight", "weighted_z"))).collect()}
        found["blind"].append(areas["mean_weight"])
        found["weighted"].append(areas["weighted_z"])
        null = audit.probability_scores(table.withColumn("_m", F.col("is_member")).withColumn("is_member", F.col("role") == "shadow")).where("role = 'holdout'").select("sample_id", "weighted_z")
        truth = table.where("role = 'holdout'").select("sample_id", "is_member").distinct()
        found["null"].append(metrics.auc(null.join(truth, "sample_id").select("is_member", F.lit("null").alias("method"), F.col("weighted_z").alias("score"))).first().auc)
    mean = {k: sum(v) / len(v) for k, v in found.items()}
    assert abs(mean["blind"] - 0.5) < 0.06 and abs(mean["null"] - 0.5) < 0.06 and mean["weighted"] > 0.68


def test_auc_grows_with_exposure(spark):
    areas = []
    for e in (1, 4, 16):
        config = audit.Config(exposure=e)
        rows = scores.long_form(audit.probability_scores(audit.token_table(spark, "/root/testdata/sf0.01", config=config), config).where("role = 'holdout'"), ("weighted_z",))
        areas.append(metrics.auc(rows).first().auc)
    assert areas[0] < areas[1] < areas[2]


def test_weighted_z_beats_unweighted_beats_loss(spark):
    rows = scores.long_form(audit.probability_scores(audit.token_table(spark, "/root/testdata/sf0.01")).where("role = 'holdout'"))
    a = {r.method: r.auc for r in metrics.auc(rows).collect()}
    assert a["weighted_z"] > a["unweighted_z"] > a["loss"] > 0.55


def test_composite_is_bounded_and_ahead_of_the_loss(spark):
    table = audit.token_table(spark, "/root/testdata/sf0.01")
    out = audit.composite(table, audit.Config(layers=(0, 1, 2, 4), probe="linear", top=3))
    assert out.where("score < 0 or score > 1").count() == 0
    a = {r.method: r.auc for r in metrics.auc(out).collect()}
    loss = metrics.auc(scores.long_form(audit.probability_scores(table).where("role = 'holdout'"), ("loss",))).first().auc
    assert a["composite"] > loss + 0.05 and a["probe_ensemble"] > 0.6


def test_audit_facade(spark, sf):
    result = audit.audit_table(spark, sf, config=audit.Config(layers=(0, 1, 4), probe="linear", copies=1, scheme=Scheme.default()))
    methods = {r.method for r in result.table.select("method").distinct().collect()}
    assert {"loss", "lowest_k", "neighbour", "surprise", "weighted_z", "probe_ensemble", "composite"} <= methods
    assert result.costs["passes"] == 3 and result.costs["tokens"] > 1000
    assert spark.sql("SELECT * FROM audit_scores WHERE slice = 'en' ORDER BY score DESC LIMIT 5").count() == 5


def test_entry_runs(spark):
    assert driver.entry(spark).count() > 0


def test_sliding_windows_count_at_the_nearest_second(spark, tmp_path):
    """Shortly before a boundary its SQL counts an event beyond it; halves go to the even second."""
    duckdb = pytest.importorskip("duckdb")
    c, at = duckdb.connect(), ("05:59:59.7", "05:59:59.5", "05:59:59.499999", "05:59:58.5", "06:00:00.2", "11:59:59.999999", "12:00:00")
    c.sql("SET TimeZone = 'UTC'")
    c.sql(f"COPY (SELECT x::TIMESTAMP AS ts, 'a' AS event_type FROM (SELECT unnest({[f'2024-03-31 {x}' for x in at]}) AS x)) TO '{tmp_path}/events.parquet' (FORMAT parquet)")
    c.sql(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet'")
    test_queries_equal_their_sql(spark, str(tmp_path), c, "sliding_windows_batch")


def test_tags_and_settings_come_from_given_tables(spark, sf, duck):
    for name in ("tag_override", "audit_grid"):
        test_queries_equal_their_sql(spark, sf, duck, name)
    assert driver.queries()["tag_override"](spark, sf).select("id").distinct().count() == spark.read.parquet(f"{sf}/part.parquet").count()


def test_code_mask_covers_every_part(spark, sf):
    got = driver.queries()["code_mask"](spark, sf)
    assert got.select("sample_id").distinct().count() == spark.read.parquet(f"{sf}/part.parquet").count()
    kinds = {(r.slice, r.tok): r.kind for r in got.where("tok in ('def', 'func', 'fn', 'class', 'for')").select("slice", "tok", "kind").distinct().collect()}
    assert kinds[("java", "class")] == kinds[("go", "func")] == kinds[("rust", "fn")] == kinds[("ruby", "def")] == "boilerplate" and kinds[("python", "for")] == "comment"
