"""A sample's tokens in its row against the token table and its shuffled joins."""

import pytest
from pyspark.sql import functions as F

from leakaudit.functions.weights import DEFAULT, Scheme
from leakaudit.operators import activation, dense, mask, rows, scores, tokens
from leakaudit.plans import audit, queries, workloads
from leakaudit.plans.audit import Config
from leakaudit.sources import catalog


def _same(a, b, keys):
    a, b = ({tuple(r[k] for k in keys): r.asDict(True) for r in df.collect()} for df in (a, b))
    assert a.keys() == b.keys() and len(a) > 0
    for key, x in a.items():
        for c, value in x.items():
            assert b[key][c] == (pytest.approx(value, abs=1e-9) if isinstance(value, (float, list)) else value), (key, c)


@pytest.mark.parametrize(("source", "config"), [("documents", Config()), ("pages", Config(exposure=2, layer=4)), ("conversations", Config(exposure=4, layer=0, scheme=Scheme({"boilerplate": 0.1, "standard": 1.0, "slippage": 7.0, "tag": 0.5})))])
def test_scores_and_tokens_are_those_of_the_joins(spark, sf, source, config):
    table, row = audit.token_table(spark, sf, source, config), audit.row_table(spark, sf, source, config)
    _same(table.select("sample_id", "pos", "t", "key", "weight", "prev1", "prev4"), rows.unfolded(row).select("sample_id", "pos", "t", "key", "weight", "prev1", "prev4"), ("sample_id", "pos"))
    _same(audit.probability_scores(table, config).select(*scores.BY, *rows.SCORED), audit.row_scores(row, config), ("sample_id",))
    layers = (config.layer,)
    stats = audit.model_stats(table, config, layers)
    model = rows.trained(row, config.layer, config.exposure)
    _same(stats.select("sample_id", "pos", "logp", "z", "z_model", "entropy"), rows.stats(row, model, config.layer), ("sample_id", "pos"))
    _same(activation.pool(stats, "both"), audit.row_pools(row, layers, "both", config), ("sample_id", "layer"))


@pytest.mark.parametrize("bound", ["WORDS", "PAIRS"])
def test_what_cannot_be_broadcast_is_joined(spark, sf, monkeypatch, bound):
    small = audit.sample_scores(spark, sf)
    monkeypatch.setattr(rows, bound, 10)
    _same(small, audit.sample_scores(spark, sf).select(*small.columns), ("sample_id",))


def test_equal_digests_are_told_apart(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(rows.xxhash, "xxh3_64_intdigest", len)
    some = rows.Index(pa.array(["bb", "a", "cc", "ddd", "dd"]))
    found = some.find(pa.array(["dd", "x", "cc", "a", "dddd", "dd", "zz"]))
    assert [None if i < 0 else some.values[int(i)].as_py() for i in found] == ["dd", None, "cc", "a", None, "dd", None]


@pytest.mark.parametrize("name", ["auc_pooled", "blind_controls", "context_entropy", "layer_top5", "ablation_dictionary"])
def test_no_token_is_shuffled(spark, sf, monkeypatch, name):
    """The token table isn't asked for, and nothing that the query writes on the way has a row a token but what it returns."""
    monkeypatch.setattr(audit, "token_table", lambda *a, **b: pytest.fail("a row a token"))
    assert queries.QUERIES[name](spark, sf).count() > 0


def test_several_dictionaries_in_one_pass(spark, sf):
    least = {"df_2": 2, "df_3": 3, "df_10": 10}
    one = audit.dictionary_scores(spark, sf, least)
    for name, m in least.items():
        _same(audit.probability_scores(audit.token_table(spark, sf, config=Config(min_df=m))).select("sample_id", F.col("weighted_z").alias("score")), one.where(F.col("method") == name).select("sample_id", "score"), ("sample_id",))


def test_dictionary_and_target_do_not_pass_the_driver(spark, sf, monkeypatch):
    """Neither is collected nor broadcast: a driver of bounded memory scores any input that the workers can."""
    monkeypatch.setattr(type(spark.range(1)), "toArrow", lambda self: pytest.fail("collected"))
    monkeypatch.setattr(type(spark.sparkContext), "broadcast", lambda self, value: pytest.fail("broadcast"))
    assert audit.sample_scores(spark, sf).count() > 0


def test_a_store_that_arrow_cannot_open(spark, sf, monkeypatch):
    small = audit.sample_scores(spark, sf)

    def closed(uri):
        raise ValueError(uri)

    monkeypatch.setattr(rows, "_opened", closed)
    _same(small, audit.sample_scores(spark, sf).select(*small.columns), ("sample_id",))


def test_dense_scores_are_those_of_the_token_table(spark, sf, monkeypatch):
    monkeypatch.setattr(dense, "POSITIONS", 50)
    row = queries.dense_target_scores(spark, sf)
    assert row.columns == [*scores.BY, "loss", "weighted_z"]
    monkeypatch.setattr(audit, "row_table", lambda *a, **b: None)
    _same(queries.dense_target_scores(spark, sf), row, ("sample_id",))


def test_mean_projection_is_that_of_the_token_table(spark, sf):
    own = Scheme({k: w for k, w in DEFAULT.items() if k not in ("comment", "literal", "lint")})
    for source, grammar in (("pages", "html"), ("documents", "prose")):
        some = catalog.samples(spark, sf, source)
        plain = tokens.tokens(some, grammar, tokens.lexicon(catalog.samples(spark, sf, "documents")), own)
        want = mask.project_mean(plain, mask.runs(tokens.spans(some, grammar)))
        got = audit.row_table(spark, sf, source, mean=own).withColumn("weight", F.col("weight_mean"))
        _same(want, rows.unfolded(got).select("sample_id", "pos", "weight"), ("sample_id", "pos"))


def test_projections_are_compared_without_a_token_table(spark, sf, monkeypatch):
    monkeypatch.setattr(audit, "token_table", lambda *a, **b: pytest.fail("a row a token"))
    assert {r.method for r in queries.ablation_projection(spark, sf).collect()} == {"max", "mean"}


def test_contamination_is_that_of_the_token_table(spark, sf, monkeypatch):
    """The contexts asked for are read by the workers under the name that they are written by."""
    row = workloads.contamination_scores(spark, sf)
    monkeypatch.setattr(audit, "row_table", lambda *a, **b: None)
    _same(workloads.contamination_scores(spark, sf), row, ("method",))


def test_the_five_best_are_chosen_among_all_layers(spark, sf):
    best = queries.layer_top5(spark, sf).collect()
    every = queries.metrics.auc(queries._uni(spark, sf, tokens.LARGE).where("role = 'shadow'")).collect()
    strength = {}
    for r in every:
        layer = int(r.method.split(":")[0])
        strength[layer] = max(strength.get(layer, 0.0), round(abs(r.auc - 0.5), 4))
    assert sorted(strength) == list(tokens.LARGE)
    assert [(r.layer, r.rank) for r in sorted(best, key=lambda r: r.rank)] == [(k, n + 1) for n, k in enumerate(sorted(strength, key=lambda k: (-strength[k], k))[:5])]


def test_scheme_totals_without_a_shuffled_dictionary(spark, sf, monkeypatch):
    """No token is looked up by a join, whose salted copies of a large dictionary could be sent to the driver."""
    with monkeypatch.context() as m:
        m.setattr(rows, "WORDS", 10)
        joined = queries.scheme_ablation_weights(spark, sf)
    monkeypatch.setattr(tokens, "lookup", lambda *a, **b: pytest.fail("a row a token"))
    _same(joined, queries.scheme_ablation_weights(spark, sf), ("without",))
