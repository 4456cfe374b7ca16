import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from leakaudit.operators import activation, dense, scores, target, tokens
from leakaudit.functions.weights import Scheme

TEXTS = [(1, "en", True, "shadow", "red blue red blue green"), (2, "en", True, "holdout", "red red blue yellow"), (3, "en", False, "holdout", "blue green red violet")]


@pytest.fixture(scope="module")
def table(spark):
    rows = spark.createDataFrame(TEXTS, "sample_id long, slice string, is_member boolean, role string, text string")
    return tokens.tokens(rows, scheme=Scheme.default()).cache()


def test_closed_forms_equal_a_dense_vocabulary(table):
    made = target.train(table, 16, (1,))
    counts = {(r.ctx, r.tok): r.n for r in made.counts.collect()}
    vocabulary = sorted({t for _, _, m, _, text in TEXTS if m for t in text.split()}) + ["<other>"]
    assert made.vocabulary.first()[0] == len(vocabulary)
    for r in target.forward(table, made).join(table.select("sample_id", "pos", "prev1"), ["sample_id", "pos"]).collect():
        logits = np.array([math.log(counts.get((r.prev1, t), 0) + 0.01) for t in vocabulary])
        at = np.array([vocabulary.index(r.key) if r.key in vocabulary else len(vocabulary) - 1])
        for moments, z in (("uniform", r.z), ("model", r.z_model)):
            logp, mu, sigma, want, entropy = (x[0] for x in dense.statistics(logits[None], at, moments))
            if logits.std() < 1e-9:
                want = 0.0
            assert abs(z - want) < 1e-6
            if moments == "uniform":
                assert abs(r.logp - logp) < 1e-9 and abs(r.mu - mu) < 1e-9 and abs(r.sigma - sigma) < 1e-6
            assert abs(r.entropy - entropy) < 1e-9


def test_needed_contexts_give_the_same_statistics(table):
    asked = table.where("role = 'holdout'").select(F.lit(1).alias("layer"), tokens.context(1).alias("ctx"))
    full, part = target.train(table, 16), target.train(table, 16, needed=asked)
    pick = lambda made: sorted(tuple(r) for r in target.forward(table.where("role = 'holdout'"), made).select("sample_id", "pos", "logp", "z", "entropy").collect())
    assert pick(full) == pick(part)


def test_hand_examples(spark):
    logp, mu, sigma, z, _ = dense.statistics(np.array([[2.0, 0, 0, 0], [2.0, 0, 0, 0]]), np.array([0, 1]))
    assert np.allclose(mu, 0.5) and np.allclose(sigma, 0.8660254) and np.allclose(z, [1.7320508, -0.5773503])
    rows = spark.createDataFrame([(1, "x", True, "holdout", float(v), float(v), w, 0.0, 0.0, "k") for v, w in zip(z, (10.0, 0.1), strict=True)], "sample_id long, slice string, is_member boolean, role string, z double, z_model double, weight double, logp double, entropy double, key string")
    r = scores.per_sample(rows).first()
    assert round(r.weighted_z, 5) == 0.84482 and round(r.unweighted_z, 5) == 0.60461
    acts = spark.createDataFrame([(1, "x", True, "holdout", 0, [1.0, 0.0], 10.0), (1, "x", True, "holdout", 0, [0.0, 1.0], 0.1)], "sample_id long, slice string, is_member boolean, role string, layer int, act array<double>, weight double")
    assert [round(x, 6) for x in activation.pool(acts, "both", 2).first().features] == [0.5, 0.5, 0.990099, 0.009901]


def test_z_is_invariant_and_model_moments_differ():
    rng = np.random.default_rng(0)
    x, t = rng.normal(size=(5, 9)), rng.integers(0, 9, 5)
    z = dense.statistics(x, t)[3]
    assert np.allclose(z, dense.statistics(3 * x + 7, t)[3])
    assert np.allclose(dense.statistics(np.ones((2, 4)), np.array([0, 1]))[3], 0)


def test_lowest_k_counts_and_equality_with_the_loss(spark):
    values = [-float(v) for v in (3, 1, 4, 1.5, 9, 2, 6, 5, 3.5, 8)]
    row = spark.range(1).select(F.array(*[F.lit(v) for v in values]).alias("l")).select(*[scores.lowest(F.col("l"), k).alias(f"k{k}") for k in (1, 10, 20, 25, 100)]).first()
    ordered = sorted(values)
    assert [row.k1, row.k10, row.k20, row.k25] == [ordered[0], ordered[0], sum(ordered[:2]) / 2, sum(ordered[:2]) / 2]
    assert abs(row.k100 - sum(values) / 10) < 1e-12


def test_uniform_scheme_equals_the_unweighted_score(spark, sf):
    from leakaudit.plans import audit

    config = audit.Config(scheme=Scheme.uniform())
    rows = audit.probability_scores(audit.token_table(spark, sf, config=config), config)
    assert rows.where("abs(weighted_z - unweighted_z) > 1e-9").count() == 0
    assert rows.where("weighted_z <= 0 or weighted_z >= 1").count() == 0


def test_a_copy_without_swaps_calibrates_to_zero(table):
    made = target.train(table, 16)
    copies = target.neighbours(table, 2, swap=0.0)
    stats = target.forward(copies.withColumn("kind", F.col("copy").cast("string")).drop("copy"), made).withColumn("copy", F.col("kind").cast("int"))
    assert all(abs(r.score) < 1e-12 for r in scores.neighbour_calibrated(stats).collect())
    swapped = target.neighbours(table, 3, swap=1.0)
    assert swapped.groupBy("sample_id", "copy").agg(F.count_distinct("t").alias("d"), F.count(F.lit(1)).alias("n")).where("d <> n").count() == 0


def test_dense_target_learns_and_half_precision_is_near(table, spark):
    made = dense.train(table, width=8, layers=3, size=64)
    full = dense.forward(table, made)
    assert full.select("layer").distinct().count() == 3 and len(full.first().act) == 8
    blank = dense.forward(table, dense.NumpyTarget(width=8, layers=3, size=64))
    mean = lambda df: df.where("layer = 0").join(table.where("is_member").select("sample_id").distinct(), "sample_id").agg(F.avg("logp")).first()[0]
    assert mean(full) > mean(blank)
    made.half = True
    near = full.alias("a").join(dense.forward(table, made).alias("b"), ["sample_id", "pos", "layer"]).select(F.max(F.abs(F.col("a.logp") - F.col("b.logp")))).first()[0]
    assert 0 < near < 0.2


def test_onnx_adapter_shapes(spark, table):
    class Session:
        def get_inputs(self):
            return [type("I", (), {"name": "ids"})]

        def get_outputs(self):
            return [type("O", (), {"name": n}) for n in ("logits", "h0")]

        def run(self, names, feed):
            n = feed["ids"].shape[1]
            return [np.arange(n * 4, dtype=float).reshape(1, n, 4), np.ones((1, n, 3))]

    made = dense.OnnxTarget(b"", lambda ts: np.arange(len(ts)) % 4)
    made._session = Session()
    logits, acts = made.forward(np.array([0, 1, 2]))
    assert logits.shape == (3, 4) and (logits[0] == 0).all() and (logits[1] == [0, 1, 2, 3]).all() and acts[0].shape == (3, 3)


def test_truncation(spark):
    rows = spark.createDataFrame([(1, "en", "one two three four five")], "sample_id long, slice string, text string")
    assert tokens.tokens(rows, max_tokens=3).count() == 3
