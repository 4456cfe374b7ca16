import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from leakaudit.llm import quality, toxicity
from leakaudit.llm.sparse import Rows, fit_linear, fit_machine, held_out
from tests.llm.common import edge, edge_texts, empty

DATA = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def tables(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet"), spark.read.parquet(f"{DATA}/labels.parquet")


def test_the_fold_is_what_the_contract_says(spark):
    rows = spark.createDataFrame([(k,) for k in (0, 1, 2, 17, 999, -3)], "doc_id long").select("doc_id", held_out(F.col("doc_id")).alias("h")).collect()
    assert all(r.h == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)


def test_the_sum_of_squares_identity():
    rng = np.random.default_rng(2)
    rows = Rows.of([(rng.choice(20, 6, replace=False), rng.normal(size=6).astype(np.float32)) for _ in range(9)])
    m = fit_machine(rows, (np.arange(9) % 2).astype(float), 20, rank=3, epochs=2)
    for k, got in enumerate(m.margin(rows)):
        i, v = rows.index[rows.bounds[k] : rows.bounds[k + 1]], rows.value[rows.bounds[k] : rows.bounds[k + 1]]
        want = m.bias + (m.weight[i] * v).sum() + sum(m.factor[i[a]] @ m.factor[i[b]] * v[a] * v[b] for a in range(6) for b in range(a + 1, 6))
        assert abs(got - want) < 1e-5


def test_pairwise_weights_learn_what_linear_ones_cannot():
    rng = np.random.default_rng(0)
    bits = rng.integers(0, 2, (600, 2))
    rows = Rows.of([(np.array([a, 2 + b]), np.ones(2, np.float32)) for a, b in bits])
    y = (bits[:, 0] ^ bits[:, 1]).astype(float)
    assert ((fit_machine(rows, y, 4, epochs=120, rate=0.3).predict(rows) > 0.5) == y).mean() > 0.95
    assert ((fit_linear(rows, np.zeros((600, 0)), y, 4, epochs=40).predict(rows, np.zeros((600, 0))) > 0.5) == y).mean() < 0.7


def test_quality_on_held_out_rows(spark, tables):
    docs, labels = tables
    model = quality.train(docs, labels)
    rows = quality.score(docs, model).join(labels, "doc_id").where("held_out").select("score", "predicted", "quality").collect()
    right = sum(r.predicted == r.quality for r in rows) / len(rows)
    pos, neg = [r.score for r in rows if r.quality], [r.score for r in rows if not r.quality]
    auc = sum((p > q) + (p == q) / 2 for p in pos for q in neg) / len(pos) / len(neg)
    assert auc > 0.95 and right > 0.9
    out = quality.score(edge(spark), model)
    assert out.count() == len(edge_texts()) and out.where("score is null or score < 0 or score > 1").count() == 0
    assert quality.score(empty(spark), model).count() == 0
    assert sorted(map(repr, quality.score(docs.limit(20), quality.train(docs, labels)).collect())) == sorted(map(repr, quality.score(docs.limit(20), model).collect()))


def test_without_labels_scores_are_one_half(spark, tables):
    model = quality.train(tables[0], tables[1].where("false"))
    assert quality.score(edge(spark), model).where("abs(score - 0.5) > 0.05").count() == 0
    chain = toxicity.train(tables[0], tables[1].where("false"))
    assert toxicity.classify(edge(spark), chain).where("rejected").count() in (0, len([t for _, t in edge_texts() if t and t.strip()]))


def test_toxicity_on_held_out_rows_and_in_a_chain(spark, tables):
    docs, labels = tables
    chain = toxicity.train(docs, labels)
    assert [len(m.dense) for m in chain] == [0, 1, 2, 3]  # each model takes the earlier probabilities
    rows = toxicity.classify(docs, chain).select("row.doc_id", "rejected").join(labels, "doc_id").where(held_out(F.col("doc_id"))).select("rejected", "toxic").collect()
    clean, bad = [r.rejected for r in rows if not r.toxic], [r.rejected for r in rows if r.toxic]
    assert sum(clean) / len(clean) < 0.03 and sum(bad) / max(1, len(bad)) > 0.6
    out = toxicity.classify(edge(spark), chain)
    assert out.count() == len(edge_texts()) and out.where("rejected").count() == 0
    kept = toxicity.keep_clean(edge(spark), labels, source=docs)
    assert kept.columns == edge(spark).columns and kept.count() == len(edge_texts())
    assert toxicity.classify(empty(spark), chain).count() == 0


def test_kinds_are_groups_of_telling_words():
    rng = np.random.default_rng(5)
    groups, rows, y, want = [[100, 101, 102], [200, 201], [300, 301, 302]], [], [], []
    for k in range(900):
        plain = rng.choice(90, 20, replace=False)
        toxic = k % 3 == 0
        mine = rng.choice(3, p=[0.5, 0.3, 0.2]) if toxic else -1
        rows.append(np.unique(np.concatenate((plain, rng.choice(groups[mine], 2, replace=False) if toxic else []))).astype(np.int32))
        y.append(float(toxic))
        want.append(mine)
    got = toxicity.kinds(rows, np.array(y))
    assert all((got[k] == (np.arange(3) == want[k])).all() for k in range(900))
    assert not toxicity.kinds(rows, np.zeros(900)).any()


def test_the_chain_against_a_model_alone(spark, tables):
    docs, labels = tables
    chain, alone = (toxicity.measure(toxicity.classify(docs, m), labels).first() for m in (toxicity.train(docs, labels), toxicity.train_alone(docs, labels)))
    assert chain.n == alone.n > 50 and chain.left_alone > 0.97
    assert chain.caught >= alone.caught - 0.1 and chain.log_loss < alone.log_loss + 0.05


def test_planted_toxic_documents_are_caught(spark, tables):
    docs, labels = tables
    chain = toxicity.train(docs, labels)
    planted = spark.createDataFrame([(1, "the and of with idiot the stupid moron of and"), (2, "the and of with this the and of and"), (3, "Worthless, pathetic scum! " + "the and of for " * 300)], "doc_id long, text string")
    assert {r.row.doc_id: r.rejected for r in toxicity.classify(planted, chain).collect()} == {1: True, 2: False, 3: True}
