import random

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from leakaudit.llm import exact, simhash
from leakaudit.llm.queries import ORACLES, QUERIES
from tests.llm.test_dedup import brute_fingerprint, brute_groups, normal

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    docs, out = spark.read.parquet(f"{SF}/documents.parquet"), []
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        path = str(tmp_path_factory.mktemp("stage") / name)
        stage(spark, docs, SF).write.parquet(path)
        docs = spark.read.parquet(path)
        out.append(docs)
    return out


def test_each_stage_does_its_work_on_what_came_before(spark, stages):
    first = spark.read.parquet(f"{SF}/documents.parquet")
    clean, single, apart, mixed, last = stages
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "exact_dedup", "near_dedup", "mix", "bpe"]
    assert all(s.columns == first.columns for s in stages[:4])
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    gone = first.join(clean, "doc_id", "left_anti").join(labels, "doc_id", "left")
    assert 0 < gone.count() < 0.2 * first.count() and gone.where("toxic = 0").count() <= 1
    rows = [(r.doc_id, r.text) for r in clean.collect()]
    keep = {}
    for k, t in rows:
        best = keep.get(normal(t))
        keep[normal(t)] = (k, t) if best is None or (-len(t), k) < (-len(best[1]), best[0]) else best
    assert sorted(r.doc_id for r in single.collect()) == sorted(k for k, _ in keep.values())
    fps = [(r.doc_id, brute_fingerprint(r.text)) for r in single.collect()]
    assert sorted(r.doc_id for r in apart.collect()) == sorted(set(brute_groups(fps, 4).values()))
    assert mixed.count() > apart.count() and mixed.join(apart, "doc_id", "left_anti").count() == 0
    assert mixed.groupBy("doc_id").count().where("count > 2").count() == 0
    assert last.count() == mixed.count() and last.where("n_tokens > 0").count() == last.count()


def test_run_gives_what_the_stages_give(spark, stages):
    got = corpus_pipeline.run(spark, SF)
    assert sorted(map(repr, got.collect())) == sorted(map(repr, stages[-1].collect()))


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_operators_equal_their_sql(spark, name):
    duckdb = pytest.importorskip("duckdb")
    c = duckdb.connect()
    c.sql(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    cursor = c.execute(ORACLES[name])
    columns = [x[0] for x in cursor.description]
    want = sorted(repr([r[columns.index(x)] for x in sorted(columns)]) for r in cursor.fetchall())
    got = QUERIES[name](spark, SF)
    assert sorted(got.columns) == sorted(columns) and sorted(repr([r[x] for x in sorted(columns)]) for r in got.collect()) == want


def test_ten_operators_are_registered():
    assert [k.split("_")[0] for k in QUERIES] == [f"op{n}" for n in range(1, 11)]


def test_copies_fall_to_one_and_others_stay(spark):
    base = " ".join(f"word{k}" for k in range(300))
    rows = [(k, base if k < 40 else base.replace("word7 ", f"other{k} ", 1) if k < 45 else f"text number {k} " + " ".join(f"x{k}y{j}" for j in range(80))) for k in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    once = exact.deduplicate(df)
    assert once.where("doc_id < 40").count() == 1 and once.count() == 21
    left = simhash.keep_one(once)
    assert left.where("doc_id >= 45").count() == 15 and left.count() < 21 and left.where(F.col("doc_id") == 0).count() == 1


def test_recall_of_near_copies_is_what_the_readme_says():
    rng, found = random.Random(3), {}
    for _ in range(1500):
        words = [b"w%d" % rng.randrange(5000) for _ in range(300)]
        other = list(words)
        for i in rng.sample(range(300), rng.randrange(1, 14)):
            other[i] = b"x%d" % rng.randrange(10**6)
        a, b = ({tuple(x[i : i + 5]) for i in range(296)} for x in (words, other))
        near = (simhash.fingerprint(words) ^ simhash.fingerprint(other)).bit_count() <= simhash.MOST_BITS
        found.setdefault(min(int(20 * len(a & b) / len(a | b)), 19), []).append(near)
    rate = {k: sum(v) / len(v) for k, v in found.items()}
    assert [round(rate[k], 2) for k in (16, 17, 18, 19)] == pytest.approx([0.08, 0.22, 0.43, 0.74], abs=0.05)
