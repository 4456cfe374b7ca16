import random

from pyspark.sql import functions as F

from leakaudit.operators import around, components, metrics, splits
from leakaudit.sources import catalog


def scored(spark, rows, method="m"):
    return spark.createDataFrame([(k, "x", m, method, float(s)) for k, (m, s) in enumerate(rows)], "sample_id long, slice string, is_member boolean, method string, score double")


def brute(rows):
    pos, neg = [s for m, s in rows if m], [s for m, s in rows if not m]
    return sum((p > q) + (p == q) / 2 for p in pos for q in neg) / len(pos) / len(neg)


def test_auc_small_ties_and_missing_class(spark):
    assert metrics.auc(scored(spark, [(True, 0.9), (True, 0.6), (True, 0.6), (False, 0.6), (False, 0.2)])).first().auc == round(5 / 6, 6)
    assert metrics.auc(scored(spark, [(True, 1), (False, 1), (False, 1)])).first().auc == 0.5
    assert metrics.auc(scored(spark, [(True, 1), (True, 2)])).first().auc is None
    assert metrics.auc(scored(spark, [(True, 1)]).where("false")).count() == 0


def test_auc_equals_all_pairs_and_its_invariances(spark):
    rng = random.Random(3)
    rows = [(rng.random() < 0.4, round(rng.gauss(0, 1), 1)) for _ in range(300)]
    df = scored(spark, rows)
    want = round(brute(rows), 6)
    assert metrics.auc(df).first().auc == want
    assert metrics.auc(df.withColumn("score", F.exp("score"))).first().auc == want
    assert abs(metrics.auc(df.withColumn("is_member", ~F.col("is_member"))).first().auc - (1 - want)) < 2e-6
    assert metrics.auc(df.union(df)).first().auc == want
    assert metrics.auc(df.repartition(7)).first().auc == want
    b = metrics.auc(df, how="binned", bins=16).first()
    assert abs(b.auc - want) <= b.error + 1e-6
    low, high = (lambda r: (r.low, r.high))(metrics.bootstrap(df, 60).first())
    assert low < want < high and high - low < 0.3


def test_roc_and_operating_points(spark):
    rows = [(True, 4), (True, 3), (False, 2), (True, 1), (False, 0)]
    points = sorted((r.threshold, r.fpr, r.tpr) for r in metrics.roc(scored(spark, rows)).collect())
    assert points[-1] == (4.0, 0.0, 1 / 3) and points[0] == (0.0, 1.0, 1.0)
    assert metrics.tpr_at_fpr(scored(spark, rows), 0.0).first().tpr == round(2 / 3, 6)
    best = metrics.best_accuracy(scored(spark, rows)).first()
    assert (best.threshold, best.accuracy) == (3.0, 0.8)
    many = scored(spark, [(k % 2 == 0, k) for k in range(100)])
    assert metrics.roc(many, max_points=10).count() == 10


def test_library_evaluator_agrees(spark):
    from pyspark.ml.evaluation import BinaryClassificationEvaluator

    rng = random.Random(5)
    df = scored(spark, [(rng.random() < 0.5, rng.random() + 0.2 * (k % 2)) for k in range(200)])
    theirs = BinaryClassificationEvaluator(rawPredictionCol="score", labelCol="y", numBins=0).evaluate(df.withColumn("y", F.col("is_member").cast("double")))
    assert abs(theirs - metrics.auc(df).first().auc) < 1e-5


def test_splits_are_balanced_and_apart(spark, sf):
    every = catalog.samples(spark, sf, unique=False)
    assert splits.overlap(every.where("is_member"), every.where("not is_member")).count() == 0
    rows = splits.balance(catalog.samples(spark, sf)).groupBy("slice", "role").agg(F.sum(F.col("is_member").cast("int")).alias("m"), F.count(F.lit(1)).alias("n")).collect()
    assert rows and all(2 * r.m == r.n for r in rows)
    assert splits.balance(catalog.samples(spark, sf), n=2).groupBy("slice", "role").count().where("count > 4").count() == 0


def test_near_copies_miss_no_pair_and_stay_on_one_side(spark):
    rng = random.Random(2)
    words = [f"w{k}" for k in range(200)]
    texts = []
    for _ in range(12):
        base = [rng.choice(words) for _ in range(rng.randint(30, 60))]
        texts.append(base)
        for _ in range(3):
            copy = list(base)
            for _ in range(rng.randint(0, 3)):
                copy[rng.randrange(len(copy))] = rng.choice(words)
            texts.append(copy)
    texts += [["too", "short"], []]
    df = spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate(texts)], "sample_id long, text string")
    sets = [{" ".join(t[i : i + 5]) for i in range(len(t) - 4)} for t in texts]
    near = {(a, b) for a in range(len(texts)) for b in range(a + 1, len(texts)) if sets[a] and sets[b] and len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= 0.8}
    pairs = splits.near_copies(df)
    groups = {r.sample_id: r.group for r in splits.isolate(df, pairs).collect()}
    parent = list(range(len(texts)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in near:
        x, y = sorted((root(a), root(b)))
        parent[y] = x
    assert near and groups == {k: root(k) for k in range(len(texts))}
    assert splits.assign_grouped(splits.isolate(df, pairs)).groupBy("group").agg(F.count_distinct("is_member", "role").alias("n")).where("n > 1").count() == 0


def test_components_of_chains_stars_and_loops(spark):
    edges = [(k, k + 1) for k in range(40)] + [(100, k) for k in range(101, 140)] + [(200, 200), (None, 5)]
    rows = components.connected_components(spark.createDataFrame(edges, "a long, b long")).collect()
    by = {}
    for r in rows:
        by.setdefault(r.component, set()).add(r.node)
    assert sorted(map(len, by.values())) == [1, 40, 41] and {200} in by.values()
    assert components.connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_as_of_before_and_after_all_targets(spark):
    events = spark.sql("SELECT * FROM VALUES (1, TIMESTAMP '2024-01-01 00:00:00'), (2, TIMESTAMP '2024-01-02 10:00:00'), (3, TIMESTAMP '2024-01-02 10:00:01'), (4, TIMESTAMP '2024-02-01 00:00:00') AS t(event_id, ts)")
    registry = spark.sql("SELECT * FROM VALUES ('a', TIMESTAMP '2024-01-02 10:00:00'), ('b', TIMESTAMP '2024-01-03 00:00:00') AS t(target_id, trained_at)")
    assert {r.event_id: r.target_id for r in around.as_of(events, registry).collect()} == {1: None, 2: "a", 3: "a", 4: "b"}


def test_readers_and_writers(spark, tmp_path):
    df = spark.createDataFrame([(1, "a", "x"), (2, "b", "y")], "sample_id long, slice string, text string")
    for fmt in ("parquet", "orc", "json", "csv"):
        catalog.write(df, f"{tmp_path}/{fmt}", fmt=fmt)
        back = catalog.read(spark, f"{tmp_path}/{fmt}", fmt, "sample_id long, slice string, text string")
        assert sorted(map(tuple, back.collect())) == [(1, "a", "x"), (2, "b", "y")]
    catalog.write(df, f"{tmp_path}/parts", ["slice"])
    catalog.write(df.where("slice = 'a'").withColumn("text", F.lit("new")), f"{tmp_path}/parts", ["slice"])
    assert {r.slice: r.text for r in catalog.read(spark, f"{tmp_path}/parts").collect()} == {"a": "new", "b": "y"}
    (tmp_path / "src").mkdir()
    (tmp_path / "src" / "m.py").write_text("x = 1\n")
    (tmp_path / "src" / "n.txt").write_text("no")
    assert [(r.slice, r.text) for r in catalog.code_files(spark, f"{tmp_path}/src").collect()] == [("python", "x = 1\n")]


def test_near_copies_deal_out_digests_not_whole_sets(spark):
    """Grouping by whole shingle sets took five times the texts on disk."""
    words = [f"w{k}" for k in range(400)]
    texts = [" ".join(words), " ".join(words), " ".join([*words[:395], "x"]), " ".join(words[:300]), "a b c d e", "a b c d e f", "a b"]
    df = spark.createDataFrame(list(enumerate(texts)), "sample_id long, text string")
    pairs = splits.near_copies(df)
    assert sorted((r.a, r.b, round(r.jaccard, 4)) for r in pairs.collect()) == [(0, 1, 1.0), (0, 2, round(391 / 397, 4))]
    plan = pairs._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate [hashes" not in plan


def test_groups_of_near_copies_do_not_list_all_pairs(spark, monkeypatch):
    """Sixty near copies, and sixty other texts that share their first lines: rare shingles come first, and a group's members needn't all be compared."""
    rng = random.Random(5)
    drawn = lambda n: [f"w{rng.randrange(10**6)}" for _ in range(n)]
    base, shared = drawn(120), drawn(20)
    near = [[*base[: (at := rng.randrange(120))], f"x{k}", *base[at + 1 :]] for k in range(60)]
    texts = near + [[*shared, *drawn(40)] for _ in range(60)]
    df = spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate(texts)], "sample_id long, text string")
    asked, write = [], splits.materialise

    def spied(table, tag="t", *more):
        made = write(table, tag, *more)
        if tag in ("met", "asked"):
            asked.append((tag, made.select("sample_id").where("sample_id >= 60").distinct().count()))
        return made

    monkeypatch.setattr(splits, "materialise", spied)
    pairs = splits.near_copies(df, linked=True)
    assert set(asked) == {("met", 0), ("asked", 0)}  # of the texts that share lines alone, none is compared
    every = splits.near_copies(df)
    grouped = lambda p: {r.sample_id: r.group for r in splits.isolate(df, p).collect()}
    assert grouped(pairs) == grouped(every) and 2 * pairs.count() < every.count()
    sets = [{" ".join(t[i : i + 5]) for i in range(len(t) - 4)} for t in texts]
    want = {(a, b) for a in range(120) for b in range(a + 1, 120) if len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= 0.8}
    assert {(r.a, r.b) for r in every.collect()} == want and {(r.a, r.b) for r in pairs.collect()} <= want
