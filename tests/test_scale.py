"""Operators whose paths differ by size, held against plain Python on both paths."""

import random
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from leakaudit import runtime
from leakaudit.operators import around, metrics, probe, splits, target, tokens
from leakaudit.plans import audit


@pytest.mark.parametrize("most", [10_000, 0])
def test_running_sums_by_window_and_by_range(spark, most):
    rng = random.Random(3)
    rows = [(g, k, rng.randint(0, 9), rng.randint(0, 9)) for g in ("a", "b", None) for k in rng.sample(range(1000), 150 if g == "a" else 7)]
    df = spark.createDataFrame(rows, "g string, k long, x long, y long")
    got = runtime.running(df, ["g"], ["k"], ["x", "y"], most=most).collect()
    assert len(got) == len(rows)
    for r in got:
        before = [q for q in rows if q[0] == r.g and q[1] < r.k]
        assert (r.before_x, r.before_y) == (sum(q[2] for q in before), sum(q[3] for q in before))


def test_heavy_contexts_are_joined_like_the_others(spark, sf):
    table = audit.token_table(spark, sf, config=audit.Config(slippage=False))
    layers = (0, 1, 2)
    made = target.train(table, 16, layers)
    assert made.contexts.where(F.col("n_c") >= made.heavy).count() > 1  # layer 0, and frequent words
    assert made.contexts.where(F.col("n_c") >= made.heavy).count() <= len(layers) / target.HEAVY
    rows = lambda m: sorted(repr((r.sample_id, r.pos, r.layer, round(r.logp, 9), round(r.z, 9), round(r.entropy, 9))) for r in target.forward(table, m, layers).collect())
    usual = rows(made)
    assert usual == rows(replace(made, heavy=float("inf"))) == rows(replace(made, heavy=1.0))
    plan = target.forward(table, made, layers)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("BroadcastHashJoin") >= 2


def test_needed_contexts_only_are_counted(spark, sf):
    table = audit.token_table(spark, sf, config=audit.Config(slippage=False))
    asked = table.where("slice = 'de'").select(F.lit(1).alias("layer"), tokens.context(1).alias("ctx"))
    some, whole = target.train(table, 16, (1,), needed=asked), target.train(table, 16, (1,))
    keys = {r.ctx for r in asked.distinct().collect()}
    assert {tuple(r) for r in some.counts.collect()} == {tuple(r) for r in whole.counts.collect() if r.ctx in keys}


def test_items_of_any_length_are_found(spark, monkeypatch):
    rng = random.Random(5)
    words = "ab abc b ca cab d".split()
    docs = [(k, " ".join(rng.choice(words) for _ in range(rng.randint(0, 30)))) for k in range(60)] + [(60, None), (61, "")]
    items = [(k, " ".join(rng.choice(words) for _ in range(n))) for k, n in enumerate([1, 1, 2, 2, 2, 3, 3, 4, 5, 6, 8, 9, 12])]
    items += [(100 + k, docs[k][1][3:40]) for k in range(12)] + [(200, None), (201, ""), (202, docs[7][1]), (203, docs[7][1])]
    left, right = spark.createDataFrame(items, "item_id long, text string"), spark.createDataFrame(docs, "doc_id long, text string")
    want = sorted((i, d) for i, x in items for d, t in docs if x and t and x in t)
    for block in (1000, 3):
        monkeypatch.setattr(around, "SHORT_BLOCK", block)
        assert sorted(tuple(r) for r in around.contains(left, right).collect()) == want
    assert around.contains(left.where("false"), right).count() == 0


def test_balance_takes_the_first_of_both_classes(spark):
    rng = random.Random(2)
    rows = [(k, rng.choice("xy"), rng.choice("mn"), rng.random() < 0.3, f"{rng.randint(0, 40):02d}") for k in range(200)]
    df = spark.createDataFrame(rows, "sample_id long, slice string, role string, is_member boolean, content_key string")
    for n in (None, 5):
        want = set()
        for s in "xy":
            for r in "mn":
                sides = [sorted((x[4], x[0]) for x in rows if x[1] == s and x[2] == r and x[3] == side) for side in (True, False)]
                least = min(map(len, sides)) if n is None else min(n, *map(len, sides))
                want |= {k for side in sides for _, k in side[:least]}
        assert {r.sample_id for r in splits.balance(df, n=n).collect()} == want


def test_lines_are_shared_by_no_two_sides(spark):
    line = lambda k: f"a line of more than forty characters, number {k:05d}"
    rows = [(k, "x", "\n".join([line(k), line(1000 + k // 3)]), "s", f"{k}") for k in range(60)] + [(99, "x", "short\nshort", "s", "99")]
    df = spark.createDataFrame(rows, "sample_id long, slice string, text string, role string, content_key string")
    grouped = splits.line_groups(df)
    assert grouped.select("group").distinct().count() == 21
    apart = splits.assign_grouped(grouped)
    assert splits.line_overlap(apart.where("role = 'holdout'"), apart.where("role = 'shadow'")).count() == 0


def test_shadow_samples_are_random_and_bounded(spark):
    rows = spark.range(4000).select(F.col("id").alias("sample_id"), F.when(F.col("id") % 2 == 0, "shadow").otherwise("holdout").alias("role"))
    some = probe.shadow_sample(rows, 0.25, 7)
    counts = {r.role: r["count"] for r in some.groupBy("role").count().collect()}
    assert counts["holdout"] == 2000 and 400 < counts["shadow"] < 600
    assert some.exceptAll(probe.shadow_sample(rows, 0.25, 7)).count() == 0 and probe.shadow_sample(rows).count() == 4000
    pooled = spark.range(600).select(
        F.col("id").alias("sample_id"), F.lit("x").alias("slice"), (F.col("id") % 2 == 0).alias("is_member"), F.when(F.col("id") < 400, "shadow").otherwise("holdout").alias("role"), F.lit(0).alias("layer"),
        F.array((F.col("id") % 2).cast("double"), F.rand(1)).alias("features"))
    probs = probe.train_probes(pooled, "linear", most=60)
    assert probs.count() == 600 and metrics.auc(probs.withColumn("method", F.lit("p")).withColumn("score", F.col("prob"))).first().auc > 0.95
    stacked = probe.stack(pooled, pooled.select("sample_id", F.rand(2).alias("score")))
    assert stacked.count() == 600 and len(stacked.first().features) == 3


def test_a_cluster_without_a_shared_folder_is_an_error(monkeypatch):
    class Context:
        master = "spark://host:7077"

        def getCheckpointDir(self):
            return None

    class Session:
        sparkContext = Context()

        class conf:  # noqa: N801
            @staticmethod
            def get(key, default=None):
                return default

    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        runtime.shared_dir(Session())


def test_batch_bounds_of_overlapping_blocks_end_with_the_last(spark):
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    one, two = runtime.batch_rows(spark, 500), runtime.batch_rows(spark, 200)
    one.__enter__()
    two.__enter__()
    one.__exit__(None, None, None)
    assert spark.conf.get(key) == "200"
    two.__exit__(None, None, None)
    assert spark.conf.get(key) == before


def test_costs_count_rows_passes_and_shuffled_bytes(spark):
    from leakaudit.operators import costs

    df = spark.range(20_000).withColumn("k", F.col("id") % 5000)
    rows = {r.stage: r for r in costs.timed({"first": lambda: df, "sum": lambda: df.groupBy("k").count(), "plain": lambda: df}, {"sum": 3}).collect()}
    assert (rows["first"].rows, rows["sum"].rows) == (20_000, 5000) and rows["sum"].passes == 3 and rows["plain"].passes == 1
    assert rows["sum"].shuffle_bytes > 1000 and rows["plain"].shuffle_bytes == 0
