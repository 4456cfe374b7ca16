from datetime import datetime, timedelta

from pyspark.sql import functions as F

from leakaudit.operators import metrics, tokens
from leakaudit.operators import target as targets
from leakaudit.plans import audit
from leakaudit.streaming import audit as live

START = datetime(2024, 1, 1)


def feed(spark, tmp_path, name, batches, schema):
    """One Parquet file per batch, read one file a trigger."""
    for k, rows in enumerate(batches):
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{tmp_path}/{name}/b{k}")
    return spark.readStream.schema(spark.createDataFrame(batches[0], schema).schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(f"{tmp_path}/{name}")


def drain(df, name, mode, tmp_path):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{tmp_path}/ck-{name}").trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def test_streamed_scores_equal_batch_scores(spark, sf, tmp_path):
    table = audit.token_table(spark, sf, config=audit.Config(slippage=False))
    made = targets.train(table)
    some = spark.read.parquet(f"{sf}/documents.parquet").select(F.col("doc_id").alias("sample_id"), F.lit("en").alias("slice"), "text").limit(30)
    some.repartition(3).write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema(some.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    for _ in range(2):  # the second start replays nothing
        live.score_stream(stream, made, f"{tmp_path}/out", f"{tmp_path}/ck").awaitTermination()
    got = sorted((r.sample_id, round(r.weighted_z, 9)) for r in spark.read.parquet(f"{tmp_path}/out").collect())
    assert got == sorted((r.sample_id, round(r.weighted_z, 9)) for r in live.score_batch(spark.read.parquet(f"{tmp_path}/in"), made).collect())


def test_late_rows_are_kept_or_dropped_at_the_watermark(spark, tmp_path):
    at = lambda m: START + timedelta(minutes=m)
    batches = [[(1, at(600))], [(2, at(1440))], [(3, at(1440 - 59 - 1)), (4, at(-60 * 24))], [(5, at(3000))], [(6, at(6000))]]
    stream = feed(spark, tmp_path, "late", batches, "score double, ts timestamp".replace("score double", "id long")).withColumn("score", F.lit(1.0))
    rows = drain(live.flagged_counts(stream, 0.5), "late_counts", "append", tmp_path).collect()
    by = {r.start: r.n for r in rows}
    # the row an hour and a day before its time comes after its window was closed
    assert by.get(START) == 2 and START - timedelta(days=1) not in by


def test_sessions_equal_the_batch_result(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet").select("user_id", "ts")
    batch = events.groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count(F.lit(1)).alias("n"))
    events.union(events.limit(1).withColumn("ts", F.lit("2030-01-01").cast("timestamp"))).coalesce(1).write.parquet(f"{tmp_path}/ev/a")
    events.limit(1).withColumn("ts", F.lit("2031-01-01").cast("timestamp")).coalesce(1).write.parquet(f"{tmp_path}/ev/b")
    stream = spark.readStream.schema(events.schema).option("recursiveFileLookup", True).parquet(f"{tmp_path}/ev")
    got = drain(live.sessions(stream), "sessions_out", "append", tmp_path).where("start < '2029-01-01'")
    assert got.count() == batch.count() and got.agg(F.sum("n")).first()[0] == events.count()


def test_texts_are_seen_once(spark, tmp_path):
    rows = [[("a", START), ("b", START)], [("a", START + timedelta(minutes=10)), ("c", START)]]
    out = drain(live.fresh(feed(spark, tmp_path, "once", rows, "text string, ts timestamp")), "once_out", "append", tmp_path)
    assert sorted(r.text for r in out.collect()) == ["a", "b", "c"]


def test_labels_meet_their_scores(spark, tmp_path):
    scored = feed(spark, tmp_path, "sc", [[(1, START, 0.9), (2, START, 0.1)]], "sample_id long, ts timestamp, score double")
    labels = feed(spark, tmp_path, "lb", [[(1, START + timedelta(minutes=90), True), (2, START + timedelta(hours=3), False)]], "label_id long, label_ts timestamp, is_member boolean")
    out = drain(live.with_labels(scored, labels), "met", "append", tmp_path).collect()
    assert [(r.sample_id, r.is_member) for r in out] == [(1, True)]


def test_rolling_auc_ends_at_the_batch_value(spark, tmp_path):
    import random

    rng = random.Random(4)
    rows = [(rng.choice("xy"), rng.randrange(64) / 64, rng.random() < 0.5) for _ in range(200)]
    stream = feed(spark, tmp_path, "auc", [rows[:90], rows[90:]], "slice string, score double, is_member boolean")
    out = drain(live.rolling_auc(stream, 64), "auc_out", "update", tmp_path)
    last = {r.slice: r for r in sorted(out.collect(), key=lambda r: r.n_pos + r.n_neg)}
    batch = metrics.auc(spark.createDataFrame(rows, "slice string, score double, is_member boolean").withColumn("method", F.lit("m")), ("slice",)).collect()
    assert {r.slice: (r.n_pos, r.n_neg, r.auc) for r in batch} == {k: (r.n_pos, r.n_neg, r.auc) for k, r in last.items()}


def test_stateless_counts(spark):
    df = spark.createDataFrame([(1, "TODO some words")], "sample_id long, text string")
    assert tuple(live.token_classes(df).first())[:3] == (1, 3, 1)
    assert tokens.CONTEXTS[1] == (1,)


def test_totals_are_written_whole_each_time(spark, tmp_path):
    rows = [[("en", 0.9), ("de", 0.1)], [("en", 0.2)], [("en", 0.8), ("fr", 0.9)]]
    out = drain(live.totals(feed(spark, tmp_path, "totals", rows, "slice string, score double"), 0.5), "totals_out", "complete", tmp_path)
    assert {tuple(r) for r in out.collect()} == {("en", 3, 2), ("de", 1, 0), ("fr", 1, 1)}
