import hashlib
import math

import pytest
from pyspark.sql import functions as F

from leakaudit.llm import mixing, multiset
from tests.llm.common import edge, edge_texts, empty


def brute_targets(sizes, weights=(5, 2, 1), share=1.5, most=2):
    names = sorted((n for n in sizes if n is not None)) + ([None] if None in sizes else [])
    w = {n: weights[k % len(weights)] for k, n in enumerate(names)}
    left, free, out = share * sum(sizes.values()), set(names), {}
    while free:
        each = {n: left * w[n] / sum(w[x] for x in free) for n in free}
        over = [n for n in free if each[n] > most * sizes[n]]
        if not over:
            return out | each
        for n in over:
            out[n] = most * sizes[n]
            left -= out[n]
            free.discard(n)
    return out


def test_mix_meets_its_targets(spark):
    df = edge(spark)
    rows = mixing.mix(df).collect()
    count = lambda t: len((t or "").replace("\x0b", " ").split())
    assert sorted(r.size for r in rows) == sorted(count(t) for _, t in edge_texts())
    sizes, taken = {}, {}
    for r in rows:
        got = sum(d.words for d in r.draws)
        assert 0 <= got <= 2 * r.size and len({d.epoch for d in r.draws}) == len(r.draws)
        sizes[r.row.source] = sizes.get(r.row.source, 0) + r.size
        taken[r.row.source] = taken.get(r.row.source, 0) + got
    want = brute_targets(sizes)
    assert all(abs(taken[s] - want[s]) <= 1 for s in sizes)
    again = mixing.mix(df).collect()
    assert sorted(map(repr, rows)) == sorted(map(repr, again))
    assert mixing.mix(empty(spark)).count() == 0


def test_mixed_rows_repeat_what_is_drawn(spark):
    df = edge(spark)
    out = mixing.mixed_rows(df)
    assert out.select("row.*").columns == df.columns
    draws = mixing.mix(df).select(F.sum(F.size("draws"))).first()[0]
    assert out.count() == draws and mixing.mixed_rows(empty(spark)).count() == 0


def test_targets_share_by_weight_and_cap(spark):
    for sizes in ({"a": 10, "b": 1000, "c": 1000, None: 400}, {"a": 5}, {"a": 0, "b": 0}, {"a": 0, "b": 10}, {"x": 100, "y": 100, "z": 100, "zz": 100}):
        df = spark.createDataFrame([(k, n, s) for k, (n, s) in enumerate(sizes.items())], "doc_id long, source string, size long")
        got = {r.source: r.target for r in mixing.targets(df).collect()}
        want = brute_targets(sizes) if sum(sizes.values()) else dict.fromkeys(sizes, 0)
        assert got == pytest.approx(want)


def test_splitting_tree_deals_every_position_once(spark):
    quotas = {0: 1000, 1: 37, 2: 0, 3: 5000}
    df = spark.createDataFrame(list(quotas.items()), "idx int, quota long")
    for shards in (1, 3, 16):
        rows = mixing.splitting_tree(df, shards, 5).collect()
        assert sorted(map(repr, rows)) == sorted(map(repr, mixing.splitting_tree(df, shards, 5).collect()))
        for idx, q in quotas.items():
            mine = sorted((r.shard, r.first, r.n) for r in rows if r.idx == idx)
            assert sum(n for _, _, n in mine) == q and [f for _, f, _ in mine] == [sum(n for _, _, n in mine[:k]) for k in range(len(mine))]
        sizes = [sum(r.n for r in rows if r.shard == s) for s in range(shards)]
        assert sum(sizes) == sum(quotas.values()) and max(sizes) - min(sizes) <= 2


def test_draws_follow_the_hypergeometric_law(spark):
    total, marked, drawn, n = 20, 8, 7, 6000
    draw = mixing.hypergeometric(F.lit(float(total)), F.lit(float(marked)), F.lit(float(drawn)), (F.pmod(F.xxhash64("id"), F.lit(1 << 40)) + 0.5) / float(1 << 40))
    found = {int(r.x): r.n for r in spark.range(n).select(draw.alias("x")).groupBy("x").agg(F.count(F.lit(1)).alias("n")).collect()}
    for k in range(0, 8):
        p = math.comb(marked, k) * math.comb(total - marked, drawn - k) / math.comb(total, drawn)
        assert abs(found.get(k, 0) / n - p) < 4 * math.sqrt(p * (1 - p) / n) + 1e-3
    assert spark.range(1).select(mixing.hypergeometric(F.lit(1e6), F.lit(4e5), F.lit(5e5), F.lit(0.5))).first()[0] == pytest.approx(2e5, abs=2)


def test_edited_texts_and_likeness(spark):
    df = edge(spark).where("doc_id is not null").dropDuplicates(["doc_id"])
    got = {r.doc_id: r for r in multiset.edited(df).withColumn("a", multiset.likeness(F.col("lanes"), F.col("edited_lanes"))).withColumn("b", multiset.likeness(F.col("lanes"), F.col("next_lanes"))).collect()}
    texts = sorted({k: t or "" for k, t in edge_texts() if k is not None}.items())
    for i, (k, t) in enumerate(texts):
        half, following = len(t) // 2, texts[(i + 1) % len(texts)][1]
        assert got[k].n_chars == len(t)
        assert got[k].edited_sha256 == hashlib.sha256((t[: len(t) - half] + following[:half]).encode()).hexdigest()
        assert 0 <= got[k].a <= 1 and 0 <= got[k].b <= 1
    assert got[5].b == 1.0 and got[-5].a > 0.4 > got[-5].b  # equal texts, then a half against an empty one


def test_every_row_has_its_edit_whatever_its_id(spark):
    assert multiset.edited(edge(spark)).count() == len(edge_texts())
    assert multiset.edited(empty(spark)).count() == 0
    one = spark.createDataFrame([(1, "abcdef")], "doc_id long, text string")
    assert multiset.edited(one).first().edited_sha256 == hashlib.sha256(b"abcabc").hexdigest()


def test_hashes_ignore_order_and_add_and_subtract(spark):
    df = spark.createDataFrame([(1, "one.\ntwo.\nthree."), (2, "three.\none.\ntwo."), (3, "one."), (4, "two.\nthree."), (5, "one.\ntwo.")], "doc_id long, text string")
    h = multiset.fingerprints(df)
    by = {r.doc_id: r.fingerprint for r in h.collect()}
    assert by[1] == by[2] and len(set(by.values())) == 4
    part = h.where("doc_id = 3").select(F.col("lanes").alias("a")).crossJoin(h.where("doc_id = 4").select(F.col("lanes").alias("b"))).crossJoin(h.where("doc_id = 1").select(F.col("lanes").alias("c")))
    assert part.select(multiset.as_hex(multiset.combine(F.col("a"), F.col("b")))).first()[0] == by[1]
    assert part.select(multiset.as_hex(multiset.remove(F.col("c"), F.col("b")))).first()[0] == by[3]
