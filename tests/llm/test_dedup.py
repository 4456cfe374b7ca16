import hashlib
import random
from collections import defaultdict

import numpy as np
import xxhash
from pyspark.sql import functions as F

from leakaudit.llm import exact, simhash
from tests.llm.common import edge, edge_texts, empty


def normal(text):
    return (text or "").translate({ord(c): None for c in " \t\n\x0b\x0c\r"})


def test_exact_members_equal_brute_force(spark):
    got = exact.members(edge(spark)).collect()
    groups = defaultdict(list)
    for k, t in edge_texts():
        groups[normal(t)].append((k, t or ""))
    keep = {n: sorted(g, key=lambda x: (-len(x[1]), x[0] is None, x[0] or 0))[0] for n, g in groups.items()}
    want = sorted(repr((k, keep[normal(t)][0], len(groups[normal(t)]), (k, len(t or "")) == (keep[normal(t)][0], len(keep[normal(t)][1])), hashlib.sha256(normal(t).encode()).hexdigest())) for k, t in edge_texts())
    assert sorted(repr(tuple(r)) for r in got) == want
    assert exact.members(empty(spark)).count() == 0


def test_deduplicate_keeps_one_row_of_each_group_with_all_columns(spark):
    df = edge(spark)
    out = exact.deduplicate(df)
    assert out.columns == df.columns
    assert sorted(normal(r.text) for r in out.collect()) == sorted({normal(t) for _, t in edge_texts()})
    assert exact.deduplicate(empty(spark)).count() == 0


def test_a_hot_group_is_spread_and_counted(spark):
    df = spark.range(3000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, F.lit("hot text")).otherwise(F.concat(F.lit("t "), F.col("id"))).alias("text"))
    hot = exact.members(df).where("group_size > 1")
    assert hot.count() == 1000 and hot.where("keep_id = 0 and group_size = 1000").count() == 1000 and hot.where("kept").count() == 1


def brute_fingerprint(text, shingle=4):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    parts = [b" ".join(words[i : i + shingle]) for i in range(max(1, len(words) - shingle + 1))]
    hashes = [xxhash.xxh64_intdigest(p, seed=42) for p in parts]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_groups(fps, bits):
    """fps: (doc_id, fingerprint) -> smallest reachable doc_id of each fingerprint."""
    distinct = sorted({f for _, f in fps})
    parent = {f: f for f in distinct}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, a in enumerate(distinct):
        for b in distinct[i + 1 :]:
            if (a ^ b).bit_count() <= bits:
                parent[root(b)] = root(a)
    low = {}
    for k, f in fps:
        if k is not None:
            low[root(f)] = min(k, low.get(root(f), k))
    return {f: low.get(root(f)) for f in distinct}


def test_simhash_groups_equal_brute_force(spark):
    got = simhash.near_groups(edge(spark)).collect()
    fps = [(k, brute_fingerprint(t)) for k, t in edge_texts()]
    groups = brute_groups(fps, 4)
    assert sorted(repr((k, f, groups[f])) for k, f in fps) == sorted(repr((r.doc_id, r.fp % 2**64, r.component_id)) for r in got)
    assert simhash.near_groups(empty(spark)).count() == 0
    df = edge(spark)
    out = simhash.keep_one(df)
    first = {groups[f]: None for _, f in fps}
    assert out.columns == df.columns and sorted(repr(r.doc_id) for r in out.collect()) == sorted(map(repr, first))


def test_one_row_of_each_group_stays(spark):
    unlike = [" ".join(f"{w}{k}" for k in range(60)) for w in ("alpha", "beta", "gamma", "delta", "epsilon", "zeta")]
    texts = [(5, unlike[0]), (5, unlike[1]), (6, unlike[2]), (None, unlike[3]), (None, unlike[4])]
    extra = [(7, unlike[0]), (5, unlike[0]), (None, unlike[3]), (8, unlike[3] + " "), (9, unlike[5]), (9, unlike[5].upper()), (3, None), (2, "")]
    rows = lambda t: spark.createDataFrame([(k, x, n) for n, (k, x) in enumerate(t)], "doc_id long, text string, key int")
    assert simhash.keep_one(rows(texts)).count() == 5
    df = rows(texts + extra)
    got = simhash.keep_one(df)
    kept = sorted((str(r.doc_id), (r.text or "").strip().lower()) for r in got.collect())
    assert got.columns == df.columns
    assert kept == sorted([("5", unlike[0]), ("5", unlike[1]), ("6", unlike[2]), ("8", unlike[3]), ("None", unlike[4]), ("9", unlike[5]), ("2", "")])


def test_links_of_dense_and_random_fingerprints_in_chunks(spark):
    rng = random.Random(1)
    base = [rng.getrandbits(64) for _ in range(40)]
    fps = set(base)
    for _ in range(700):  # one dense cloud, and copies of others with one to six bits flipped
        x = base[0] if rng.random() < 0.6 else rng.choice(base)
        for b in rng.sample(range(64), rng.randint(1, 6)):
            x ^= 1 << b
        fps.add(x)
    df = spark.createDataFrame([(int(np.uint64(f).view(np.int64)),) for f in sorted(fps)], "fp long")
    pairs = [(k, f) for k, f in enumerate(sorted(fps))]
    want = brute_groups(pairs, 4)
    for chunk in (4096, 40):  # 40: the cloud's buckets are dealt into chunks, pair by pair
        parent = {f: f for f in fps}

        def root(x, parent=parent):
            while parent[x] != x:
                x = parent[x]
            return x

        for r in simhash.edges(df, chunk=chunk).collect():
            parent[root(r.b % 2**64)] = root(r.a % 2**64)
        low = {}
        for k, f in pairs:
            low[root(f)] = min(k, low.get(root(f), k))
        assert {f: low[root(f)] for f in fps} == want


def test_a_segment_differs_by_at_most_one_bit():
    rng = random.Random(7)
    for _ in range(300):
        bits = rng.sample(range(64), 4)
        assert min(sum(low <= b < low + n for b in bits) for low, n in simhash.SEGMENTS) <= 1
    assert sum(n for _, n in simhash.SEGMENTS) == 64
