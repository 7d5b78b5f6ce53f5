import math
import random

import numpy as np
import pytest

from motifjoin.llm import queries, topk


def brute(rows, every, k=5):
    q = {}
    vecs = [(i, [math.floor(256 * float(x)) for x in v]) for i, v in rows if i is not None and v and all(x is not None and math.isfinite(x) for x in v)]
    for i, v in vecs:
        if i % every == 0:
            scores = sorted(((-sum(a * b for a, b in zip(v, w)), j) for j, w in vecs if j != i))[:k]
            q[i] = [(r + 1, j, -s) for r, (s, j) in enumerate(scores)]
    return q


def got(df):
    out = {}
    for r in df.collect():
        out.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    return {k: sorted(v) for k, v in out.items()}


def test_query_equals_brute_force(spark, sf):
    rows = [(r.vec_id, r.embedding) for r in spark.read.parquet(f"{sf}/embeddings.parquet").collect()]
    assert got(queries.op10_exact_top_k(spark, sf)) == brute(rows, 50)


def test_ties_nulls_padding_and_many_shards(spark, monkeypatch):
    monkeypatch.setattr(topk, "SHARD_ROWS", 7)
    monkeypatch.setattr(topk, "BLOCK_ROWS", 3)
    rng = random.Random(3)
    rows = [(i, [rng.choice([-0.5, 0.25, 0.26, -0.1]) for _ in range(3)]) for i in range(60)]
    rows += [(100, None), (110, []), (120, [None, 1.0]), (130, [float("nan"), 1.0]), (140, [float("inf"), 0.0]), (150, [0.5]), (None, [1.0, 1.0]), (160, [0.0, 0.0, 0.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").selectExpr("*", "0 as score", "1 as q")
    f32 = [(i, None if v is None else [None if x is None else float(np.float32(x)) for x in v]) for i, v in rows]
    f32 = [(i, None if v is None else v + [0.0] * (4 - len(v)) if v else v) for i, v in f32]
    assert got(topk.top_k(df.filter("vec_id % 10 = 0"), df, 5)) == brute(f32, 10)


def test_few_or_no_candidates(spark):
    one = spark.createDataFrame([(0, [1.0]), (1, [2.0])], "vec_id long, embedding array<float>")
    assert got(topk.top_k(one.filter("vec_id = 0"), one, 5)) == {0: [(1, 1, 256 * 512)]}
    assert topk.top_k(one.limit(0), one.limit(0), 5).count() == 0


def shard_of(m, kind=np.float64):
    order = topk.grouped(m.astype(float), topk.BLOCK_VECTORS)
    return topk.Shard(np.arange(len(m))[order], m[order], m.shape[1], kind)


def direct(m, q, own, k):
    return [[(j, s) for s, j in sorted((-sum(int(a) * int(b) for a, b in zip(x, y)), j) for j, y in enumerate(m) if j != o)[:k]] for x, o in zip(q, own)]


@pytest.mark.parametrize("kind", [np.float64, object])
@pytest.mark.parametrize("share", [1.0, 0.05])
def test_max_score_equals_direct_products(kind, share):
    rng = np.random.default_rng(4)
    m = rng.integers(-40, 40, (300, 20)) * (rng.random((300, 20)) < share)
    m[50:60] = m[40]  # ties
    q, own = m[:25], np.arange(25)
    shard = shard_of(m, kind)
    assert (shard.lists is None) == (share == 1.0)
    got_ = topk.max_score(q, own, shard, 5, np.full(25, -np.inf))
    assert [[(int(i), -int(s)) for i, s in zip(*x)] for x in got_] == direct(m, q, own, 5)
    floors = np.array([float(-want[4][1]) for want in direct(m, q, own, 5)])  # the k-th best is known: ties with it stay
    got_ = topk.max_score(q, own, shard, 5, floors)
    assert [[(int(i), -int(s)) for i, s in zip(*x)] for x in got_] == direct(m, q, own, 5)


@pytest.mark.parametrize("spread,most", [(0.3, 0.05), (1.5, 0.6)])
def test_clustered_vectors_are_pruned(spread, most):
    rng = np.random.default_rng(2)
    centres = rng.normal(size=(50, 64))
    x = centres[rng.integers(0, 50, 8000)] + spread * rng.normal(size=(8000, 64))
    m = np.floor(256 * x / np.linalg.norm(x, axis=1, keepdims=True)).astype(np.int64)
    counts, q = topk.Counts(), m[::200]
    found = topk.max_score(q, np.arange(0, 8000, 200), shard_of(m), 5, np.full(len(q), -np.inf), counts)
    full = (m @ q.T).T
    for i, (ids, s) in enumerate(found):
        full[i, 200 * i] = -(10**9)
        assert sorted(s.tolist(), reverse=True) == sorted(np.sort(full[i])[-5:].tolist(), reverse=True)
    assert counts.completed <= most * counts.pairs and counts.competitive <= counts.near <= counts.pairs


def test_given_vectors_are_pruned(spark, sf):
    rows = spark.read.parquet(f"{sf.replace('0.001', '0.1')}/embeddings.parquet").collect()
    m = np.floor(256 * np.array([[float(x) for x in r.embedding] for r in rows])).astype(np.int64)
    counts, at = topk.Counts(), np.arange(0, len(m), 50)
    topk.max_score(m[at], at, shard_of(m), 5, np.full(len(at), -np.inf), counts)
    print(f"of {counts.pairs} pairs {counts.near / counts.pairs:.3f} in blocks that reach the threshold, {counts.competitive / counts.pairs:.3f} competitive after the essential terms, {counts.completed / counts.pairs:.3f} completed")
    assert counts.completed < 0.2 * counts.pairs


def test_large_components_are_exact(spark):
    rows = [(0, [1e6, 3.0]), (1, [2e6, -1.0]), (2, [2e6, -1.0 - 2**-8]), (3, [-5e6, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    assert got(topk.top_k(df, df, 2)) == {k: v[:2] for k, v in brute(rows, 1).items()}
    with pytest.raises(Exception, match="64 bits"):
        topk.top_k(df, df.selectExpr("vec_id", "transform(embedding, x -> x * 1e12D) as embedding"), 1).collect()


def test_queries_that_share_an_id(spark):
    df = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.0, 1.0]), (3, [1.0, 1.0])], "vec_id long, embedding array<float>")
    q = spark.createDataFrame([(9, [1.0, 0.0]), (9, [1.0, 0.0]), (9, [0.0, 1.0])], "vec_id long, embedding array<float>")
    rows = sorted((r.query_id, r["rank"], r.vec_id) for r in topk.top_k(q, df, 2).collect())
    assert rows == [(9, 1, 1), (9, 1, 2), (9, 2, 3), (9, 2, 3)]


def test_copies_of_query_blocks_are_not_broadcast(spark, monkeypatch):
    monkeypatch.setattr(topk, "SHARD_ROWS", 10)
    df = spark.createDataFrame([(i, [float(i % 7), 0.5]) for i in range(200)], "vec_id long, embedding array<float>")
    out = topk.top_k(df.filter("vec_id % 50 = 0"), df)
    assert "Broadcast" not in out._jdf.queryExecution().executedPlan().toString()
    assert out.count() == 20
