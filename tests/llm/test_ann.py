import numpy as np
from pyspark.sql import functions as F

from tupleshare.llm import ann


def dot(v, w):
    total = 0.0
    for a, b in zip(v, w, strict=True):
        total += float(a) * float(b)
    return total


def brute(rows, k, asks):
    clean = [(i, v) for i, v in rows if v is not None and i is not None and len(v) == 8 and all(x is not None and np.isfinite(x) for x in v) and any(v)]
    out = {}
    for i, v in clean:
        if asks(i):
            out[i] = sorted(((-dot(v, w), j) for j, w in clean if j != i))[:k]
    return {i: [(j, -s) for s, j in best] for i, best in out.items()}


def search(df, k=5, **kw):
    got = {}
    for r in ann.nearest(df, F.col("vec_id") % 3 == 0, ann.Search(k=k, **kw)).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append((r.vec_id, r.score))
        assert r.rank == len(got[r.query_id])
    return got


def test_matches_brute_force_with_ties_and_unusable_rows(spark):
    rng = np.random.default_rng(1)
    rows = [(i, [float(np.float32(x)) for x in rng.standard_normal(8)]) for i in range(300)]
    rows += [(300 + i, rows[0][1]) for i in range(90)]
    rows += [(900, None), (903, [0.0] * 8), (906, [1.0] * 7 + [None]), (909, [float("nan")] * 8), (912, [float("inf")] + [1.0] * 7), (915, [1.0] * 3), (None, [1.0] * 8)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumns({"id": F.lit("x"), "code": F.lit(1), "score": F.lit(0)}).repartition(6)
    expect = brute(rows, 5, lambda i: i % 3 == 0)
    for kw in ({}, {"block": 20}, {"sample": 1}):
        assert search(df, **kw) == expect


def test_few_candidates_and_empty(spark):
    df = spark.createDataFrame([(3, [1.0, 0.0]), (1, [2.0, 1.0])], "vec_id long, embedding array<double>")
    assert search(df) == {3: [(1, 2.0)]}
    assert search(df.limit(0)) == {}


def test_bounds_hold_for_most_and_recall(spark):
    rng = np.random.default_rng(2)
    x = rng.standard_normal((4000, 64)).astype(np.float32)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    got = {}
    for r in ann.nearest(df, F.col("vec_id") % 20 == 0, ann.Search(sample=100)).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    hits = 0
    for q in range(0, 4000, 20):
        s = x.astype(float) @ x[q].astype(float)
        s[q] = -np.inf
        hits += len(got[q] & set(np.argsort(-s)[:20].tolist()))
    assert hits / (200 * 20) > 0.99
