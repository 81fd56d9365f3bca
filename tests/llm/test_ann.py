import math

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from tiersort.llm import ann
from tiersort.llm.queries import QUERIES
from helpers import DATA


def exact(rows, queries, k=5):
    """Brute force by the contract: id -> [(vec_id, score)]."""
    good = [(i, v) for i, v in rows if i is not None and v and all(x is not None and math.isfinite(x) for x in v) and any(v)]
    norm = {i: math.sqrt(sum(x * x for x in v)) for i, v in good}
    out = {}
    for q, a in good:
        if q in queries:
            s = [(-sum(x * y for x, y in zip(a, v)) / (norm[q] * norm[i]), i) for i, v in good if i != q]
            out[q] = [(i, -x) for x, i in sorted((round(x, 12), i) for x, i in s)[:k]]
    return out


def test_recall_and_scores(spark):
    rows = [(r.vec_id, list(r.embedding)) for r in spark.read.parquet(f"{DATA}/embeddings.parquet").collect()]
    want = exact(rows, {i for i, _ in rows if i % 50 == 0})
    got = {}
    vec = dict(rows)
    for r in QUERIES["op1_ann"](spark, DATA).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
        a, b = np.array(vec[r.query_id], float), np.array(vec[r.vec_id], float)
        assert abs(r.score - a @ b / np.sqrt((a @ a) * (b @ b))) < 1e-12
    assert got.keys() == want.keys()
    hits = sum(len({i for i, _ in w} & {v for _, v, _ in got[q]}) for q, w in want.items())
    assert hits >= 0.9 * sum(map(len, want.values()))
    for g in got.values():
        assert [r for r, _, _ in sorted(g)] == [1, 2, 3, 4, 5]
        assert sorted(g) == [(i + 1, v, s) for i, (_, v, s) in enumerate(sorted(g, key=lambda x: (-x[2], x[1])))]


def test_ties_bad_vectors_and_hot_group(spark):
    rng = np.random.default_rng(3)
    rows = [(i, rng.normal(size=8).tolist()) for i in range(300)]
    same = rng.normal(size=8).tolist()
    rows += [(1000 + i, same) for i in range(400)]  # more equal vectors than a shard or a rerank holds
    rows += [(5000, None), (5001, [0.0] * 8), (5002, [float("nan")] * 8), (5003, [None] + [1.0] * 7), (5004, [float("inf")] * 8), (5005, []), (None, same), (5006, [1.0, 2.0])]
    df = spark.createDataFrame([(i, v, "x") for i, v in rows], "vec_id long, embedding array<double>, score string")
    got = {}
    for r in ann.search(df, F.col("id") % 50 == 0, probes=1.0, rerank=20, shard_rows=64).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id))
    want = exact([x for x in rows if x[0] != 5006], {i for i, _ in rows if i is not None and i % 50 == 0})
    for q in (1000, 1050, 1100):
        assert [v for _, v in sorted(got[q])] == [i for i, _ in want[q]] == [i for i in range(1000, 1006) if i != q][:5]
    assert got.keys() == want.keys()


@pytest.mark.parametrize("n", [0, 1, 3])
def test_few_vectors(spark, n):
    df = spark.createDataFrame([(50 * i, [1.0 + i, 2.0]) for i in range(n)], "vec_id long, embedding array<float>")
    assert ann.search(df, F.col("id") % 50 == 0).count() == n * max(0, n - 1)


def test_codes_rank_like_distances():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(600, 16))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    index = ann.Index(x, ann.kmeans(x, 4, np.random.default_rng(3)), 8)
    cell, codes = index.encode(x)
    rows = np.flatnonzero(cell == 0)
    near = index.promising(x[rows[:20]], 0, codes[rows], 10)
    for i, r in enumerate(near):
        assert i in r  # a member's own code is among the nearest
    assert (index.visits(x[:20], 1)[:, 0] == cell[:20]).all()


def recall_of(spark, x, is_query="id % 50 = 0", every=50):
    df = spark.createDataFrame(pd.DataFrame({"vec_id": np.arange(len(x)), "embedding": [v.tolist() for v in x]}), "vec_id long, embedding array<double>")
    got = {}
    for r in ann.search(df, F.expr(is_query)).collect():
        got.setdefault(r.query_id, []).append(r.vec_id)
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    asks = np.arange(0, len(x), every)
    score = unit[asks] @ unit.T
    score[np.arange(len(asks)), asks] = -2
    want = np.argsort(-score, 1, kind="stable")[:, :5]
    return sum(len({*w.tolist()} & {*got[q]}) for q, w in zip(asks.tolist(), want)) / want.size


def test_recall_within_tight_clusters(spark):
    """Many vectors that differ by less than the codes tell apart."""
    rng = np.random.default_rng(5)
    centre = rng.normal(size=(6, 48))
    assert recall_of(spark, centre[rng.integers(0, 6, 6000)] + rng.normal(size=(6000, 48)) * 0.01) >= 0.95


def test_recall_where_queries_are_unlike_the_rest(spark):
    rng = np.random.default_rng(6)
    centre = rng.normal(size=(40, 32))
    x = centre[rng.integers(0, 40, 6000)] + rng.normal(size=(6000, 32)) * 0.05
    x[::50] = rng.normal(size=(120, 32))
    assert recall_of(spark, x) >= 0.9


def test_recall_without_structure(spark):
    assert recall_of(spark, np.random.default_rng(7).normal(size=(6000, 64))) >= 0.9
