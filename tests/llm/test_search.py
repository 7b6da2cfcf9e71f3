"""Exact top-k search against brute force: ties, negative, repeated and zero rows, several parts of queries."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from trainscape.llm import topk_search


def brute(rows, k=5, every=50):
    """(query_id, rank, vec_id, score) by all integer products."""
    q = {(i, tuple(v)) for i, v in rows if i % every == 0}
    out = []
    for qi in sorted({i for i, _ in q}):
        found = sorted((-sum(int(np.floor(256 * a)) * int(np.floor(256 * b)) for a, b in zip(v, w)), j) for i, v in q if i == qi for j, w in rows if j != qi and len(w) == len(v))[:k]
        out += [(qi, n + 1, j, -s) for n, (s, j) in enumerate(found)]
    return out


def searched(spark, rows, **more):
    df = spark.createDataFrame([(i, list(map(float, v))) for i, v in rows], "vec_id long, embedding array<double>").repartition(3)
    return sorted(tuple(r) for r in topk_search.exact_top_k(df, F.col("vec_id") % 50 == 0, **more).collect())


def test_equal_scores_keep_smaller_ids(spark):
    rows = [(0, [1.0] * 64)] + [(i, [-1.0] * 64) for i in [1, *range(1001, 1255)]] + [(i, [-1.0] * 64) for i in range(2001, 2256)]
    rows = [r for r in rows if r[0] == 0 or r[0] % 50]
    got = searched(spark, rows)
    assert got == [(0, n + 1, j, -(256 * 256 * 64)) for n, j in enumerate([1, 1001, 1002, 1003, 1004])]


@pytest.mark.parametrize("shape", ["mixed", "negative", "repeated"])
@pytest.mark.parametrize("numbers, block, chunk", [(4_000_000, 256, 65_536), (24, 8, 32)])
def test_equals_brute_force(spark, shape, numbers, block, chunk):
    r = np.random.default_rng(7)
    x = np.round(r.normal(size=(400, 6)), 1)
    if shape == "negative":
        x = np.where(np.arange(400)[:, None] % 50 == 0, np.abs(x), -np.abs(x))
    elif shape == "repeated":
        x = x[np.arange(400) % 7]
        x[::9] = 0
    rows = [(i - 100, v) for i, v in enumerate(x)] + [(3, x[3]), (50, x[150]), (100, x[200])] + [(1000 + i, v[:4]) for i, v in enumerate(x[:60])]
    assert searched(spark, rows, numbers=numbers, block=block, chunk=chunk) == brute(rows)


def test_scores_beyond_float_and_64_bits(spark):
    rows = [(0, [1e6] * 4), (1, [1e6] * 4), (2, [1e6, 1e6, 1e6, 1e6 + 1 / 256]), (3, [-1e15] * 4), (4, [1e15] * 4), (5, [1e15] * 4)]
    got = searched(spark, rows)
    assert [g[2] for g in got] == [4, 5, 2, 1, 3] and got[0][3] == 2**63 - 1 and got[-1][3] == -(2**63 - 1)


def test_blocks_are_pruned():
    r = np.random.default_rng(2)
    x = np.floor(np.repeat(r.normal(size=(20, 8)) * 400, 50, axis=0) + r.normal(size=(1000, 8)) * 10)
    ids, q = np.arange(1000) * 3, x[::97]
    best = topk_search.TopK(len(q), 5)
    least = topk_search.first_thresholds(q, ids[::97], x[::5], ids[::5], 5)
    made, every = topk_search.search_blocks(q, ids[::97], x, ids, best, least, 32)
    assert made < 0.3 * every
    for k in range(len(q)):
        scores = (q[k] @ x.T).astype(np.int64)
        want = sorted((-scores[j], ids[j]) for j in range(1000) if ids[j] != ids[::97][k])[:5]
        assert [(-a, b) for a, b in zip(best.scores[k], best.ids[k])] == want
