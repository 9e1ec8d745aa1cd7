import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitextspark.llm import topk_search as search


def plain(rows, k=5, every=50):
    good = [(i, [math.floor(256 * float(np.float32(c))) for c in v]) for i, v, *_ in rows if i is not None and v and all(c is not None and math.isfinite(c) for c in v)]
    out = []
    for q, x in good:
        if q % every == 0:
            found = sorted((-sum(a * b for a, b in zip(x, y, strict=True)), i) for i, y in good if i != q)[:k]
            out += [(q, n + 1, i, -s) for n, (s, i) in enumerate(found)]
    return sorted(out)


def test_equals_brute_force(spark):
    rng = random.Random(7)
    hot = [rng.uniform(-1, 1) for _ in range(8)]
    rows = [(i, hot if i % 3 == 0 else [rng.choice([0.5, -0.25, rng.uniform(-1, 1)]) for _ in range(8)], 1) for i in range(600)]
    rows += [(1000, None, 1), (1050, [1.0, None] + [0.0] * 6, 1), (1100, [float("nan")] + [0.0] * 7, 1), (1150, [float("inf")] + [0.0] * 7, 1), (None, hot, 1), (1200, [], 2), (1250, [0.0] * 8, 2)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, score int")
    for block in (1000, 4):
        got = sorted(map(tuple, search.top_k(df, F.col("vec_id") % 50 == 0, block=block).select("query_id", "rank", "vec_id", "score").collect()))
        assert got == plain(rows)
    assert search.top_k(df.limit(0), F.col("vec_id") % 50 == 0).count() == 0
    few = spark.createDataFrame(rows[:3], "vec_id long, embedding array<float>, score int")
    assert sorted(map(tuple, search.top_k(few, F.col("vec_id") % 50 == 0).select("query_id", "rank", "vec_id", "score").collect())) == plain(rows[:3])


def test_statistics_bound_the_product_at_every_resolution():
    rng = np.random.default_rng(3)
    a, b = rng.normal(size=(50, 64)), rng.normal(size=(60, 64))
    last = None
    for s in (1, 4, 16, 64):
        bound = search.statistics(a, s) @ search.statistics(b, s).T
        assert (bound >= a @ b.T - 1e-9).all() and (last is None or (bound <= last + 1e-9).all())
        last = bound


def test_bounds_rule_out_candidates():
    rng = np.random.default_rng(3)
    base = np.repeat(rng.normal(size=(4000, 4)), 16, axis=1) + 0.05 * rng.normal(size=(4000, 64))
    x = np.floor(256 * base)
    found = search.Searcher(np.arange(8), x[:8], 5)
    for a in range(0, 4000, 50):
        found.show(np.arange(a, a + 50), x[a : a + 50])
    assert found.exact < 0.5 * found.bounded


def test_most_pairs_are_ruled_out_one_by_one_at_the_real_tile_sizes():
    # smooth vectors, as of series: segments say nearly all of them; many queries, so no whole tile can go
    rng = np.random.default_rng(5)
    base = np.cumsum(rng.normal(size=(20_000, 64)), axis=1) * rng.lognormal(0, 0.7, size=(20_000, 1))
    x = np.floor(16 * base)
    found = search.Searcher(np.arange(1024), x[:1024], 5)
    for a in range(0, len(x), search.TILE_ROWS):
        found.show(np.arange(a, min(a + search.TILE_ROWS, len(x))), x[a : a + search.TILE_ROWS])
    assert found.exact < 0.1 * found.bounded
    scores = x[:1024] @ x.T
    scores[np.arange(1024), np.arange(1024)] = -np.inf
    assert (np.sort(scores, axis=1)[:, ::-1][:, :5] == found.score).all()


def test_unequal_lengths_are_refused(spark):
    df = spark.createDataFrame([(0, [0.5, 0.5, 0.5]), (1, [0.5] * 5)], "vec_id long, embedding array<float>")
    with pytest.raises(ValueError):
        search.top_k(df, F.col("vec_id") % 50 == 0)
