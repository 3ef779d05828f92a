"""Tiles of the complete graph give the weights of the join pair by pair, odd points included."""

import numpy as np
import pytest

from evenpart.operators import graphs as G


def _rows(df):
    return {(r.src, r.dst): r.w for r in df.collect()}


@pytest.mark.parametrize("tuned", [False, True])
def test_tiles(spark, monkeypatch, tuned):
    monkeypatch.setattr(G, "PAIR_ROWS", 4)
    monkeypatch.setattr(G, "PAIR_COLUMNS", 7)
    x = np.random.default_rng(3).normal(size=(30, 5))
    x[20:] = x[:10]
    v = spark.createDataFrame([(i % 27 * 3 - 9, r.tolist()) for i, r in enumerate(x)], "vid long, x array<double>").cache()
    scales = spark.createDataFrame([(i * 3 - 9, 0.3 * (i % 4)) for i in range(25)], "vid long, s double") if tuned else None
    held = v if scales is None else v.join(scales, "vid")
    want = sorted((r.src, r.dst, r.w) for r in G._joined_pairs(held, 1.3).collect())
    got = sorted((r.src, r.dst, r.w) for r in G.affinity_pairs(v, 1.3, scales).collect())
    assert [g[:2] for g in got] == [w[:2] for w in want] and len(got) > 200
    assert np.allclose([g[2] for g in got], [w[2] for w in want], rtol=1e-14, atol=0)
    some = sorted((r.src, r.dst) for r in G.affinity_pairs(v, 1.3, scales, least=0.2).collect())
    assert some == [w[:2] for w in want if w[2] >= 0.2]


def test_odd_points(spark, monkeypatch):
    rows = [(1, [0.0, 1.0]), (2, None), (3, [1.0, None]), (4, [2.0, 1.0]), (None, [1.0, 1.0])]
    got = _rows(G.affinity_pairs(spark.createDataFrame(rows, "vid long, x array<double>"), 1.0))
    assert len(got) == 6 and abs(got[1, 4] - np.exp(-2)) < 1e-15 and [p for p, w in got.items() if w is not None] == [(1, 4)]
    assert G.affinity_pairs(spark.createDataFrame([], "vid long, x array<double>"), 1.0).collect() == []
    # any number of points that fits the memory of a task has a complete graph, not 50,000 alone
    assert G.MOST_BROADCAST >= 100_000
