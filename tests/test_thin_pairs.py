"""Pairs too thin to be uneven are settled by bounds; what passes over edges answer does not change."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from evenpart.functions import blocks
from evenpart.operators import large, power
from evenpart.operators import partition as P
from evenpart.operators.graphs import md5_coin

N, K, EPS = 240, 3, 0.6


@pytest.fixture(scope="module")
def thin(spark):
    """Every vertex has two neighbours in the next class: the Frobenius norm is above the edge, the degree bound below."""
    cls = np.arange(N) % K + 1
    pairs = {(min(i, j), max(i, j)) for i in range(N) for j in ((i + 1) % N, (i + 7) % N)}
    edges = spark.createDataFrame([(i, j, 1.0) for i, j in sorted(pairs)], "src long, dst long, w double").cache()
    return cls, pairs, spark.createDataFrame([(i, int(c)) for i, c in enumerate(cls)], "vid long, cls int").cache(), edges


def test_thin_pairs_need_no_sweep(thin, monkeypatch):
    cls, pairs, assign, edges = thin
    w = np.zeros((N, N))
    for i, j in pairs:
        w[i, j] = w[j, i] = 1
    eps = 0.5  # the edge is 10, the Frobenius norms about 12, the degree bound 5
    for s, t in ((1, 2), (1, 3), (2, 3)):
        c = w[np.ix_(cls == s, cls == t)]
        assert np.linalg.norm(c - c.mean()) > eps**3 * 80 > np.linalg.norm(c - c.mean(), 2)

    def none(*_, **__):
        raise AssertionError("swept")

    monkeypatch.setattr(power, "power_sweeps", none)
    for checker in ("power", "sigma"):
        monkeypatch.setattr(large, "SIDE", 16)
        got = P.check_pairs(assign, eps, checker, edges).collect()
        assert sorted((r.s, r.t, r.status) for r in got) == [(s, t, blocks.UNIFORM) for s, t in ((1, 2), (1, 3), (2, 3))]
        assert all(abs(r.d - w[np.ix_(cls == r.s, cls == r.t)].mean()) < 1e-12 and r.gap == 0 for r in got)
    got = P.check_pairs(assign, EPS, "codegree", edges)  # thinner than eps^3: no edge is written a second time
    monkeypatch.setattr(large.Edges, "crossing", property(none))
    assert sorted((r.s, r.t, r.status) for r in P.check_pairs(assign, EPS, "codegree", edges).collect()) == sorted((r.s, r.t, r.status) for r in got.collect())


@pytest.mark.parametrize("few", [0, 10_000])
def test_codegrees_of_few_anchors(thin, monkeypatch, few):
    cls, pairs, assign, edges = thin
    monkeypatch.setattr(large, "FEW_ASKED", few)
    source = large.Edges(assign, edges)
    asked = large.directed(large.pair_stats(source, assign)).withColumn("d", F.lit(0.5)).join(large.choose_anchors(assign, 4).withColumnRenamed("cls", "side"), "side").select("s", "t", "side", "y", "d")
    want = {}
    near = {i: {j for p in pairs for j in p if i in p and j != i} for i in range(N)}
    for r in asked.collect():
        far = r.t if r.side == r.s else r.s
        for v in range(N):
            if v != r.y and cls[v] == r.side and (n := sum(cls[x] == far for x in near[v] & near[r.y])):
                want[r.s, r.t, r.side, r.y, v] = (n, n)
    assert {(r.s, r.t, r.side, r.y, r.vid): (r.n, r.h) for r in source._common(asked).collect()} == want


def test_probe_in_one_pass(thin, monkeypatch):
    cls, pairs, assign, edges = thin
    whole = P.pair_density(edges, assign).where("s = 1 AND t = 2").first()["d"]
    want = 0.0
    for i in range(4):
        half = [assign.where((F.col("cls") == c) & (md5_coin(F.col("vid"), F.lit(f"42:{i}:{side}")) < 0.5)) for c, side in ((1, "a"), (2, "b"))]
        want = max(want, abs(P.rect_density(edges, *half).first()["d"] - whole))

    def none(*_, **__):
        raise AssertionError("a pass of its own")

    monkeypatch.setattr(P, "rect_density", none)
    assert abs(P.probe_gap(edges, assign, 1, 2, trials=4) - want) < 1e-12 and want > 0
