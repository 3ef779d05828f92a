"""Checks of classes beyond a block give the verdicts of the dense check."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from evenpart.functions import blocks
from evenpart.operators import large
from evenpart.operators import partition as P

N, K, EPS = 120, 3, 0.45


@pytest.fixture(scope="module")
def world(spark):
    rng = np.random.default_rng(12)
    x = rng.normal(size=(N, 3)) + 2.5 * np.eye(3)[np.arange(N) % 2]
    y = np.abs(x) / np.linalg.norm(x, axis=1, keepdims=True)
    cls = np.arange(N) % K + 1
    assign = spark.createDataFrame([(i, int(c)) for i, c in enumerate(cls)], "vid long, cls int").cache()
    frame = lambda a: spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(a)], "vid long, x array<double>").cache()
    w = blocks.gaussian(x, x, 1.5)
    b = (w > np.median(w)).astype(float)
    np.fill_diagonal(b, 0)
    edges = spark.createDataFrame([(i, j, float(b[i, j])) for i in range(N) for j in range(i + 1, N) if b[i, j]], "src long, dst long, w double").cache()
    sources = {"edges": (b, {"edges": edges}), "gauss": (w, {"vertices": frame(x), "sigma": 1.5}), "inner": (y @ y.T, {"vertices": frame(y)})}
    return cls, assign, sources


def _dense(w, cls, checker, **options):
    out = {}
    for s in range(1, K + 1):
        for t in range(s + 1, K + 1):
            a, b = np.flatnonzero(cls == s), np.flatnonzero(cls == t)
            status, gap, ra, cb = blocks.check(w[np.ix_(a, b)], EPS, checker, **options)
            marks = frozenset([*a[ra].tolist(), *b[cb].tolist()]) if status == blocks.WITNESS else frozenset()
            out[s, t] = (status, round(float(w[np.ix_(a, b)].mean()), 6), round(float(gap), 6), marks)
    return out


def _found(df):
    rows, out, marks = df.collect(), {}, {}
    for r in rows:
        if r.vid is not None:
            marks.setdefault((r.s, r.t), set()).add(r.vid)
    for r in rows:
        if r.vid is None:
            out[r.s, r.t] = (r.status, round(r.d, 6), round(r.gap, 6), frozenset(marks.get((r.s, r.t), ())))
    return out


@pytest.mark.parametrize("kind", ["edges", "gauss", "inner"])
def test_codegree(world, monkeypatch, kind):
    cls, assign, sources = world
    w, source = sources[kind]
    for options in ({}, {"policy": "lemma_order", "anchors": "typical"}):
        want = _dense(w, cls, "codegree", **options)
        assert _found(P.check_pairs(assign, EPS, "codegree", **source, **options)) == want
        monkeypatch.setattr(large, "SIDE", 16)
        monkeypatch.setattr(large, "ANCHORS", N)
        got = _found(P.check_pairs(assign, EPS, "codegree", **source, **options))
        monkeypatch.undo()
        # a source that asks a sample of the vertices can't call a pair uniform, unless the sample is all of them
        assert got == want
    assert any(v[0] == blocks.WITNESS for v in want.values())


def test_density_at_any_size(world, monkeypatch):
    cls, assign, sources = world
    monkeypatch.setattr(large, "SIDE", 16)
    for w, source in sources.values():
        got = _found(P.check_pairs(assign, EPS, "density", **source))
        assert {k: v[1] for k, v in got.items()} == {k: v[1] for k, v in _dense(w, cls, "density").items()}


def test_spectral_of_inner_products(world):
    cls, assign, sources = world
    w, source = sources["inner"]
    inner = large.Inner(assign, source["vertices"])
    found, marks = inner.spectral(large.pair_stats(inner, assign), 0.2)
    seen = {}
    for r in marks.collect():
        seen.setdefault((r.s, r.t, r.side), []).append(r.vid)
    for r in found.collect():
        block = w[np.ix_(cls == r.s, cls == r.t)]
        d = block.mean()
        assert r.sigma == pytest.approx(np.linalg.svd(block - d)[1][0], rel=1e-6)
        assert r.bad == (r.sigma >= 0.2**3 * np.sqrt(block.size))
        if r.gap is not None:
            assert abs(w[np.ix_(seen[r.s, r.t, r.s], seen[r.s, r.t, r.t])].mean() - d) == pytest.approx(r.gap, rel=1e-6)


def test_anchors_are_the_smallest_coins(spark):
    placed = spark.range(3000).select(F.col("id").alias("vid"), (F.col("id") % 2 + 1).cast("int").alias("cls"))
    got = large.choose_anchors(placed, 50).collect()
    from evenpart.operators.graphs import md5_coin

    coins = {r.vid: (r.c, r.vid) for r in placed.select("vid", md5_coin(F.col("vid"), F.lit("anchor:42")).alias("c")).collect()}
    for c in (1, 2):
        mine = sorted((v for v in coins if v % 2 + 1 == c), key=coins.get)[:50]
        assert {r.y for r in got if r.cls == c} == set(mine)
