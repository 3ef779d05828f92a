"""The codegree check of large classes on the kernel: pairs that nobody asks, both ways of sending points, single precision."""

import numpy as np
import pytest

from evenpart.functions import blocks
from evenpart.operators import clustering as C
from evenpart.operators import large
from evenpart.operators import partition as P

EPS = 0.3


@pytest.fixture(scope="module")
def apart(spark):
    """Three classes: two on the same places, one far away, so that its pairs are too thin to be asked."""
    rng = np.random.default_rng(5)
    cls = np.arange(90) % 3 + 1
    x = rng.normal(size=(90, 3)) * rng.choice([0.1, 1.0], size=(90, 1)) + np.where(cls == 3, 30.0, 0.0)[:, None]
    frame = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vid long, x array<double>").cache()
    return x, cls, spark.createDataFrame([(i, int(c)) for i, c in enumerate(cls)], "vid long, cls int").cache(), frame


@pytest.mark.parametrize("sent", [True, False])
def test_pairs_that_are_not_asked(apart, monkeypatch, sent):
    x, cls, assign, frame = apart
    monkeypatch.setattr(large, "SIDE", 16)
    monkeypatch.setattr(large, "LOT", 7)
    monkeypatch.setattr(large, "ANCHORS", 90)
    if not sent:
        monkeypatch.setattr(large, "MOST_POINTS", 0)
    rows = P.check_pairs(assign, EPS, "codegree", None, frame, 1.0).collect()
    w = blocks.gaussian(x, x, 1.0)
    for s, t in ((1, 2), (1, 3), (2, 3)):
        a, b = np.flatnonzero(cls == s), np.flatnonzero(cls == t)
        status, gap, ra, cb = blocks.check(w[np.ix_(a, b)], EPS, "codegree")
        got = [r for r in rows if (r.s, r.t) == (s, t)]
        (head,) = [r for r in got if r.vid is None]
        assert (head.status, round(head.gap, 9)) == (status, round(gap, 9))
        assert {r.vid for r in got if r.vid is not None} == (set() if ra is None else {*a[ra].tolist(), *b[cb].tolist()})
    assert {(r.s, r.t) for r in rows if r.status == blocks.WITNESS} == {(1, 2)}


@pytest.mark.parametrize("scale", [1.5, 3.0, 6.0])
def test_single_precision_decides_as_double(monkeypatch, scale):
    rng = np.random.default_rng(int(10 * scale))
    x = rng.normal(size=(300, 20)) * rng.choice([0.2, 1.0, 3.0], size=(300, 1))
    x[150:] = x[:150]  # copies: ties of codegrees and gaps
    for w in (blocks.gaussian(x, x[::-1] + 0.1, scale), (blocks.gaussian(x, x[::-1], scale) > 0.2).astype(float)):
        for options in ({}, {"policy": "lemma_order", "anchors": "typical"}, {"anchors": 64}):
            found = blocks.check(w, EPS, "codegree", **options)
            monkeypatch.setattr(blocks, "LEAST_SINGLE", 10**9)
            want = blocks.check(w, EPS, "codegree", **options)
            monkeypatch.undo()
            assert found[0] == want[0] and abs(found[1] - want[1]) < 1e-12


def test_median_scale(spark):
    x = np.random.default_rng(1).normal(size=(40, 3))
    v = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vid long, x array<double>")
    d = np.sort([np.sqrt(((a - b) ** 2).sum()) for i, a in enumerate(x) for b in x[:i]])
    assert abs(C.median_scale(v) - d[(len(d) - 1) // 2]) < 1e-9
