"""Classes beyond a block are asked from the same anchors as classes inside one: verdicts and witnesses don't change at the limit."""

import numpy as np
import pytest

from evenpart.functions import blocks
from evenpart.operators import large
from evenpart.operators import partition as P

N, EPS = 300, 0.4


@pytest.fixture(scope="module")
def world(spark):
    """Three classes: two alike, one drawn wider, so that some pairs have a witness, some are even and some stay open."""
    rng = np.random.default_rng(7)
    cls = np.arange(N) % 3 + 1
    x = rng.normal(size=(N, 3)) * np.where(cls == 3, 1.6, 0.7)[:, None]
    x[30:60] = x[:30]  # copies: ties of codegrees and gaps
    unit = np.abs(x) / np.linalg.norm(x, axis=1, keepdims=True)
    frame = lambda a: spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(a)], "vid long, x array<double>").cache()
    assign = spark.createDataFrame([(i, int(c)) for i, c in enumerate(cls)], "vid long, cls int").cache()
    b = (blocks.gaussian(x, x, 1.5) > 0.5).astype(float)
    np.fill_diagonal(b, 0)
    edges = spark.createDataFrame([(i, j, 1.0) for i in range(N) for j in range(i + 1, N) if b[i, j]], "src long, dst long, w double").cache()
    return assign, {"gauss": {"vertices": frame(x), "sigma": 2.0}, "flat": {"vertices": frame(x), "sigma": 40.0}, "inner": {"vertices": frame(unit)}, "edges": {"edges": edges}}


def _found(df):
    rows = df.collect()
    marks = {(r.s, r.t): sorted(m.vid for m in rows if m.vid is not None and (m.s, m.t) == (r.s, r.t)) for r in rows}
    return {(r.s, r.t): (r.status, round(r.d, 9), round(r.gap, 9), marks[r.s, r.t]) for r in rows if r.vid is None}


@pytest.mark.parametrize(("kind", "options", "status"), [
    ("gauss", {}, blocks.WITNESS), ("gauss", {"policy": "lemma_order", "anchors": "typical"}, blocks.WITNESS), ("gauss", {"anchors": 16}, blocks.WITNESS), ("flat", {}, blocks.UNIFORM),
    ("inner", {}, blocks.WITNESS), ("edges", {"anchors": 16}, blocks.WITNESS),
])
def test_same_anchors_on_both_sides_of_the_limit(world, monkeypatch, kind, options, status):
    assign, sources = world
    want = _found(P.check_pairs(assign, EPS, "codegree", **sources[kind], **options))
    monkeypatch.setattr(large, "SIDE", 64)
    monkeypatch.setattr(large, "LOT", 23)
    assert _found(P.check_pairs(assign, EPS, "codegree", **sources[kind], **options)) == want
    assert status in {v[0] for v in want.values()}


def test_inner_products_ask_lot_by_lot(world, monkeypatch):
    assign, sources = world
    want = _found(P.check_pairs(assign, EPS, "codegree", **sources["inner"]))
    monkeypatch.setattr(large, "SIDE", 64)
    monkeypatch.setattr(large, "ANCHORS", 40)
    assert _found(P.check_pairs(assign, EPS, "codegree", **sources["inner"])) == want


@pytest.mark.parametrize("scale", [0.7, 2.0, 5.0])
def test_single_precision_gives_the_sizes_of_double(monkeypatch, scale):
    rng = np.random.default_rng(3)
    x, far = rng.normal(size=(400, 20)) * rng.choice([0.2, 1.0, 30.0], size=(400, 1)), rng.normal(size=(400, 20))
    x[200:300], far[100:200] = x[:100], x[:100]
    monkeypatch.setattr(large, "SIDE", 150)
    monkeypatch.setattr(large, "STEP", 64)
    w = blocks.gaussian(far, x, scale)
    d, n, own = float(w.mean()), w.T @ w, slice(90, 260)
    for bar in (d * d * 400, float(np.median(n)), float(n[5, 7])):  # the last is met by a pair's own codegree
        hood, near = w[:, own] > d, n[own] >= bar
        near[np.arange(170), np.arange(90, 260)] = False
        a, b, inner, deg = large.reach_of_all(x, own, far, scale, d, bar)
        assert (a == hood.sum(0)).all() and np.allclose(deg, w[:, own].sum(0))
        close = np.abs(n[own] - bar) <= 1e-9 * bar  # equal but for the last digit
        assert (np.abs(b - near.sum(1)) <= close.sum(1)).all()
        assert (np.abs(inner - ((hood.T.astype(float) @ w) * near).sum(1)) <= large.ROUNDING * np.maximum(a * b, 1) + close.sum(1) * a).all()
