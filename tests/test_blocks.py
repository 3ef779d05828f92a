"""Hand-checked cases of the block kernels and measures."""

import itertools

import numpy as np
import pytest

from evenpart.functions import blocks
from evenpart.operators import local


def two_blocks(m=8):
    half = np.arange(m) < m // 2
    return (half[:, None] == half[None]).astype(float)


@pytest.mark.parametrize("checker", ["codegree", "sigma", "exhaustive"])
def test_complete_and_empty_pairs_are_uniform(checker):
    for w in (np.ones((8, 8)), np.zeros((8, 8))):
        assert blocks.check(w, 0.3, checker)[0] == blocks.UNIFORM


def test_two_blocks_have_a_witness_of_one_block():
    status, gap, a, b = blocks.codegree(two_blocks(), 0.5)
    assert status == blocks.WITNESS and gap == pytest.approx(0.5) and a.sum() == 4
    status, _, _, _, s = blocks.sigma(two_blocks(), 0.7)
    assert s == pytest.approx(4.0) and status == blocks.WITNESS
    assert blocks.sigma(two_blocks(), 0.8)[0] == blocks.UNIFORM


def test_degree_step_fires():
    w = np.zeros((8, 8))
    w[:, :4] = 1
    status, gap, a, b = blocks.codegree(w, 0.3, policy="lemma_order")
    assert status == blocks.WITNESS and gap == pytest.approx(0.5) and a.all() and b.sum() == 4


@pytest.mark.parametrize("seed", range(5))
def test_sigma_between_its_bounds(seed):
    w = (np.random.default_rng(seed).random((12, 12)) < 0.5).astype(float)
    c = w - w.mean()
    s = blocks.sigma(w, 1e-3)[4]
    assert np.abs(c.sum(1)).max() / np.sqrt(12) - 1e-9 <= s <= np.linalg.norm(c) + 1e-9


@pytest.mark.parametrize("seed", range(10))
def test_assignment_is_best(seed):
    g = np.random.default_rng(seed).integers(0, 9, (5, 5)).astype(float)
    best = max(sum(g[i, p[i]] for i in range(5)) for p in itertools.permutations(range(5)))
    assert g[np.arange(5), blocks.assignment(g)].sum() == best


def test_scores():
    assert blocks.scores([[5, 1], [2, 4]])["accuracy"] == 75
    assert blocks.scores([[4, 0], [3, 0], [0, 3]])["accuracy"] == 70
    one = blocks.scores([[7, 3]])
    assert (one["accuracy"], one["nmi"], one["ari"]) == (70, 0, 0)


def test_sizes_and_constants():
    assert [r[:2] for r in blocks.class_sizes(500, 3, 20)] == [(3, 166), (9, 55), (27, 18)]
    assert blocks.class_sizes(1599, 7, 50)[-1][0] == 49
    assert blocks.class_sizes(1000, 2, 16, "global")[-1] == (66, 15, 10)
    assert [blocks.theory(e, 2, 100)["least_k"] for e in (0.5, 0.33, 0.15)] == [25, 31, 42]


def test_refine_recycles_leftovers():
    for size, inside, new in ((10, 4, 3), (10, 5, 3), (5, 2, 5)):
        mark = np.arange(size) < inside
        cls, k = local.refine(np.ones(size, int), 1, {1: mark}, 3, np.arange(size), 0)
        assert k == new and (cls == 0).sum() == size - new * (size // 3)


def test_energy_of_constant_density():
    d = np.full((4, 4), 0.5)
    assert local.energy(d) == pytest.approx((0.25 * 3 / 8, 0.25))


def test_planted_blocks_are_recovered():
    rng, y = np.random.default_rng(1), np.arange(240) // 120
    a = np.triu(rng.random((240, 240)) < np.where(y[:, None] == y[None], 0.9, 0.1), 1)
    a = (a | a.T).astype(float)
    labels, k, trace = local.fit_predict(a, a, 2, 0.3, 4, h=10, pick="max_gap")
    assert blocks.scores(blocks.confusion_of(labels, y))["accuracy"] >= 85
    assert all(0 <= r["energy"] < 0.5 for r in trace) and k >= 3


def test_first_triple_needs_no_whole_decomposition(monkeypatch):
    """The first singular value and vectors of large blocks, and the verdicts made of them, without the others."""
    rng = np.random.default_rng(6)
    x, y = rng.normal(size=(260, 20)), rng.normal(size=(240, 20)) + 0.3
    planted = (rng.random((260, 240)) < 0.3 + 0.5 * np.outer(np.arange(260) < 100, np.arange(240) < 90)).astype(float)
    for w in (blocks.gaussian(x, y, 3.0), planted, np.kron(np.eye(2), np.ones((130, 120)))):
        c = w - w.mean()
        u, sv, v = np.linalg.svd(c)
        want = blocks.rounded(u[:, 0], v[0], c, 12)
        whole = np.linalg.svd
        monkeypatch.setattr(np.linalg, "svd", lambda a, *more: whole(a, *more) if len(a) < 200 else pytest.fail("the whole block"))
        a, first, b = blocks.first_triple(c)
        status, mean, rows, cols, _ = blocks.sigma(w, 0.3)
        monkeypatch.undo()
        assert first == pytest.approx(sv[0], rel=1e-12) and abs(abs(a @ u[:, 0]) - 1) < 1e-10 and abs(abs(b @ v[0]) - 1) < 1e-10
        assert status == blocks.WITNESS and mean == pytest.approx(want[0], rel=1e-9)
        assert abs(abs(c[rows][:, cols].mean()) - mean) < 1e-12
