"""Measures on tables whose values are known."""

from evenpart.functions.blocks import scores


def test_perfect_and_single():
    got = scores([[200, 0], [0, 200]])
    assert (got["accuracy"], got["ari"]) == (100, 1) and abs(got["nmi"] - 1) < 1e-12
    one = scores([[7, 3]])
    assert (one["accuracy"], one["nmi"], one["ari"]) == (70, 0, 0)
