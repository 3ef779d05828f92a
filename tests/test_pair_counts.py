"""Shared hubs are counted where the smaller member lies: pairs cross no exchange, hubs of many parts included."""

import contextlib
import io
import random
from collections import Counter

import pytest

from evenpart.operators import graphs as G


@pytest.mark.parametrize("part", [2048, 5])
def test_pairs_cross_no_exchange(spark, monkeypatch, part):
    monkeypatch.setattr(G, "HUB_PART", part)
    random.seed(1)
    rows = [(random.randrange(60), random.randrange(25)) for _ in range(500)]
    want = Counter((a, b) for a, h in set(rows) for b, k in set(rows) if h == k and a < b)
    got = G.co_occurrence(spark.createDataFrame([*rows, (None, 1), (1, None)], "v long, h long"), "v", "h")
    assert {(r.src, r.dst): r.w for r in got.collect()} == dict(want)
    text = io.StringIO()
    with contextlib.redirect_stdout(text):
        got.explain()
    plan = text.getvalue().splitlines()
    assert "Generate explode(b" in next(line for line in plan if "Generate" in line or "Exchange" in line)  # from the result down
