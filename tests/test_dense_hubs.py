"""Hubs that many entities share: memberships are sent to the tasks, no list a member crosses an exchange."""

import contextlib
import io
import random
from collections import Counter

import pytest

from evenpart.operators import graphs as G


@pytest.mark.parametrize("form", ["long", "int"])
def test_dense_hubs_deal_no_lists(spark, monkeypatch, form):
    monkeypatch.setattr(G, "MOST_LISTED", 100, raising=False)
    random.seed(2)
    rows = [(random.randrange(90) * 7, f"h{random.randrange(12)}") for _ in range(700)]
    want = Counter((a, b) for a, h in set(rows) for b, k in set(rows) if h == k and a < b)
    got = G.co_occurrence(spark.createDataFrame([*rows, (None, "h1"), (1, None)], f"v {form}, h string"), "v", "h")
    assert got.schema.simpleString() == f"struct<src:{'bigint' if form == 'long' else form},dst:{'bigint' if form == 'long' else form},w:bigint>"
    found = got.collect()
    assert len(found) == len(want) and {(r.src, r.dst): r.w for r in found} == dict(want)
    text = io.StringIO()
    with contextlib.redirect_stdout(text):
        got.explain()
    assert "Exchange" not in text.getvalue()
