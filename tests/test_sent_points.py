"""Blocks of points are made where the points are held: no copy of a point is dealt, and a loop keeps the witnesses it asks for."""

import numpy as np

from evenpart.functions import blocks
from evenpart.operators import partition as P


def test_no_copies_and_chosen_marks_only(spark, monkeypatch):
    rng = np.random.default_rng(9)
    x = rng.normal(size=(96, 3)) + 2.0 * np.eye(3)[np.arange(96) % 3]
    v = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vid long, x array<double>").cache()
    a = P.initial_partition(v, 6).cache()
    read = lambda df: sorted((r.s, r.t, r.status or "", r.d or 0.0, r.gap or 0.0, r.side or 0, r.vid or 0) for r in df.collect())
    sent = P.check_pairs(a, 0.45, "codegree", None, v, 2.0)
    plan = sent._jdf.queryExecution().toString()
    assert "CoGroup" not in plan and "Generate" not in plan  # nothing is dealt to the meetings of lots
    whole = read(sent)
    monkeypatch.setattr(P, "MOST_NUMBERS", 0)
    assert np.allclose([r[3:5] for r in read(P.check_pairs(a, 0.45, "codegree", None, v, 2.0))], [r[3:5] for r in whole])
    monkeypatch.undo()
    bad = sorted({r[:2] for r in whole if r[2] == blocks.WITNESS})
    assert len(bad) > 2
    assert read(P.check_pairs(a, 0.45, "codegree", None, v, 2.0, marks=False)) == [r for r in whole if r[2]]
    some = {bad[0], bad[-1]}
    assert read(P.check_pairs(a, 0.45, "codegree", None, v, 2.0, only=some)) == [r for r in whole if r[:2] in some]
