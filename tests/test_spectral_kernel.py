"""Spectral clustering of the complete kernel by tiles against the same steps over stored edges."""

import numpy as np
import pytest

from evenpart.operators import clustering as C
from evenpart.operators import graphs as G


@pytest.mark.parametrize("tuned", [False, True])
def test_same_classes_as_over_edges(spark, monkeypatch, tuned):
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(m, 0.4, (40, 2)) for m in ((0, 0), (4, 0), (0, 4))])
    v = spark.createDataFrame([(5 * i, [float(a) for a in p]) for i, p in enumerate(x)], "vid long, x array<double>").repartition(3)
    monkeypatch.setattr(C, "TILE_ROWS", 7)
    monkeypatch.setattr(C, "TILE_COLUMNS", 11)
    monkeypatch.setattr(G, "MOST_BROADCAST", 1000)
    s = G.local_scales(v) if tuned else None
    edges = G.affinity_pairs(v, scales=s) if tuned else G.affinity_pairs(v, sigma=1.0)
    groups = lambda df: {frozenset(r.vid for r in df.collect() if r.cluster == k) for k in range(3)}
    monkeypatch.setattr(G, "MOST_BROADCAST", 10)  # beyond what may be stored as pairs
    got = C.spectral_kernel(v, 3, scales=s) if tuned else C.spectral_kernel(v, 3, 1.0)
    assert groups(got) == groups(C.spectral(edges, v, 3))


def test_grid_of_a_large_table_needs_no_stored_pairs(spark, monkeypatch):
    """Complete-graph spectral settings beyond ``MOST_POINTS`` and ``MOST_BROADCAST``, with the labels of the stored graph."""
    from evenpart.operators import graphs, grids

    rng = np.random.default_rng(8)
    rows = [(i, [float(z) for z in rng.normal(size=2) + 6 * (i % 2)], str(i % 2)) for i in range(60)]
    v = spark.createDataFrame(rows, "vid long, x array<double>, y string")
    monkeypatch.setattr(grids, "MOST_POINTS", 10)
    monkeypatch.setattr(graphs, "MOST_BROADCAST", 10)
    got = grids.grid(v, [{"method": "spectral", "c": 2, **more} for more in ({}, {"self_tuned": True})]).collect()
    assert [r.accuracy for r in got] == [100.0, 100.0] and all(len(r.labels) == 60 for r in got)


@pytest.mark.parametrize("tuned", [False, True])
def test_no_number_of_points_is_refused(spark, monkeypatch, tuned):
    """The complete kernel of more points than were sent before has its classes too."""
    monkeypatch.setattr(C, "MOST_POINTS", 10, raising=False)
    rng = np.random.default_rng(3)
    v = spark.createDataFrame([(i, [float(z) for z in rng.normal(size=2) * 0.4 + 6 * (i % 2)]) for i in range(60)], "vid long, x array<double>")
    got = C.spectral_kernel(v, 2, scales=G.local_scales(v)) if tuned else C.spectral_kernel(v, 2, 1.0)
    assert {frozenset(r.vid % 2 for r in got.collect() if r.cluster == k) for k in (0, 1)} == {frozenset([0]), frozenset([1])}
