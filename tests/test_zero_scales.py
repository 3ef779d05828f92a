"""Self-tuned weights where copies make a local scale 0."""

from evenpart.operators import graphs as G
from evenpart.queries import methods as M


def test_points_among_copies(spark):
    rows = [(i, [0.0, 0.0]) for i in range(12)] + [(100 + i, [5.0 + i, 1.0]) for i in range(10)]
    v = spark.createDataFrame(rows, "vid long, x array<double>")
    for edges in (M._knn_graph(v, True), G.affinity_pairs(v, scales=G.local_scales(v))):
        got = edges.collect()
        assert got and all(0 <= r.w <= 1 for r in got)
        assert all(r.w == 1 for r in got if r.dst < 12)
        assert all(r.w == 0 for r in got if r.src < 12 <= r.dst)
