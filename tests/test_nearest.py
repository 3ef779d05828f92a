"""The pruned search gives the rows of the block search, ties and copies included, and shuffles nothing but the queries."""

import contextlib
import io

import numpy as np
import pytest
from pyspark.sql import functions as F

from evenpart.operators import clustering as C
from evenpart.operators import graphs as G


def _points(spark, kind):
    rng = np.random.default_rng(4)
    x = {"normal": rng.normal(size=(300, 3)), "grid": rng.integers(0, 4, (300, 3)).astype(float), "copies": np.repeat(rng.normal(size=(6, 3)), 50, axis=0)}[kind]
    return spark.createDataFrame([(int(v), [float(a) for a in p]) for v, p in zip(rng.permutation(300) * 3, x, strict=True)], "vid long, x array<double>").repartition(3)


@pytest.mark.parametrize("kind", ["normal", "grid", "copies"])
def test_rows_of_the_block_search(spark, monkeypatch, kind):
    monkeypatch.setattr(G, "BOX", 16)
    monkeypatch.setattr(G, "ASKED", 50)
    v = _points(spark, kind)
    rows = lambda df: sorted((r.qid, r.vid, r["rank"], round(r.dist, 9)) for r in df.collect())
    for k in (1, 7, 400):
        want = rows(G._knn_blocks(v, v, k))
        assert rows(G.knn(v, v, k)) == want
    some = v.where("vid % 2 = 0")
    assert rows(G.knn(v, some, 5)) == rows(G._knn_blocks(v, some, 5))


def test_points_are_not_sent_to_every_block(spark):
    v = _points(spark, "normal")
    text = io.StringIO()
    with contextlib.redirect_stdout(text):
        G.knn(v, v, 5).explain()
    assert "Generate" not in text.getvalue() and "Window" not in text.getvalue() and text.getvalue().count("Exchange hashpartitioning") == 1


def test_edges_cross_one_exchange_for_all_products(spark, monkeypatch):
    rng = np.random.default_rng(5)
    x = np.concatenate([rng.normal(m, 0.4, (40, 2)) for m in ((0, 0), (6, 0), (0, 6))])
    v = spark.createDataFrame([(5 * i, [float(a) for a in p]) for i, p in enumerate(x)], "vid long, x array<double>")
    e = G.knn_edges(G.knn(v, v, 6)).select("src", "dst", F.exp(-F.col("dst") * 0 - F.col("dist") ** 2).alias("w"))
    want = C._spectral_joined(e, v, 3, 42, 30)
    groups = lambda df: {frozenset(r.vid for r in df.collect() if r.cluster == k) for k in range(3)}
    want = groups(want)
    monkeypatch.setattr(C, "_spectral_joined", None)
    assert groups(C.spectral(e, v, 3)) == want
