"""The distributed loops, fit and baselines against their in-memory twins."""

import hashlib
import json

import numpy as np
import pytest
from pyspark.sql import functions as F

from evenpart.functions import blocks
from evenpart.operators import clustering as C
from evenpart.operators import grids, large, local
from evenpart.operators import graphs as G
from evenpart.operators import partition as P

N = 150


@pytest.fixture(scope="module")
def world(spark):
    rng = np.random.default_rng(21)
    y = np.arange(N) % 3
    x = 4.0 * np.eye(3)[y] + rng.normal(size=(N, 3))
    vids = np.arange(N) * 7 + 3
    v = spark.createDataFrame([(int(i), [float(a) for a in r], str(t)) for i, r, t in zip(vids, x, y, strict=True)], "vid long, x array<double>, y string").cache()
    w = blocks.gaussian(x, x, 2.0)
    np.fill_diagonal(w, 0)
    b = (w > 0.3).astype(float)
    edges = spark.createDataFrame([(int(vids[i]), int(vids[j]), 1.0) for i in range(N) for j in range(i + 1, N) if b[i, j]], "src long, dst long, w double").cache()
    return vids, x, y, v, w, b, edges


@pytest.mark.parametrize("options", [{"pick": "random"}, {"pick": "first", "recycle": "global", "checker": "sigma"}, {"pick": "max_gap", "recycle": "none", "keep": "last_valid", "stop_rule": "k_squared"}])
def test_practical_loop(world, options):
    vids, x, _, v, w, b, edges = world
    for a, graph in ((w, {"sigma": 2.0}), (b, {"edges": edges})):
        cls, k, trace = local.partition(a, 0.35, 2, 9, vids=vids, min_parts=5, **options)
        got = P.practical_loop(v, 0.35, 2, 9, min_parts=5, **graph, **options)
        assert got.k == k and {r.vid: r.cls for r in got.assign.collect()} == dict(zip(vids.tolist(), cls.tolist(), strict=True))
        for key in ("iter", "k", "m", "residue", "pairs", "bad", "required", "stop"):
            assert [r[key] for r in got.trace] == [r[key] for r in trace]
        assert np.allclose([r["energy"] for r in got.trace], [r["energy"] for r in trace])
    assert len(trace) >= 2


def test_weights_outside_the_unit_range_are_refused(world):
    with pytest.raises(ValueError, match="scale them"):
        P.practical_loop(world[3], 0.35, 2, 9, edges=world[6].withColumn("w", F.lit(3.0)))


def _full_twin(b, checker, eps, parts, rounds):
    vids = np.arange(len(b))
    cls, k, out = local.initial(vids, parts, 42), parts, []
    while True:
        at = [np.flatnonzero(cls == s) for s in range(1, k + 1)]
        bad, marks = 0, {}
        for s in range(k):
            for t in range(s + 1, k):
                status, _, ra, cb = blocks.check(b[np.ix_(at[s], at[t])], eps, checker)
                bad += status != blocks.UNIFORM
                if status == blocks.WITNESS:
                    for i in at[s][ra]:
                        marks.setdefault(int(i), set()).add(t + 1)
                    for i in at[t][cb]:
                        marks.setdefault(int(i), set()).add(s + 1)
        out.append((k, bad))
        if bad <= eps * k * k or len(out) >= rounds:
            return cls, out
        m, new, place = len(at[0]) // 4**k, np.zeros(len(b), int), 0
        rank = local.order_of(vids, 42)
        for s in range(k):
            cells: dict = {}
            for i in at[s]:
                cells.setdefault(",".join(map(str, sorted(marks.get(int(i), ())))), []).append(int(i))
            for name in sorted(cells):
                members = sorted(cells[name], key=lambda i: rank[i])
                for lo in range(0, len(members) // m * m, m):
                    place += 1
                    new[members[lo : lo + m]] = place
        cls, k = new, place


@pytest.mark.parametrize("checker", ["codegree", "sigma"])
def test_full_loop_reaches_a_second_round(spark, checker):
    v, e = G.planted(spark, 96, 2, 0.9, 0.1)
    b = np.zeros((96, 96))
    for r in e.collect():
        b[r.src, r.dst] = b[r.dst, r.src] = 1
    want, rounds = _full_twin(b, checker, 0.2, 2, 2)
    got = P.full_loop(v, 0.2, 2, checker, e, max_rounds=2)
    assert len(rounds) == 2 and [(r["k"], r["bad"]) for r in got.trace] == rounds and got.trace[-1]["stop"] in ("few_bad_pairs", "max_rounds")
    assert [r.cls for r in got.assign.orderBy("vid").collect()] == want.tolist()


def test_fit_votes_saves_and_predicts(spark, world, tmp_path):
    vids, x, y, v, w, _, _ = world
    options = {"pick": "max_gap", "keep": "last_valid"}
    want, k, _ = local.fit_predict(x, w, 3, 0.35, 4, vids=vids, h=9, **options)
    m = C.fit(v, 3, 0.35, 4, 9, sigma=2.0, **options)
    assert m.partition.k == k and {r.vid: r.cluster for r in m.labels.collect()} == dict(zip(vids.tolist(), want.tolist(), strict=True))
    m.save(str(tmp_path / "m"))
    back = C.load(spark, str(tmp_path / "m"))
    assert back.partition.k == k and back.partition.trace == m.partition.trace and back.classes.tolist() == m.classes.tolist()
    near = v.withColumn("vid", F.col("vid") + 100_000)
    assert {r.vid: r.cluster for r in back.predict(near).collect()} == {r.vid: r.cluster for r in m.predict(near).collect()}
    # a point's own twin is its nearest neighbour
    assert {r.vid - 100_000: r.cluster for r in m.predict(near, 1).collect()} == dict(zip(vids.tolist(), want.tolist(), strict=True))


def test_fit_beyond_a_block_on_features(spark, world, monkeypatch):
    vids, x, y, v, _, _, _ = world
    monkeypatch.setattr(large, "SIDE", 30)
    monkeypatch.setattr(large, "ANCHORS", 20)
    for checker in ("codegree", "sigma"):
        m = C.fit(v, 3, 0.35, 2, 9, sigma=2.0, kernel="features", dims=64, checker=checker, pick="max_gap")
        assert m.labels.count() == N and m.partition.k >= 4 and C.quality(C.confusion(m.labels, v))["accuracy"] > 50


def test_grid_gives_the_same_rows_on_both_sides_of_its_limit(world, monkeypatch):
    v = world[3]
    ours = {"eps": 0.35, "fanout": 4, "c": 3, "h": 9, "pick": "max_gap", "keep": "last_valid"}
    settings = [ours, {**ours, "knn": "log_n", "pick": "random"}, {**ours, "self_tuned": True, "method": "dominant"}, {"method": "random_partition", "k": 12, "c": 3}, {"method": "landmark", "sample": 40, "c": 3}, {"method": "random_labels", "c": 3}]
    inside = {r.setting: r for r in grids.grid(v, settings).collect()}
    monkeypatch.setattr(grids, "MOST_POINTS", 50)
    outside = {r.setting: r for r in grids.grid(v, settings).collect()}
    assert set(inside) == set(outside) == {json.dumps(s, sort_keys=True) for s in settings}
    for key, r in inside.items():
        assert (r.k, r.iters, r.stop, r.bad, r.required, r.labels) == (outside[key].k, outside[key].iters, outside[key].stop, outside[key].bad, outside[key].required, outside[key].labels), key
        assert r.accuracy == pytest.approx(outside[key].accuracy)


def test_baselines_find_blobs(world):
    vids, x, y, v, w, _, edges = world
    found = {
        "spectral": C.spectral(edges, v, 3), "landmark": C.landmark(v, 3, 60), "kmeans": C.kmeans(v, 3), "gmm": C.gmm(v, 3), "lloyd": C.lloyd(v, 3), "centroids": C.spectral_on_centroids(v, 3, 20),
        "power": C.power_iteration(G.affinity_pairs(v, sigma=2.0), 3),
    }
    scores = {name: C.quality(C.confusion(labels, v))["accuracy"] for name, labels in found.items()}
    # EM with full covariances starts at random and may end with two blobs in one component
    assert all(scores[name] > 85 for name in ("spectral", "landmark", "kmeans", "lloyd", "centroids")) and scores["gmm"] > 60 and scores["power"] > 33, scores
    assert C.quality(C.confusion(C.random_labels(v, 3), v))["accuracy"] < 60


def test_order_keys_agree(spark):
    rows = spark.range(50).select(F.col("id").alias("vid"), P.order_key(F.col("id"), 9).alias("k")).collect()
    assert all(r.k == hashlib.md5(f"{r.vid}:9".encode()).hexdigest() for r in rows)
    ids = spark.createDataFrame([(int(i),) for i in np.random.default_rng(1).integers(0, 10**8, 400)] + [(2**40 + i,) for i in range(30)], "vid long").distinct()
    ranked = sorted((r.vid, r["rank"]) for r in P.rank_by_number(ids, "vid").collect())
    assert [r for _, r in ranked] == list(range(len(ranked)))


def test_median_scale(world, monkeypatch):
    _, x, _, v, *_ = world
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))[np.triu_indices(N, 1)]
    assert C.median_scale(v) == pytest.approx(np.median(d), rel=1e-2)
    monkeypatch.setattr(C, "ALL_PAIRS", 10)
    monkeypatch.setattr(C, "SCALE_GROUP", 50)
    assert C.median_scale(v) == pytest.approx(np.median(d), rel=0.1)
