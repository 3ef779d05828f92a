"""Distributed power sweeps, sampled anchors, partition verdict, energy mass and other late methods."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from evenpart.functions import blocks
from evenpart.operators import clustering as C
from evenpart.operators import graphs as G
from evenpart.operators import partition as P
from evenpart.operators.power import check_power, power_sweeps
from evenpart.sources.planted import PlantedReader, RowRange


@pytest.fixture(scope="module")
def planted(spark):
    v, e = G.planted(spark, 96, 3, 0.9, 0.1)
    return v, e.cache(), P.initial_partition(v, 3).cache()


def _blocks(planted):
    _, e, a = planted
    cls = {r["vid"]: r["cls"] for r in a.collect()}
    w = {(r["src"], r["dst"]): r["w"] for r in e.collect()}
    members = {k: sorted(v for v, c in cls.items() if c == k) for k in sorted(set(cls.values())) if k}
    return members, {(s, t): np.array([[w.get((min(i, j), max(i, j)), 0.0) for j in members[t]] for i in members[s]]) for s in members for t in members if s < t}


def test_power_sweeps_reach_the_first_singular_value(planted):
    _, e, a = planted
    _, dense = _blocks(planted)
    stats = power_sweeps(e, a, sweeps=25, tol=1e-4)[0].collect()
    assert len(stats) == len(dense)
    for r in stats:
        w = dense[r["s"], r["t"]]
        top = np.linalg.svd(w - w.mean())[1][0]
        assert r["sigma"] <= top * (1 + 1e-9) and r["sigma"] >= 0.97 * top


def test_power_witness_has_its_gap(planted):
    _, e, a = planted
    members, dense = _blocks(planted)
    got = check_power(e, a, 0.3, sweeps=12).collect()
    verdicts = [r for r in got if r["status"] is not None]
    assert sorted((r["s"], r["t"]) for r in verdicts) == sorted(dense)
    for r in verdicts:
        w, exact = dense[r["s"], r["t"]], blocks.sigma(dense[r["s"], r["t"]], 0.3)
        assert r["status"] == exact[0] == blocks.WITNESS and abs(r["d"] - w.mean()) < 1e-9
        side = {x: [q["vid"] for q in got if q["status"] is None and (q["s"], q["t"], q["side"]) == (r["s"], r["t"], x)] for x in (r["s"], r["t"])}
        rows, cols = np.isin(members[r["s"]], side[r["s"]]), np.isin(members[r["t"]], side[r["t"]])
        assert rows.any() and cols.any() and abs(abs(w[rows][:, cols].mean() - w.mean()) - r["gap"]) < 1e-9
        assert r["gap"] >= 0.5 * exact[1]


def test_power_calls_constant_blocks_uniform(spark):
    v = spark.range(12).select(F.col("id").alias("vid"))
    e = v.select(F.col("vid").alias("src")).join(v.select(F.col("vid").alias("dst")), F.col("src") < F.col("dst")).withColumn("w", F.lit(1.0))
    got = check_power(e, P.initial_partition(v, 2), 0.3, sweeps=3).collect()
    assert [(r["status"], r["vid"]) for r in got] == [(blocks.UNIFORM, None)]
    none = check_power(e.where("src < 0"), P.initial_partition(v, 2), 0.3, sweeps=3).collect()
    assert [(r["status"], r["d"]) for r in none] == [(blocks.UNIFORM, 0.0)]


def test_noise_adjusted_beyond_a_block(planted, monkeypatch):
    """Classes that fill no block get the raised edge too: the verdicts are those of the dense check."""
    from evenpart.operators import large

    _, e, a = planted
    for adjust in (False, True):
        want = {(r.s, r.t): r.status for r in P.check_pairs(a, 0.3, "sigma", e, noise_adjust=adjust).where("status is not null").collect()}
        monkeypatch.setattr(large, "SIDE", 8)
        got = {(r.s, r.t): r.status for r in P.check_pairs(a, 0.3, "sigma", e, noise_adjust=adjust).where("status is not null").collect()}
        monkeypatch.undo()
        assert got == want and len(got) > 0


def test_spectral_norm_of_the_exact_kernel_beyond_a_block(spark, monkeypatch):
    """Sweeps over tiles of the Gaussian kernel give the verdicts and densities of the dense check."""
    from evenpart.operators import large

    rng = np.random.default_rng(4)
    v = spark.createDataFrame([(i, [float(z) for z in rng.normal(size=2) + 3 * (i % 2)]) for i in range(90)], "vid long, x array<double>").cache()
    a = P.initial_partition(v, 3).cache()
    read = lambda: {(r.s, r.t): (r.status, round(r.d, 9)) for r in P.check_pairs(a, 0.45, "sigma", None, v, 1.5).where("status is not null").collect()}
    want = read()
    monkeypatch.setattr(large, "SIDE", 8)
    found = P.check_pairs(a, 0.45, "sigma", None, v, 1.5).cache()
    assert read() == want and len(want) == 3
    bad = {p for p, (status, _) in want.items() if status == blocks.WITNESS}
    assert bad and {(r.s, r.t) for r in found.where("vid is not null").collect()} == bad


def test_density_without_blocks_is_the_same(planted):
    _, e, a = planted
    _, dense = _blocks(planted)
    got = {(r["s"], r["t"]): r["d"] for r in P.check_pairs(a, 0.3, "density", e).collect()}
    assert got.keys() == dense.keys() and all(abs(got[p] - dense[p].mean()) < 1e-12 for p in got)


def test_sampled_anchors():
    rng = np.random.default_rng(3)
    w = np.kron(np.eye(2), np.ones((20, 20)))
    assert blocks.codegree(w, 0.3, anchors=40)[:2] == blocks.codegree(w, 0.3)[:2]
    status, gap, rows, cols = blocks.codegree(w, 0.3, anchors=4)
    assert status == blocks.WITNESS and abs(abs(w[rows][:, cols].mean() - 0.5) - gap) < 1e-12
    flat = np.full((20, 20), 0.5) + rng.normal(size=(20, 20)) * 1e-6
    assert blocks.codegree(flat, 0.3)[0] == blocks.UNIFORM and blocks.codegree(flat, 0.3, anchors=4)[0] == blocks.UNVERIFIED


def test_energy_mass_grows_under_refinement(spark, planted):
    v, e, _ = planted
    coarse = P.initial_partition(v, 2)
    fine = coarse.withColumn("cls", (F.col("cls") * 2 - (F.col("vid") % 2)).cast("int"))
    low, high = (P.energy_mass(e, a).first()["energy_mass"] for a in (coarse, fine))
    assert 0 < low <= high <= 1


def test_partition_verdict(spark):
    a = spark.createDataFrame([(0, 1), (1, 2), (2, 0)], "vid long, cls int")
    bad = spark.createDataFrame([(1, 2, blocks.WITNESS)], "s int, t int, status string")
    assert tuple(P.partition_is_uniform(a, bad, 0.34).first()) == (2, 1, 1, True)
    assert tuple(P.partition_is_uniform(a, bad, 0.2).first()) == (2, 1, 1, False)


def test_centroids_then_spectral(spark):
    rng = np.random.default_rng(5)
    rows = [(i, [float(z) for z in rng.normal(size=2) + 20 * (i % 2)], str(i % 2)) for i in range(80)]
    v = spark.createDataFrame(rows, "vid long, x array<double>, y string")
    assert C.quality(C.confusion(C.spectral_on_centroids(v, 2, 8), v))["accuracy"] == 100


def test_planted_ranges_cover_every_row_once():
    reader = PlantedReader({"n": "50", "blocks": "5", "tasks": "7"})
    parts = reader.partitions()
    assert [p.lo for p in parts] + [50] == [0] + [p.hi for p in parts]
    whole = list(reader.read(RowRange(0, 50)))
    assert sorted(r for p in parts for r in reader.read(p)) == sorted(whole)
    with pytest.raises(ValueError):
        PlantedReader({"n": "5", "blocks": "9"})
