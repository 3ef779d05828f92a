"""Loops go on to the least class size of their rule; a cap on classes raises that size."""

import numpy as np
from pyspark.sql import functions as F

from evenpart.operators import local
from evenpart.operators import partition as P


def _graph(n=600):
    w = np.triu(np.random.default_rng(2).integers(0, 2, (n, n)), 1).astype(float)
    return w + w.T


def test_local_loop_ends_at_h():
    _, k, trace = local.partition(_graph(), 0.3, 2, h=2, min_parts=10**6, checker="sigma")
    assert trace[-1]["stop"] == "class_too_small" and trace[-1]["m"] < 2 <= trace[-2]["m"] and k > 256


def test_cap_raises_h():
    _, k, trace = local.partition(_graph(), 0.3, 2, h=2, min_parts=10**6, checker="sigma", max_classes=16)
    assert trace[-1]["stop"] == "class_too_small" and trace[-2]["m"] < 2 * 38 and k <= 17


def test_distributed_loop_passes_512_classes(spark):
    v = spark.range(1200).select(F.col("id").alias("vid"))
    e = v.where("vid < 40").select(F.col("vid").alias("src"), (F.col("vid") + 600).alias("dst"), F.lit(1.0).alias("w"))
    got = P.practical_loop(v, 0.3, 24, 10, "density", e, min_parts=10**6)
    assert got.trace[-1]["stop"] == "class_too_small" and got.k >= 576
