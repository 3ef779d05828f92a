"""User-defined functions: only where the inner step is a matrix product, or a table is made from numbers."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from evenpart.functions.blocks import theory


def anchor_distance(anchors: list[list[float]]):
    """Column function: distance of ``x`` to the nearest anchor, a block of rows at a time."""
    a = np.asarray(anchors, dtype=float)

    @F.pandas_udf("double")
    def nearest(x: pd.Series) -> pd.Series:
        if not len(x):
            return pd.Series([], dtype="float64")
        rows = np.stack(x.to_list())
        d2 = (rows**2).sum(1)[:, None] + (a**2).sum(1)[None] - 2 * rows @ a.T
        return pd.Series(np.sqrt(np.maximum(d2, 0).min(1)))

    return nearest


def entropy_of_counts(column: str):
    """Aggregate: entropy of a group's counts (few rows a group: make the counts first)."""

    @F.pandas_udf("double")
    def entropy(n: pd.Series) -> float:
        p = n[n > 0] / n.sum()
        return float(-(p * np.log(p)).sum()) + 0.0

    return entropy(column)


@F.udtf(returnType="eps double, fanout int")
class ExpandGrid:
    """``steps`` values of eps, evenly spaced, with every fanout."""

    def eval(self, eps_lo: float, eps_hi: float, steps: int, l_lo: int, l_hi: int) -> Iterator[tuple[float, int]]:
        for i in range(steps):
            for fanout in range(l_lo, l_hi + 1):
                yield round(eps_lo + i * (eps_hi - eps_lo) / max(steps - 1, 1), 6), fanout


@F.udtf(returnType="gamma_a double, gamma_b double, witness_gap double, least_k int, in_range boolean")
class TheoryTable:
    """Constants of the lemmas at (eps, classes, vertices)."""

    def eval(self, eps: float, k: int, n: int) -> Iterator[tuple]:
        t = theory(eps, k, n)
        yield t["gamma_a"], t["gamma_b"], t["witness_gap"], t["least_k"], t["in_range"]


def register(spark: SparkSession) -> None:
    """Make the table functions and the SQL functions known to the session."""
    spark.udtf.register("expand_grid", ExpandGrid)
    spark.udtf.register("theory_table", TheoryTable)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION ep_density(e DOUBLE, na DOUBLE, nb DOUBLE) RETURNS DOUBLE RETURN e / greatest(na * nb, 1)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION ep_energy(d DOUBLE, k DOUBLE) RETURNS DOUBLE RETURN d * d / (k * k)")
