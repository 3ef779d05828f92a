"""The spectral-norm check without dense blocks: one pass over the weights advances every pair of classes.

A vertex holds one coordinate per other class, and an edge between two classes belongs to one pair only, so a sweep
is one join of the edges with the coordinates and one aggregation.  Nothing here depends on the size of a class.

A graph answers ``stats`` (as ``pair_density``), ``push`` (vid, other, push: the weights times the coordinates of the other
class) and ``cells`` (s, t, i, j, e: the weight between slices).  ``Links`` joins edges; ``large.Gaussian`` makes tiles of the
kernel anew in every sweep.
"""

from __future__ import annotations

from functools import cached_property

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenpart.functions import blocks
from evenpart.operators.graphs import md5_coin
from evenpart.operators.partition import between_classes, pair_density
from evenpart.plans.scratch import cut

#: Tables of a row per ordered pair of classes are sent to all tasks up to this many rows, and shuffled beyond.
MOST_SENT = 1_000_000
#: Level sets are read off this many slices of a side.
SLICES = 16


def _crossing(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """(vid, cls, near, other, w): every edge between two classes, from both of its ends."""
    e = between_classes(edges, assign.where("cls > 0")).withColumn("w", F.col("w").cast("double"))
    one = e.select(F.col("src").alias("vid"), F.col("ca").alias("cls"), F.col("dst").alias("near"), F.col("cb").alias("other"), "w")
    return one.union(e.select("dst", "cb", "src", "ca", "w"))


class Links:
    """Weights are rows (src, dst, w)."""

    def __init__(self, edges: DataFrame, assign: DataFrame) -> None:
        self._links, self._stats = (edges, assign), cut(pair_density(edges, assign))

    @cached_property
    def crossing(self) -> DataFrame:
        return cut(_crossing(*self._links))  # not written where no pair needs a sweep

    def most_degrees(self, pairs: DataFrame) -> DataFrame:
        """(s, t, side, most): the largest sum of the sizes of a vertex's weights into the other class of each of these pairs (s, t)."""
        edges, assign = self._links
        e = between_classes(edges, assign.where("cls > 0")).withColumns({"s": F.least("ca", "cb"), "t": F.greatest("ca", "cb")}).join(F.broadcast(pairs.select("s", "t")), ["s", "t"])  # at most MOST_SENT rows
        both = e.select("s", "t", F.col("ca").alias("side"), F.col("src").alias("vid"), "w").union(e.select("s", "t", "cb", "dst", "w"))
        return both.groupBy("s", "t", "side", "vid").agg(F.sum("w").alias("deg")).groupBy("s", "t", "side").agg(F.max("deg").alias("most"))

    def stats(self) -> DataFrame:
        return self._stats

    def push(self, vec: DataFrame) -> DataFrame:
        far = vec.select(F.col("vid").alias("near"), F.col("other").alias("cls"), "val")
        return self.crossing.join(far, ["near", "cls"]).groupBy("vid", "other").agg(F.sum(F.col("w") * F.col("val")).alias("push"))

    def cells(self, sliced: DataFrame) -> DataFrame:
        near = sliced.select(F.col("vid").alias("near"), F.col("cls").alias("other"), F.col("other").alias("cls"), F.col("slice").alias("far_slice"))
        met = self.crossing.where("cls < other").join(sliced, ["vid", "cls", "other"]).join(near, ["near", "cls", "other"])
        return met.groupBy(F.col("cls").alias("s"), F.col("other").alias("t"), F.col("slice").alias("i"), F.col("far_slice").alias("j")).agg(F.sum("w").alias("e"))


def power_sweeps(graph, assign: DataFrame, sweeps: int = 20, tol: float = 1e-3, seed: int = 42) -> tuple[DataFrame, DataFrame, Links]:
    """(stats with sigma and moved, coordinates, graph) after at most ``sweeps`` sweeps; ``graph`` may be rows of edges.

    ``sigma`` is the length a unit vector has after the centred block was applied to it, so it never exceeds the first
    singular value; ``moved`` is its relative change in the last sweep.
    """
    graph = Links(graph, assign) if isinstance(graph, DataFrame) else graph
    stats = graph.stats()
    pairs = stats.select(F.col("s").alias("cls"), F.col("t").alias("other"), "d").union(stats.select("t", "s", "d"))
    k = assign.agg(F.max("cls")).first()[0] or 0
    sent = F.broadcast if k * (k - 1) <= MOST_SENT else (lambda df: df)
    grid = assign.where("cls > 0").join(F.broadcast(pairs.select("cls", "other")) if k * (k - 1) <= MOST_SENT else pairs.select("cls", "other"), "cls")
    raw = grid.select("vid", "cls", "other", (md5_coin(F.col("vid"), F.col("other"), F.lit(seed)) - 0.5).alias("val"))
    length = raw.groupBy("cls", "other").agg(F.sqrt(F.sum(F.col("val") * F.col("val"))).alias("len"))
    vec = cut(raw.join(sent(length), ["cls", "other"]).select("vid", "cls", "other", (F.col("val") / F.col("len")).alias("val")))
    before, last = None, None
    for _ in range(sweeps):
        sums = vec.groupBy("cls", "other").agg(F.sum("val").alias("sum")).select(F.col("other").alias("cls"), F.col("cls").alias("other"), "sum")
        shift = sums.join(pairs, ["cls", "other"]).select("cls", "other", (F.col("d") * F.col("sum")).alias("shift"))
        new = vec.join(graph.push(vec), ["vid", "other"], "left").join(sent(shift), ["cls", "other"])
        new = cut(new.select("vid", "cls", "other", (F.coalesce("push", F.lit(0.0)) - F.col("shift")).alias("val")))
        length = cut(new.groupBy("cls", "other").agg(F.sqrt(F.sum(F.col("val") * F.col("val"))).alias("len")))
        # a side that vanishes keeps its zeros: its pair has no uneven direction left
        vec = new.join(sent(length), ["cls", "other"]).select("vid", "cls", "other", F.when(F.col("len") > 1e-12, F.col("val") / F.col("len")).otherwise(0.0).alias("val"))
        before, last = last, length.groupBy(F.least("cls", "other").alias("s"), F.greatest("cls", "other").alias("t")).agg(F.max("len").alias("sigma"))
        if before is not None:
            last = cut(last.join(before.select("s", "t", F.col("sigma").alias("_b")), ["s", "t"]).withColumn("moved", F.abs(F.col("sigma") - F.col("_b")) / F.greatest("sigma", F.lit(1e-12))).drop("_b"))
            if (last.agg(F.max("moved")).first()[0] or 0.0) <= tol:
                break
    if last is None or "moved" not in last.columns:
        raise ValueError("at least two sweeps are needed")
    return stats.join(last, ["s", "t"]), cut(vec), graph


def _level_sets(stats: DataFrame, vec: DataFrame, graph, bad: DataFrame, floor: float) -> tuple[DataFrame, DataFrame]:
    """Best pair of level sets of the coordinates of each bad pair, from sums over slices of both sides.

    Each side is cut into ``SLICES`` at its quantiles; a pair is then a small table of sums, whose corners are the
    level sets of both signs.
    """
    both = bad.select(F.col("s").alias("cls"), F.col("t").alias("other")).union(bad.select("t", "s"))
    asked = vec.join(both, ["cls", "other"], "left_semi")
    cuts = asked.groupBy("cls", "other").agg(F.percentile_approx("val", F.array(*[F.lit(i / SLICES) for i in range(1, SLICES)]), F.lit(1000)).alias("cuts"))
    sliced = cut(asked.join(cuts, ["cls", "other"]).select("vid", "cls", "other", F.size(F.filter("cuts", lambda c: c < F.col("val"))).alias("slice")))
    sums = graph.cells(sliced)
    sizes = sliced.groupBy(F.least("cls", "other").alias("s"), F.greatest("cls", "other").alias("t"), (F.col("cls") < F.col("other")).alias("first"), "slice").agg(F.count("*").alias("n"))
    count = lambda first: sizes.where("first" if first else "not first").select("s", "t", F.col("slice").alias("i" if first else "j"), F.col("n").alias("na" if first else "nb"))
    cells = count(True).join(count(False), ["s", "t"]).join(sums, ["s", "t", "i", "j"], "left").join(stats.select("s", "t", "d"), ["s", "t"])
    cells = cells.select("s", "t", "i", "j", "na", "nb", F.coalesce("e", F.lit(0.0)).alias("e"), "d")

    def corners(f: pd.DataFrame) -> pd.DataFrame:  # SLICES x SLICES rows
        e, na, nb = np.zeros((SLICES, SLICES)), np.zeros(SLICES), np.zeros(SLICES)
        i, j = f["i"].to_numpy(), f["j"].to_numpy()
        e[i, j], na[i], nb[j] = f["e"], f["na"], f["nb"]
        d, best = float(f["d"].iloc[0]), (-1.0, 0, 0, 0, 0)
        for up in (False, True):
            for right in (False, True):
                turn = lambda m: m[:: -1 if up else 1] if m.ndim == 1 else m[:: -1 if up else 1, :: -1 if right else 1]  # noqa: E731, B023
                ca, cb = turn(na).cumsum(), (nb[::-1] if right else nb).cumsum()
                area = np.outer(ca, cb)
                gap = np.where((ca[:, None] >= floor * na.sum()) & (cb[None] >= floor * nb.sum()) & (area > 0), np.abs(turn(e).cumsum(0).cumsum(1) / np.maximum(area, 1) - d), -1)
                a, b = np.unravel_index(int(gap.argmax()), gap.shape)
                if gap[a, b] > best[0] + 1e-12:
                    best = (float(gap[a, b]), *((SLICES - 1 - a, SLICES - 1) if up else (0, a)), *((SLICES - 1 - b, SLICES - 1) if right else (0, b)))
        return pd.DataFrame([(f["s"].iloc[0], f["t"].iloc[0], *best)], columns=["s", "t", "gap", "a0", "a1", "b0", "b1"])

    chosen = cut(cells.groupBy("s", "t").applyInPandas(corners, "s int, t int, gap double, a0 int, a1 int, b0 int, b1 int"))
    return chosen, sliced


def _bounds(graph, edge: Column) -> DataFrame:
    """The graph's stats with ``below``: the norm of the centred block is below ``edge`` for certain, without a sweep.

    It is at most its Frobenius norm, and at most the root of the largest row and column sums plus that of the constant block.
    Weights that are not negative have a largest sum of at least the mean one, so denser pairs are not asked for it.
    """
    stats, cells = graph.stats(), F.col("na") * F.col("nb")
    norm = F.sqrt(F.greatest(F.col("e2") - cells * F.col("d") * F.col("d"), F.lit(0.0)))
    found = stats.withColumns({"edge": edge, "below": F.coalesce(norm < edge, F.lit(False))})
    open_ = found.where(~F.col("below") & (2 * F.col("d") * F.sqrt(cells) < F.col("edge")))
    if not isinstance(graph, Links) or not 0 < open_.count() <= MOST_SENT:
        return found
    most = graph.most_degrees(open_).groupBy("s", "t").agg(F.sqrt(F.product("most")).alias("most"), F.count("*").alias("sides"))
    found = found.join(cut(most), ["s", "t"], "left")
    thin = (F.col("sides") == 2) & (F.col("most") + F.col("d") * F.sqrt(cells) < F.col("edge"))
    return found.withColumn("below", F.col("below") | F.coalesce(thin, F.lit(False))).drop("most", "sides")


def check_power(graph, assign: DataFrame, eps: float, sweeps: int = 20, tol: float = 1e-3, margin: float = 0.05, large: float = 0.05, seed: int = 42, noise_adjust: bool = False) -> DataFrame:
    """Rows of ``check_pairs`` (s, t, status, d, gap, side, vid) by distributed power sweeps.

    ``noise_adjust`` raises the edge to the norm that coins of the pair's density would give, as ``blocks.sigma`` does.

    The estimate is a lower bound: at or above eps^3 sqrt(pq) the pair is uneven for certain.  A pair is called uniform
    only if its estimate has settled and stays ``margin`` below; anything between is UNVERIFIED.
    """
    graph = Links(graph, assign) if isinstance(graph, DataFrame) else graph
    edge = F.lit(eps**3) * F.sqrt(F.col("na") * F.col("nb"))
    if noise_adjust:
        edge = F.greatest(edge, F.lit(1.05 * 2) * F.sqrt(F.greatest(F.col("d") * (1 - F.col("d")), F.lit(0.0)) * F.col("nb")))
    bound = _bounds(graph, edge)
    if bound.where(~F.col("below")).isEmpty():
        none = F.lit(None)
        return bound.select("s", "t", F.lit(blocks.UNIFORM).alias("status"), "d", F.lit(0.0).alias("gap"), none.cast("int").alias("side"), none.cast("long").alias("vid"))
    stats, vec, graph = power_sweeps(graph, assign, sweeps, tol, seed)
    stats = stats.join(bound.select("s", "t", "below"), ["s", "t"])
    settled = F.col("below") | ((F.col("sigma") * (1 + margin) < edge) & (F.col("moved") <= tol))
    judged = cut(stats.select("s", "t", "d", (F.col("sigma") >= edge).alias("bad"), settled.alias("even")))
    chosen, sliced = _level_sets(stats, vec, graph, judged.where("bad"), max(eps**9 / 108, large))
    found = judged.join(chosen, ["s", "t"], "left").withColumn("sure", F.coalesce(F.col("bad") & (F.col("gap") >= eps**9 / 108), F.lit(False)))
    status = F.when(F.col("sure"), blocks.WITNESS).when(~F.col("bad") & F.col("even"), blocks.UNIFORM).otherwise(blocks.UNVERIFIED)
    none = F.lit(None)
    verdict = found.select("s", "t", status.alias("status"), "d", F.when(F.col("sure"), F.col("gap")).otherwise(0.0).alias("gap"), none.cast("int").alias("side"), none.cast("long").alias("vid"))
    sure = found.where("sure").select("s", "t", "a0", "a1", "b0", "b1")
    a = sliced.withColumns({"s": F.least("cls", "other"), "t": F.greatest("cls", "other")}).join(sure, ["s", "t"])
    inside = F.when(F.col("cls") == F.col("s"), F.col("slice").between(F.col("a0"), F.col("a1"))).otherwise(F.col("slice").between(F.col("b0"), F.col("b1")))
    return verdict.unionByName(a.where(inside).select("s", "t", none.cast("string").alias("status"), none.cast("double").alias("d"), none.cast("double").alias("gap"), F.col("cls").cast("int").alias("side"), "vid"))
