"""Pair checks for classes that fill no single block: by tiles, by joins over edges, or by sums of features.

Every source answers the same four questions about all pairs s < t at once, and no task ever holds more than two tiles:

* ``degrees``: (s, t, side, vid, deg), the weight of each vertex of class ``side`` into the other class of its pair;
* ``squares``: (s, t, e2), the sum of squared weights;
* ``anchor_sums``: (s, t, side, y, size_a, size_b, inner) for anchors y of class ``side``, or for those of all that decide
  their direction: how many vertices of the other
  class are y's neighbours above the density, how many vertices of its own class share too many neighbours with y, and the
  weight between these two sets;
* ``anchor_sets``: (s, t, side, vid), the members of both sets of one anchor a pair.

``Edges`` joins the edges with themselves, ``Gaussian`` multiplies tiles of the kernel (quadratic work, in as many tasks as
there are pairs of tiles), ``Inner`` uses that weights are inner products: all answers are then sums over features, one
pass over the vertices each.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import cached_property

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from evenpart.functions import blocks
from evenpart.operators.graphs import md5_coin
from evenpart.plans.scratch import cut

#: Members of a tile.
SIDE = 4096
#: Anchors of a class that ``Inner`` asks in one pass over the points.
ANCHORS = 1024
#: Numbers that all tasks are sent at once (features of anchors, sums of classes).
MOST_NUMBERS = 32_000_000
#: Points whose features are sent to all tasks, and members that a task asks at a time; larger tables meet tile by tile.
MOST_POINTS, LOT = 1_000_000, 1024
#: Members of the other class whose products are summed in single precision; lots are summed in double precision.
STEP = 512
#: Tasks of a pass over all anchors at most.
MOST_TASKS = 2048
#: Anchors that are asked by passes over the edges, and their links that are sent to all tasks.
FEW_ASKED, MOST_LINKS = 10_000, 1_000_000
#: Level sets of the spectral check are read off this many slices of a side.
SLICES = 16


def choose_anchors(placed: DataFrame, anchors: str | int, seed: int = 42) -> DataFrame:
    """(cls, y): all members, or the ``anchors`` members of each class with the smallest md5 coin."""
    if anchors in ("all", "typical"):
        return placed.select("cls", F.col("vid").alias("y"))
    # a coin of its own: classes of a start follow the order of the plain one.  Each task keeps its smallest before the shuffle
    few = placed.withColumn("coin", md5_coin(F.col("vid"), F.lit(f"anchor:{seed}")))
    return few.withColumn("r", F.row_number().over(Window.partitionBy("cls").orderBy("coin", "vid"))).where(F.col("r") <= anchors).select("cls", F.col("vid").alias("y"))


def spread_anchors(placed: DataFrame, anchors: int) -> DataFrame:
    """(cls, y): ``anchors`` members of each class, evenly spread over its ascending ids, as ``blocks.codegree`` takes columns."""
    sizes = placed.groupBy("cls").agg(F.count("*").alias("n")).collect()  # a row a class
    at = [(r["cls"], int(i)) for r in sizes for i in np.unique(np.linspace(0, r["n"] - 1, min(anchors, r["n"])).astype(int))]
    ranked = placed.select("cls", F.col("vid").alias("y"), (F.row_number().over(Window.partitionBy("cls").orderBy("vid")) - 1).alias("r"))
    return ranked.join(F.broadcast(placed.sparkSession.createDataFrame(at, "cls int, r int")), ["cls", "r"]).select("cls", "y")


def directed(pairs: DataFrame) -> DataFrame:
    """(s, t, side, far) twice for every (s, t): once for the members of either class."""
    one = pairs.select("s", "t", F.col("s").alias("side"), F.col("t").alias("far"))
    return one.union(pairs.select("s", "t", F.col("t").alias("side"), F.col("s").alias("far")))


class Edges:
    """Weights are rows (src, dst, w)."""

    def __init__(self, placed: DataFrame, edges: DataFrame) -> None:
        self.placed, self.edges = placed, edges

    def _both_ends(self) -> DataFrame:
        """Every edge between two classes from both of its ends."""
        from evenpart.operators.partition import between_classes

        e = between_classes(self.edges, self.placed).withColumn("w", F.col("w").cast("double"))
        pair = [F.least("ca", "cb").alias("s"), F.greatest("ca", "cb").alias("t")]
        one = e.select(*pair, F.col("ca").alias("side"), F.col("src").alias("vid"), F.col("dst").alias("near"), "w")
        return one.union(e.select(*pair, "cb", "dst", "src", "w"))

    @cached_property
    def crossing(self) -> DataFrame:
        return cut(self._both_ends())  # written for many anchors only; a few are answered by passes over the edges

    def stats(self) -> DataFrame:
        from evenpart.operators.partition import pair_density

        return pair_density(self.edges, self.placed)

    def degrees(self) -> DataFrame:
        return self.crossing.groupBy("s", "t", "side", "vid").agg(F.sum("w").alias("deg"))

    def squares(self) -> DataFrame:
        return self.crossing.where("side = s").groupBy("s", "t").agg(F.sum(F.col("w") * F.col("w")).alias("e2"))

    def _common(self, asked: DataFrame) -> DataFrame:
        """(s, t, side, y, vid, n, h): codegrees of asked (s, t, side, y, d) with the vertices of their class, and h over y's neighbours only."""
        few = asked.count() <= FEW_ASKED
        crossing, sent = (self._both_ends(), F.broadcast(asked)) if few else (self.crossing, asked)
        mine = crossing.join(sent.withColumnRenamed("y", "vid"), ["s", "t", "side", "vid"]).select("s", "t", "side", F.col("vid").alias("y"), "near", F.col("w").alias("wy"), "d")
        if few and (mine := cut(mine)).count() <= MOST_LINKS:
            mine = F.broadcast(mine)
        both = crossing.select("s", "t", "side", "vid", "near", "w").join(mine, ["s", "t", "side", "near"]).where("vid <> y")
        return both.groupBy("s", "t", "side", "y", "vid").agg(F.sum(F.col("wy") * F.col("w")).alias("n"), F.sum(F.when(F.col("wy") > F.col("d"), F.col("w")).otherwise(0.0)).alias("h"))

    def anchor_sums(self, anchors: DataFrame, stats: DataFrame, eps: float, which: str | int = "all", asked: DataFrame | None = None) -> DataFrame:
        asked = cut(directed(stats).join(stats, ["s", "t"]).join(anchors.withColumnRenamed("cls", "side"), "side").select("s", "t", "side", "y", "d"))
        crossing = self._both_ends() if asked.count() <= FEW_ASKED else self.crossing
        near = self._common(asked).join(stats.select("s", "t", "bar"), ["s", "t"]).where("n >= bar")
        sums = near.groupBy("s", "t", "side", "y").agg(F.count("*").alias("size_b"), F.sum("h").alias("inner"))
        hood = crossing.join(asked.withColumnRenamed("y", "vid"), ["s", "t", "side", "vid"]).where("w > d").groupBy("s", "t", "side", F.col("vid").alias("y")).agg(F.count("*").alias("size_a"))
        return sums.join(hood, ["s", "t", "side", "y"]).select("s", "t", "side", "y", "size_a", "size_b", "inner")

    def anchor_sets(self, chosen: DataFrame, stats: DataFrame) -> DataFrame:
        asked = chosen.join(stats.select("s", "t", "d"), ["s", "t"]).select("s", "t", "side", "y", "d")
        near = self._common(asked).join(stats.select("s", "t", "bar"), ["s", "t"]).where("n >= bar").select("s", "t", "side", "vid")
        hood = self.crossing.join(asked.withColumnRenamed("y", "vid"), ["s", "t", "side", "vid"]).where("w > d")
        return near.union(hood.select("s", "t", F.when(F.col("side") == F.col("s"), F.col("t")).otherwise(F.col("s")), F.col("near")))


class Gaussian:
    """Weights are exp(-d^2 / (2 sigma^2)) of points (vid, x), made tile by tile."""

    def __init__(self, placed: DataFrame, vertices: DataFrame, sigma: float) -> None:
        self.k, most = placed.groupBy("cls").agg(F.count("*").alias("n")).agg(F.max("cls"), F.max("n")).first()
        self.tiles, self.sigma = max(1, -(-most // SIDE)), sigma
        rows = placed.join(vertices.select("vid", "x"), "vid")
        self.rows = cut(rows.select("vid", "cls", "x", F.pmod(F.xxhash64("vid"), F.lit(self.tiles)).cast("int").alias("tile")))
        self.placed = placed
        self.sent = placed.count() <= MOST_POINTS

    @cached_property
    def _points(self):
        """Ids, features and places of the classes of all points in the order of their classes, at every task."""
        got = self.rows.select("cls", "vid", "x").orderBy("cls", "vid").toArrow()  # at most MOST_POINTS rows
        cls, vid = got.column("cls").to_numpy(), got.column("vid").to_numpy()
        ends = np.searchsorted(cls, np.arange(1, self.k + 2))
        x = np.vstack([np.stack(part.to_numpy(zero_copy_only=False)) for part in got.column("x").chunks if len(part)])
        return self.rows.sparkSession.sparkContext.broadcast((vid, x, ends)), ends

    def _asked(self, made: Callable, schema: str) -> DataFrame:
        """Rows that ``made(c, o, vids, far)`` gives for each lot of members of class c and each other class o; nothing is shuffled.

        ``far()`` yields the weights between the lot and one tile of class o after another, with that tile's features and place, so
        that sums over the whole of class o end in the task that began them.
        """
        points, ends = self._points
        lots = [(c, lo) for c in range(1, self.k + 1) for lo in range(int(ends[c - 1]), int(ends[c]), LOT)]
        sigma, k = self.sigma, self.k

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            vid, x, end = points.value
            for f in frames:
                for i in f["id"]:
                    c, lo = lots[int(i)]
                    own = slice(lo, min(lo + LOT, int(end[c])))
                    for o in range(1, k + 1):
                        if o != c:
                            tiles = [slice(a, min(a + SIDE, int(end[o]))) for a in range(int(end[o - 1]), int(end[o]), SIDE)]
                            got = made(c, o, vid[own], lambda: ((blocks.gaussian(x[own], x[t], sigma), x[t], t) for t in tiles))  # noqa: B023
                            if got is not None and len(got):
                                yield got

        return self.rows.sparkSession.range(0, len(lots), 1, len(lots)).mapInPandas(run, schema)

    def _pass(self, made: Callable, schema: str, extra: DataFrame | None = None) -> DataFrame:
        """Rows that ``made(s, t, W, vids of s, vids of t, x of both)`` gives for every pair of classes and of their tiles.

        With ``extra`` (vid, other, val) ``made`` takes the values of both sides too, and members without one stay out.
        """
        each = F.explode(F.sequence(F.lit(1), F.lit(self.k)))
        sent = self.rows.withColumn("o", each).where("o <> cls")
        if extra is not None:
            sent = sent.join(extra.select("vid", F.col("other").alias("o"), "val"), ["vid", "o"])
        more = [] if extra is None else ["val"]
        sent = sent.withColumn("p", F.explode(F.sequence(F.lit(0), F.lit(self.tiles - 1))))
        first = F.col("cls") < F.col("o")
        sent = sent.select(
            F.least("cls", "o").alias("s"), F.greatest("cls", "o").alias("t"), F.when(first, F.col("tile")).otherwise(F.col("p")).alias("i"), F.when(first, F.col("p")).otherwise(F.col("tile")).alias("j"), "cls", "vid", "x", *more,
        )
        sigma = self.sigma

        def run(key: tuple, m: pd.DataFrame) -> pd.DataFrame:
            s, t = int(key[0]), int(key[1])
            m = m.sort_values("vid")
            a, b = m[m["cls"] == s], m[m["cls"] == t]
            if not len(a) or not len(b):
                return made(s, t, None, None, None, None, None, *[None, None][: 2 * len(more)])
            xa, xb = np.stack(a["x"].to_list()), np.stack(b["x"].to_list())
            return made(s, t, blocks.gaussian(xa, xb, sigma), a["vid"].to_numpy(), b["vid"].to_numpy(), xa, xb, *[side[c].to_numpy() for c in more for side in (a, b)])

        return sent.groupBy("s", "t", "i", "j").applyInPandas(run, schema)

    @cached_property
    def _sums(self) -> DataFrame:
        columns = ["s", "t", "side", "vid", "deg", "e2"]

        def made(s, t, w, va, vb, xa, xb):
            if w is None:
                return pd.DataFrame({c: [] for c in columns})
            sides = [pd.DataFrame({"s": s, "t": t, "side": s, "vid": va, "deg": w.sum(1), "e2": (w**2).sum(1)}), pd.DataFrame({"s": s, "t": t, "side": t, "vid": vb, "deg": w.sum(0), "e2": 0.0})]
            return pd.concat(sides)

        def whole(c, o, vids, far):
            deg, e2 = np.zeros(len(vids)), np.zeros(len(vids))
            for w, *_ in far():
                deg += w.sum(1)
                e2 += (w**2).sum(1) if c < o else 0.0
            return pd.DataFrame({"s": min(c, o), "t": max(c, o), "side": c, "vid": vids, "deg": deg, "e2": e2})

        form = "s int, t int, side int, vid long, deg double, e2 double"
        if self.sent:
            return cut(self._asked(whole, form))
        got = self._pass(made, form)
        return cut(got.groupBy("s", "t", "side", "vid").agg(F.sum("deg").alias("deg"), F.sum("e2").alias("e2")))

    def stats(self) -> DataFrame:
        return self._stats

    @cached_property
    def _stats(self) -> DataFrame:
        return cut(pair_stats(self, self.placed))

    def _table(self, values: DataFrame, name: str) -> np.ndarray:
        """The column of (vid, other, column) as one row a point in the order of ``_points``; nan where there is none."""
        vid, _, ends = self._points[0].value
        got, order = values.select("vid", "other", name).toArrow(), np.argsort(vid)
        table = np.full((len(vid), self.k + 1), np.nan)
        table[order[np.searchsorted(vid, got.column(0).to_numpy(), sorter=order)], got.column(1).to_numpy()] = got.column(2).to_numpy()
        return table

    def push(self, vec: DataFrame) -> DataFrame:
        """(vid, other, push): the kernel times the coordinates (vid, other, val) of the other class of each pair."""
        if self.sent and self.placed.count() * (self.k + 1) <= MOST_NUMBERS:
            held = self.rows.sparkSession.sparkContext.broadcast(np.nan_to_num(self._table(vec, "val")))
            whole = lambda c, o, vids, far: pd.DataFrame({"vid": vids, "other": o, "push": sum(w @ held.value[t, c] for w, _, t in far())})
            return self._asked(whole, "vid long, other int, push double")

        def made(s, t, w, va, vb, xa, xb, pa, pb):
            if w is None:
                return pd.DataFrame({c: [] for c in ("vid", "other", "push")})
            return pd.concat([pd.DataFrame({"vid": va, "other": t, "push": w @ pb}), pd.DataFrame({"vid": vb, "other": s, "push": pa @ w})])

        return self._pass(made, "vid long, other int, push double", vec).groupBy("vid", "other").agg(F.sum("push").alias("push"))

    def cells(self, sliced: DataFrame) -> DataFrame:
        """(s, t, i, j, e): the weight between the slices (vid, other, slice) of both sides of a pair."""

        def made(s, t, w, va, vb, xa, xb, ia, ib):
            if w is None:
                return pd.DataFrame({c: [] for c in ("s", "t", "i", "j", "e")})
            one = np.eye(SLICES)
            e = one[ia].T @ w @ one[ib]
            i, j = np.indices(e.shape)
            return pd.DataFrame({"s": s, "t": t, "i": i.ravel(), "j": j.ravel(), "e": e.ravel()})

        got = self._pass(made, "s int, t int, i int, j int, e double", sliced.withColumnRenamed("slice", "val"))
        return got.groupBy("s", "t", "i", "j").agg(F.sum("e").alias("e"))

    def degrees(self) -> DataFrame:
        return self._sums.drop("e2")

    def squares(self) -> DataFrame:
        return self._sums.groupBy("s", "t").agg(F.sum("e2").alias("e2"))

    def _anchors(self, asked: DataFrame) -> dict:
        """(s, t, side) to the ids and features of the anchors of asked (s, t, side, y, d, bar), d and bar."""
        few = asked.join(self.rows.select(F.col("vid").alias("y"), "x"), "y").select("s", "t", "side", "y", "d", "bar", "x").toPandas()  # checked below
        if len(few) * (len(few["x"].iloc[0]) if len(few) else 0) > MOST_NUMBERS:
            raise ValueError(f"{len(few)} anchors: ask for fewer")
        groups = few.sort_values("y").groupby(["s", "t", "side"])
        return {tuple(map(int, key)): (g["y"].to_numpy(), np.stack(g["x"].to_list()), float(g["d"].iloc[0]), float(g["bar"].iloc[0])) for key, g in groups}

    def _codegrees(self, asked: DataFrame, made: Callable, schema: str) -> DataFrame:
        """Rows that ``made(key, vids, y, near, h, size_a)`` gives for each lot of members against the anchors of their class.

        ``near`` marks members with a codegree of at least bar, ``h`` is the weight to an anchor's neighbours, of which it has ``size_a``.
        """
        held, sigma = self.rows.sparkSession.sparkContext.broadcast(self._anchors(asked)), self.sigma

        def whole(c, o, vids, far):
            key = (min(c, o), max(c, o), c)
            if key not in held.value:
                return None
            y, xy, d, bar = held.value[key]
            both, size = np.zeros((len(vids), 2 * len(y))), np.zeros(len(y), int)
            for w, x, _ in far():
                wy = blocks.gaussian(x, xy, sigma)
                hood = wy > d
                both += w @ np.hstack([wy, hood])
                size += hood.sum(0)
            return made(key, vids, y, (both[:, : len(y)] >= bar) & (vids[:, None] != y[None]), both[:, len(y) :], size)

        return self._asked(whole, schema)

    def _common(self, asked: DataFrame) -> DataFrame:
        """(s, t, side, y, vid, n, h, size_a) of asked (s, t, side, y, d, bar); the anchors' features are sent to all tasks."""
        held, sigma = self.rows.sparkSession.sparkContext.broadcast(self._anchors(asked)), self.sigma
        columns = ["s", "t", "side", "vid", "y", "n", "h", "size_a"]

        def made(s, t, w, va, vb, xa, xb):
            out = []
            if w is not None:
                for side, own, other, block in ((s, va, xb, w.T), (t, vb, xa, w)):  # block: rows of the other class, columns of this one
                    if (s, t, side) not in held.value:
                        continue
                    y, xy, d, _ = held.value[(s, t, side)]
                    wy = blocks.gaussian(other, xy, sigma)
                    n, hood = wy.T @ block, wy > d
                    h, size = hood.T.astype(float) @ block, hood.sum(0)
                    out.append(pd.DataFrame({"s": s, "t": t, "side": side, "vid": own, "y": [y.tolist()] * len(own), "n": list(n.T), "h": list(h.T), "size_a": [size.tolist()] * len(own)}))
            # without a type the columns of no rows are doubles, which are no lists
            return pd.concat(out) if out else pd.DataFrame({c: pd.Series([], dtype=object) for c in columns})

        got = self._pass(made, "s int, t int, side int, vid long, y array<long>, n array<double>, h array<double>, size_a array<long>")
        each = got.select("s", "t", "side", "vid", F.explode(F.arrays_zip("y", "n", "h", "size_a")).alias("z")).select("s", "t", "side", "vid", "z.*")
        return each.groupBy("s", "t", "side", "y", "vid").agg(F.sum("n").alias("n"), F.sum("h").alias("h"), F.sum("size_a").alias("size_a"))

    def leading_anchors(self, asked: DataFrame, eps: float, typical: bool) -> DataFrame:
        """(s, t, side, y): of all members of ``side`` in asked (s, t, side, d, bar, m) those that may have the largest gap, else one that is open.

        Every member meets its whole class over the whole other one.  Nothing is shuffled; a direction gives few rows.
        """
        points, ends = self._points
        limits = {(r["s"], r["t"], r["side"]): (r["d"], r["bar"], r["m"]) for r in asked.select("s", "t", "side", "d", "bar", "m").collect()}  # k(k-1) rows
        lots = [(key, lo) for key in sorted(limits) for lo in range(int(ends[key[2] - 1]), int(ends[key[2]]), LOT)]
        sigma, spark, form = self.sigma, self.rows.sparkSession, "s int, t int, side int, y long, gap double"
        if not lots:
            return spark.createDataFrame([], form).drop("gap")

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            vid, x, end = points.value
            for f in frames:
                for i in f["id"]:
                    (s, t, side), lo = lots[int(i)]
                    far, (d, bar, m) = (t if side == s else s), limits[s, t, side]
                    whole = slice(int(end[side - 1]), int(end[side]))
                    hi = min(lo + LOT, whole.stop)
                    a, b, inner, deg = reach_of_all(x[whole], slice(lo - whole.start, hi - whole.start), x[int(end[far - 1]) : int(end[far])], sigma, d, bar)
                    open_ = b >= max(eps**4 / 4 * m, 1)
                    if typical:
                        open_ &= np.abs(deg - d * m) < eps**4 * m
                    floor = max(eps**4 / 16 * m, 1)
                    gap = np.where(open_ & (a >= floor) & (b >= floor), np.abs(inner / np.maximum(a * b, 1) - d), -1.0)
                    gap[gap < eps**4 - ROUNDING] = -1.0
                    keep = np.flatnonzero((gap >= 0) & (gap >= gap.max() - 2 * ROUNDING)) if gap.max() >= 0 else np.flatnonzero(open_)[:1]
                    if len(keep):
                        yield pd.DataFrame({"s": s, "t": t, "side": side, "y": vid[lo + keep], "gap": gap[keep]})

        rows = cut(spark.range(0, len(lots), 1, min(len(lots), MOST_TASKS)).mapInPandas(run, form))
        most = F.max("gap").over(Window.partitionBy("s", "t", "side"))
        rows = rows.withColumns({"most": most, "r": F.row_number().over(Window.partitionBy("s", "t", "side").orderBy(F.desc("gap"), "y"))})
        return cut(rows.where((F.col("r") == 1) | ((F.col("gap") >= 0) & (F.col("gap") >= F.col("most") - 2 * ROUNDING))).select("s", "t", "side", "y"))

    def anchor_sums(self, anchors: DataFrame, stats: DataFrame, eps: float, which: str | int = "all", asked: DataFrame | None = None) -> DataFrame:
        """The sums of the named anchors; of all (``which``) only those that decide their direction, of ``asked`` (s, t, side) where it is given."""
        sides = directed(stats).select("s", "t", "side") if asked is None else asked
        known = sides.join(stats, ["s", "t"])
        if isinstance(which, int):
            asked = known.join(anchors.withColumnRenamed("cls", "side"), "side").select("s", "t", "side", "y", "d", "bar")
        else:
            led = self.leading_anchors(known.withColumn("m", F.col("na").cast("double")), eps, which == "typical")
            # copies of a point have the same sums: the smallest id speaks for them
            led = led.join(self.rows.select(F.col("vid").alias("y"), "x"), "y").groupBy("s", "t", "side", "x").agg(F.min("y").alias("y")).drop("x")
            asked = led.join(stats, ["s", "t"]).select("s", "t", "side", "y", "d", "bar")
        if self.sent:

            def made(key, vids, y, near, h, size):
                return pd.DataFrame({"s": key[0], "t": key[1], "side": key[2], "y": y, "size_a": size, "size_b": near.sum(0), "inner": (h * near).sum(0)})

            parts = self._codegrees(asked, made, "s int, t int, side int, y long, size_a long, size_b long, inner double")
            sums = parts.groupBy("s", "t", "side", "y").agg(F.max("size_a").alias("size_a"), F.sum("size_b").alias("size_b"), F.sum("inner").alias("inner"))
            return sums.where("size_b > 0")
        near = self._common(asked).where("vid <> y").join(stats.select("s", "t", "bar"), ["s", "t"]).where("n >= bar")
        return near.groupBy("s", "t", "side", "y").agg(F.max("size_a").alias("size_a"), F.count("*").alias("size_b"), F.sum("h").alias("inner"))

    def anchor_sets(self, chosen: DataFrame, stats: DataFrame) -> DataFrame:
        asked = chosen.join(stats.select("s", "t", "d", "bar"), ["s", "t"]).select("s", "t", "side", "y", "d", "bar")
        if self.sent:
            made = lambda key, vids, y, near, h, size: pd.DataFrame({"s": key[0], "t": key[1], "side": key[2], "vid": vids[near[:, 0]]})  # noqa: E731  an anchor a pair
            near = self._codegrees(asked, made, "s int, t int, side int, vid long")
        else:
            near = self._common(asked).where("vid <> y").join(stats.select("s", "t", "bar"), ["s", "t"]).where("n >= bar").select("s", "t", "side", "vid")
        far = F.when(F.col("side") == F.col("s"), F.col("t")).otherwise(F.col("s"))
        own = asked.join(self.rows.select(F.col("vid").alias("y"), F.col("x").alias("xy")), "y").select("s", "t", far.alias("cls"), "xy", "d")
        from evenpart.operators.graphs import dist2

        w = F.exp(-dist2(F.col("x"), F.col("xy")) / F.lit(2.0 * self.sigma**2))
        hood = self.rows.join(own, "cls").where(w > F.col("d")).select("s", "t", F.col("cls").alias("side"), "vid")
        return near.union(hood)


#: What single precision may change of a mean weight.
ROUNDING = (STEP + 32) * 2.0**-23


def _single(x: np.ndarray, y: np.ndarray, sigma: float) -> np.ndarray:
    """``blocks.gaussian`` in single precision: squared distances in double, so that a weight is off by 2^-22 at most."""
    d2 = x @ y.T
    d2 *= 1 / sigma**2
    d2 -= ((x**2).sum(1) / (2 * sigma**2))[:, None]
    d2 -= (y**2).sum(1) / (2 * sigma**2)
    w = d2.astype(np.float32)
    np.minimum(w, 0, out=w)
    return np.exp(w, out=w)


def reach_of_all(x: np.ndarray, own: slice, far: np.ndarray, sigma: float, d: float, bar: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(size_a, size_b, inner, degree) of the anchors ``x[own]`` among all of their class ``x`` over the other class ``far``.

    Sizes are those of double precision: single precision decides what its error bound allows, as ``blocks.codegree``
    does; ``inner`` is off by ``ROUNDING`` times both sizes at most.
    """
    y = x[own]
    size_a, size_b, inner, deg = np.zeros(len(y), int), np.zeros(len(y), int), np.zeros(len(y)), np.zeros(len(y))
    for at in range(0, len(far), STEP):
        w = blocks.gaussian(far[at : at + STEP], y, sigma)
        size_a += (w > d).sum(0)
        deg += w.sum(0)
    # sums of STEP products, each of two weights that are off by 2^-22
    slack = bar * (STEP + 16) * 2.0**-24 + len(far) * 2.0**-21
    for lo in range(0, len(x), SIDE):
        z = x[lo : lo + SIDE]
        n, h = np.zeros((len(y), len(z))), np.zeros((len(y), len(z)))
        for at in range(0, len(far), STEP):
            rows = far[at : at + STEP]
            wy, wz = blocks.gaussian(rows, y, sigma), _single(rows, z, sigma)
            n += wy.T.astype(np.float32) @ wz
            h += (wy > d).T.astype(np.float32) @ wz
        near = n >= bar
        i, j = np.nonzero(np.abs(n - bar) <= 2 * slack)
        if len(i) * 256 > n.size:
            n[:] = 0
            for at in range(0, len(far), STEP):
                n += blocks.gaussian(far[at : at + STEP], y, sigma).T @ blocks.gaussian(far[at : at + STEP], z, sigma)
            near = n >= bar
        else:
            some = max(1, 2**21 // len(far))
            for a in range(0, len(i), some):
                one, two = i[a : a + some], j[a : a + some]
                near[one, two] = np.einsum("ij,ij->j", blocks.gaussian(far, y[one], sigma), blocks.gaussian(far, z[two], sigma)) >= bar
        same = np.arange(max(own.start, lo), min(own.stop, lo + len(z)))
        near[same - own.start, same - lo] = False
        size_b += near.sum(1)
        inner += np.einsum("ij,ij->i", h, near)
    return size_a, size_b, inner, deg


class Inner:
    """Weights are inner products of features (vid, x): sums of features answer for whole classes."""

    def __init__(self, placed: DataFrame, vertices: DataFrame) -> None:
        # a task holds members of few classes, so the sums it gathers are few
        self.rows = cut(placed.select("vid", "cls").join(vertices.select("vid", "x"), "vid").repartitionByRange("cls", "vid"))

    def _summed(self, made: Callable, key: str, rows: DataFrame | None = None) -> DataFrame:
        """(key, sums): sums of the arrays that ``made(frame, features)`` yields by key; each task sums its own rows first."""
        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            held: dict = {}
            for f in frames:
                if len(f):
                    for k, v in made(f, np.stack(f["x"].to_list())):
                        held[k] = held[k] + v if k in held else v
            if held:
                yield pd.DataFrame({"key": list(held), "sums": [v.ravel() for v in held.values()]})

        def total(f: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"key": f["key"].iloc[:1], "sums": [np.sum(f["sums"].to_list(), axis=0)]})

        form = f"key {key}, sums array<double>"
        return (self.rows if rows is None else rows).mapInPandas(run, form).groupBy("key").applyInPandas(total, form)

    @cached_property
    def classes(self) -> dict[int, tuple[float, np.ndarray, np.ndarray]]:
        """Size, sum of features and sum of their outer products of every class."""
        k, p = self.rows.agg(F.countDistinct("cls"), F.max(F.size("x"))).first()
        if k * p * p > MOST_NUMBERS:
            raise ValueError(f"{k} classes of {p} features: take fewer features or raise h")

        def made(f, x):
            for c in f["cls"].unique():
                own = np.column_stack([np.ones((f["cls"] == c).sum()), x[(f["cls"] == c).to_numpy()]])
                yield int(c), own.T @ own

        return {int(r.key): ((g := np.asarray(r.sums).reshape(p + 1, p + 1))[0, 0], g[0, 1:], g[1:, 1:]) for r in self._summed(made, "int").toPandas().itertuples()}

    def degrees(self) -> DataFrame:
        held = self.rows.sparkSession.sparkContext.broadcast({c: s for c, (_, s, _) in self.classes.items()})

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                for c, own in f.groupby("cls") if len(f) else ():
                    x = np.stack(own["x"].to_list())
                    for o, s in held.value.items():
                        if o != c:
                            yield pd.DataFrame({"s": min(c, o), "t": max(c, o), "side": c, "vid": own["vid"], "deg": x @ s})

        return self.rows.mapInPandas(run, "s int, t int, side int, vid long, deg double")

    def squares(self) -> DataFrame:
        g = {c: v[2] for c, v in self.classes.items()}
        rows = [(s, t, float((g[s] * g[t]).sum())) for s in g for t in g if s < t]
        return self.rows.sparkSession.createDataFrame(rows, "s int, t int, e2 double")

    def anchor_sums(self, anchors: DataFrame, stats: DataFrame, eps: float, which: str | int = "all", asked: DataFrame | None = None) -> DataFrame:
        """All anchors in lots of ``ANCHORS`` a class, each lot one pass over the points."""
        most = anchors.groupBy("cls").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0
        if most <= ANCHORS:
            return self._anchor_sums(anchors, stats)
        ranked, out = cut(anchors.withColumn("lot", F.floor((F.row_number().over(Window.partitionBy("cls").orderBy("y")) - 1) / ANCHORS).cast("int"))), None
        for lot in range(-(-most // ANCHORS)):
            part = cut(self._anchor_sums(ranked.where(F.col("lot") == lot).drop("lot"), stats))
            out = part if out is None else out.unionByName(part)
        return out

    def _anchor_sums(self, anchors: DataFrame, stats: DataFrame) -> DataFrame:
        few = anchors.join(self.rows.select(F.col("vid").alias("y"), "x"), "y").toPandas()  # at most ANCHORS a class, checked
        if len(few) * (len(few["x"].iloc[0]) if len(few) else 0) > MOST_NUMBERS:
            raise ValueError(f"{len(few)} anchors: ask for fewer")
        asked = {int(c): (g["y"].to_numpy(), np.stack(g["x"].to_list())) for c, g in few.sort_values("y").groupby("cls")}
        limits = {(r["s"], r["t"]): (r["d"], r["bar"]) for r in stats.select("s", "t", "d", "bar").collect()}  # k(k-1)/2 rows
        held = self.rows.sparkSession.sparkContext.broadcast((asked, limits, {c: g for c, (_, _, g) in self.classes.items()}))

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            table, bars, outer = held.value
            sums: dict = {}
            for f in frames:
                for c, own in f.groupby("cls") if len(f) else ():
                    x, vids = np.stack(own["x"].to_list()), own["vid"].to_numpy()
                    for o, (y, xy) in table.items():
                        if o == c:  # the anchors of this class, against every other one
                            for far in outer:
                                if (pair := (min(c, far), max(c, far))) in bars and far != c:
                                    m = (x @ (xy @ outer[far]).T >= bars[pair][1]) & (vids[:, None] != y[None])
                                    k, v = (*pair, c, 1), np.column_stack([m.sum(0), m.T.astype(float) @ x])
                                    sums[k] = sums[k] + v if k in sums else v
                        elif (pair := (min(c, o), max(c, o))) in bars:
                            m = x @ xy.T > bars[pair][0]
                            k, v = (*pair, o, 0), np.column_stack([m.sum(0), m.T.astype(float) @ x])
                            sums[k] = sums[k] + v if k in sums else v
            for (s, t, side, kind), v in sums.items():
                yield pd.DataFrame({"s": [s], "t": [t], "side": [side], "kind": [kind], "sums": [v.ravel()]})

        def joined(key: tuple, f: pd.DataFrame) -> pd.DataFrame:
            y = held.value[0][int(key[2])][0]
            a, b = (np.sum(f.loc[f["kind"] == kind, "sums"].to_list(), axis=0).reshape(len(y), -1) for kind in (0, 1))
            return pd.DataFrame({"s": key[0], "t": key[1], "side": key[2], "y": y, "size_a": a[:, 0].astype(int), "size_b": b[:, 0].astype(int), "inner": (a[:, 1:] * b[:, 1:]).sum(1)})

        parts = self.rows.mapInPandas(run, "s int, t int, side int, kind int, sums array<double>")
        return parts.groupBy("s", "t", "side").applyInPandas(joined, "s int, t int, side int, y long, size_a long, size_b long, inner double").where("size_b > 0")

    def anchor_sets(self, chosen: DataFrame, stats: DataFrame) -> DataFrame:
        few = chosen.join(stats.select("s", "t", "d", "bar"), ["s", "t"]).join(self.rows.select(F.col("vid").alias("y"), "x"), "y").toPandas()  # an anchor a pair
        near, hood = {}, {}
        for r in few.itertuples():
            far, xy = (r.t if r.side == r.s else r.s), np.asarray(r.x)
            near.setdefault(int(r.side), []).append((r.s, r.t, r.y, self.classes[far][2] @ xy, r.bar))
            hood.setdefault(int(far), []).append((r.s, r.t, xy, r.d))
        held = self.rows.sparkSession.sparkContext.broadcast((near, hood))

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                for c, own in f.groupby("cls") if len(f) else ():
                    x, vids = np.stack(own["x"].to_list()), own["vid"].to_numpy()
                    for s, t, y, q, bar in held.value[0].get(int(c), ()):
                        yield pd.DataFrame({"s": s, "t": t, "side": int(c), "vid": vids[(x @ q >= bar) & (vids != y)]})
                    for s, t, xy, d in held.value[1].get(int(c), ()):
                        yield pd.DataFrame({"s": s, "t": t, "side": int(c), "vid": vids[x @ xy > d]})

        return self.rows.mapInPandas(run, "s int, t int, side int, vid long")

    def spectral(self, stats: DataFrame, eps: float, large: float = 0.05) -> tuple[DataFrame, DataFrame]:
        """((s, t, sigma, gap), (s, t, side, vid)) of the pairs whose centred block has a first singular value of eps^3 sqrt(pq) or more.

        The block is P M Q' for P = [1, features]: its singular values are those of a small matrix made of the sums of
        outer products, and its singular vectors are linear in the features.  Level sets come from slices at quantiles.
        """
        spark, table = self.rows.sparkSession, self.rows.sparkSession.sparkContext.broadcast(self.classes)

        def values(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            roots = {}
            for f in frames:
                out = []
                for s, t, d in zip(f["s"], f["t"], f["d"], strict=True):
                    for c in (s, t):
                        if c not in roots:
                            n, total, g = table.value[c]
                            val, vec = np.linalg.eigh(np.block([[np.array([[n]]), total[None]], [total[:, None], g]]))
                            keep = val > 1e-10 * val[-1]
                            roots[c] = (vec[:, keep] * np.sqrt(val[keep]), vec[:, keep] / np.sqrt(val[keep]))
                    m = np.eye(len(roots[s][0]))
                    m[0, 0] = -d
                    u, sv, vt = np.linalg.svd(roots[s][0].T @ m @ roots[t][0])
                    out.append((s, t, d, float(sv[0]), roots[s][1] @ u[:, 0], roots[t][1] @ vt[0]))
                yield pd.DataFrame(out, columns=["s", "t", "d", "sigma", "a", "b"])

        made_small = stats.select("s", "t", "d").repartition("s").mapInPandas(values, "s int, t int, d double, sigma double, a array<double>, b array<double>").toPandas()  # k(k-1)/2 rows
        small = {(int(r.s), int(r.t)): (r.sigma, np.asarray(r.a), np.asarray(r.b), r.d) for r in made_small.itertuples()}
        edge = {k: eps**3 * np.sqrt(self.classes[k[0]][0] * self.classes[k[1]][0]) for k in small}
        bad = {k: v for k, v in small.items() if v[0] >= edge[k]}
        sent: dict[int, list] = {}
        for (s, t), (_, a, b, _) in bad.items():
            sent.setdefault(s, []).append((s, t, a))
            sent.setdefault(t, []).append((s, t, b))
        held = spark.sparkContext.broadcast(sent)

        def valued(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                for c, own in f.groupby("cls") if len(f) else ():
                    x = np.stack(own["x"].to_list())
                    for s, t, a in held.value.get(int(c), ()):
                        yield pd.DataFrame({"s": s, "t": t, "side": int(c), "vid": own["vid"], "val": a[0] + x @ a[1:]})

        vals = cut(self.rows.mapInPandas(valued, "s int, t int, side int, vid long, val double"))
        cuts = vals.groupBy("s", "t", "side").agg(F.percentile_approx("val", F.array(*[F.lit(i / SLICES) for i in range(1, SLICES)]), F.lit(1000)).alias("cuts"))
        sliced = cut(vals.join(cuts, ["s", "t", "side"]).select("s", "t", "side", "vid", F.size(F.filter("cuts", lambda c: c < F.col("val"))).alias("slice")))

        def made(f, x):
            for (s, t, side), own in f.groupby(["s", "t", "side"]):
                at = f.index.get_indexer(own.index)
                for i in own["slice"].unique():
                    part = x[at[(own["slice"] == i).to_numpy()]]
                    yield f"{s},{t},{side},{i}", np.append(len(part), part.sum(0))

        got = {tuple(map(int, r.key.split(","))): np.asarray(r.sums) for r in self._summed(made, "string", sliced.join(self.rows.select("vid", "x"), "vid")).toPandas().itertuples()}
        floor, rows, ranges = max(eps**9 / 108, large), [], []
        for s, t, (sv, *_), d in [(s, t, v, v[3]) for (s, t), v in small.items()]:
            best = (-1.0, None, None)
            if (s, t) in bad:
                zero = np.zeros(len(self.classes[s][1]) + 1)
                a, b = (np.array([got.get((s, t, c, i), zero) for i in range(SLICES)]) for c in (s, t))
                for up in (1, -1):
                    for right in (1, -1):
                        ca, cb = a[::up].cumsum(0), b[::right].cumsum(0)
                        area = np.outer(ca[:, 0], cb[:, 0])
                        fit = (ca[:, :1] >= floor * ca[-1, 0]) & (cb[:, 0][None] >= floor * cb[-1, 0]) & (area > 0)
                        gap = np.where(fit, np.abs(ca[:, 1:] @ cb[:, 1:].T / np.maximum(area, 1) - d), -1)
                        i, j = np.unravel_index(int(gap.argmax()), gap.shape)
                        if gap[i, j] > best[0] + 1e-12:
                            best = (float(gap[i, j]), (0, int(i)) if up == 1 else (SLICES - 1 - int(i), SLICES - 1), (0, int(j)) if right == 1 else (SLICES - 1 - int(j), SLICES - 1))
            rows.append((s, t, sv, best[0] if best[0] >= eps**9 / 108 else None, (s, t) in bad))
            if rows[-1][3] is not None:
                ranges += [(s, t, s, *best[1]), (s, t, t, *best[2])]
        marks = sliced.join(F.broadcast(spark.createDataFrame(ranges, "s int, t int, side int, lo int, hi int")), ["s", "t", "side"]).where(F.col("slice").between(F.col("lo"), F.col("hi")))  # two rows a pair
        return spark.createDataFrame(rows, "s int, t int, sigma double, gap double, bad boolean"), marks.select("s", "t", "side", "vid")


# ---- the codegree check on any source ------------------------------------------------------------------------


def pair_stats(source, placed: DataFrame) -> DataFrame:
    """(s, t, na, nb, e, e2, d) of all pairs."""
    if isinstance(source, Edges):  # known without degrees
        return source.stats()
    sizes = placed.groupBy("cls").agg(F.count("*").alias("n"))
    grid = sizes.select(F.col("cls").alias("s"), F.col("n").alias("na")).join(sizes.select(F.col("cls").alias("t"), F.col("n").alias("nb")), F.col("s") < F.col("t"))
    sums = source.degrees().where("side = s").groupBy("s", "t").agg(F.sum("deg").alias("e")).join(source.squares(), ["s", "t"], "left")
    e = F.coalesce("e", F.lit(0.0))
    return grid.join(sums, ["s", "t"], "left").select("s", "t", "na", "nb", e.alias("e"), F.coalesce("e2", F.lit(0.0)).alias("e2"), (e / (F.col("na") * F.col("nb"))).alias("d"))


ROWS = "s int, t int, status string, d double, gap double, side int, vid long"


def _rows(verdict: DataFrame, marks: DataFrame) -> DataFrame:
    none = F.lit(None)
    one = verdict.select(F.col("s").cast("int").alias("s"), F.col("t").cast("int").alias("t"), "status", "d", "gap", none.cast("int").alias("side"), none.cast("long").alias("vid"))
    return one.unionByName(marks.select(F.col("s").cast("int").alias("s"), F.col("t").cast("int").alias("t"), none.cast("string").alias("status"), none.cast("double").alias("d"), none.cast("double").alias("gap"), F.col("side").cast("int").alias("side"), "vid"))


def check_codegree(source, placed: DataFrame, eps: float, policy: str = "max_gap", anchors: str | int = "all") -> DataFrame:
    """Rows of ``check_pairs`` by the degree and codegree steps of ``blocks.codegree``, in both directions and from the same anchors.

    Where a number of anchors is asked for, a pair without a witness stays UNVERIFIED.
    """
    g = eps**4
    m = F.col("m")
    stats = pair_stats(source, placed).withColumn("m", F.col("na").cast("double"))
    stats = cut(stats.withColumn("bar", F.lit(2 * g) * m + F.col("d") * F.col("d") * m))
    live = stats.where(F.col("d") >= eps**3)
    if live.isEmpty():  # every pair is too thin to be uneven
        none = F.lit(None)
        return _rows(stats.select("s", "t", F.lit(blocks.UNIFORM).alias("status"), "d", F.lit(0.0).alias("gap")), stats.where("false").select("s", "t", none.cast("int").alias("side"), none.cast("long").alias("vid")))
    floor = F.greatest(F.lit(g / 16) * m, F.lit(1.0))

    seen = source.degrees()
    all_ = directed(live).join(placed.select(F.col("cls").alias("side"), "vid"), "side").join(seen, ["s", "t", "side", "vid"], "left").join(live, ["s", "t"])
    off = F.coalesce("deg", F.lit(0.0)) - F.col("d") * m
    deg = cut(all_.select("s", "t", "side", "vid", F.coalesce("deg", F.lit(0.0)).alias("deg"), "d", "m", F.when(off >= F.lit(g) * m, 1).when(off <= -F.lit(g) * m, -1).otherwise(0).alias("turn")))
    several = deg.where("turn <> 0").groupBy("s", "t", "side", "turn").agg(F.count("*").alias("size"), F.sum("deg").alias("sum"), F.max("d").alias("d"), F.max("m").alias("m"))
    both = F.sum("size").over(Window.partitionBy("s", "t", "side"))
    step1 = several.withColumn("all", both).withColumn("gap", F.abs(F.col("sum") / (F.col("size") * m) - F.col("d")))
    step1 = step1.where((F.col("all") >= F.lit(g / 8) * m) & (F.col("size") >= floor) & (F.col("gap") >= g)).select("s", "t", "side", F.lit("degree").alias("kind"), "turn", F.lit(None).cast("long").alias("y"), "size", "gap")

    pool = spread_anchors(placed, anchors) if isinstance(anchors, int) else choose_anchors(placed, anchors)
    # in the published order a direction with deviant degrees asks no anchor
    sides = directed(live).select("s", "t", "side")
    sides = sides.join(step1.select("s", "t", "side").distinct(), ["s", "t", "side"], "left_anti") if policy == "lemma_order" else sides
    sums = source.anchor_sums(pool, live, eps, anchors, sides).join(live.select("s", "t", "d", "m"), ["s", "t"])
    if anchors == "typical":
        sums = sums.join(deg.where("turn = 0").select("s", "t", "side", F.col("vid").alias("y")), ["s", "t", "side", "y"], "left_semi")
    opened = cut(sums.where(F.col("size_b") >= F.greatest(F.lit(g / 4) * m, F.lit(1.0))))
    gaps = opened.withColumn("gap", F.abs(F.col("inner") / (F.col("size_a") * F.col("size_b")) - F.col("d"))).where((F.col("size_a") >= floor) & (F.col("size_b") >= floor) & (F.col("gap") >= g))
    step2 = gaps.select("s", "t", "side", F.lit("anchor").alias("kind"), F.lit(0).alias("turn"), "y", F.col("size_b").alias("size"), "gap")
    # the order of the direct check: in a direction the largest gap (or the degree step, larger set first), then the larger of two directions
    ranked = step1.unionByName(step2)
    if policy == "lemma_order":
        inside = [(F.col("kind") == "degree").desc(), F.when(F.col("kind") == "degree", F.col("size")).otherwise(0).desc(), F.desc("turn"), F.desc("gap"), F.asc("y")]
    else:
        inside = [F.desc("gap"), (F.col("kind") == "degree").desc(), F.desc("turn"), F.asc("y")]
    ranked = ranked.withColumn("r", F.row_number().over(Window.partitionBy("s", "t", "side").orderBy(*inside))).where("r = 1").drop("r")
    best = cut(ranked.withColumn("r", F.row_number().over(Window.partitionBy("s", "t").orderBy(F.desc("gap"), F.desc("side")))).where("r = 1").drop("r"))
    doubt = opened.select("s", "t")
    if anchors == "typical":  # a side without a typical member was not looked at
        doubt = doubt.union(deg.groupBy("s", "t", "side").agg(F.min(F.abs("turn")).alias("off")).where("off > 0").select("s", "t"))
    doubt = doubt.distinct().withColumn("open", F.lit(True))
    part = isinstance(anchors, int) and placed.groupBy("cls").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] > anchors
    status = F.when(F.col("gap").isNotNull(), blocks.WITNESS).when(F.col("d") < eps**3, blocks.UNIFORM).when(F.coalesce("open", F.lit(False)) | F.lit(part), blocks.UNVERIFIED).otherwise(blocks.UNIFORM)
    verdict = stats.join(best.select("s", "t", "gap"), ["s", "t"], "left").join(doubt, ["s", "t"], "left").select("s", "t", status.alias("status"), "d", F.coalesce("gap", F.lit(0.0)).alias("gap"))
    chosen = best.where("kind = 'anchor'").select("s", "t", "side", "y")
    by_degree = best.where("kind = 'degree'").select("s", "t", "side", "turn")
    marks = deg.join(by_degree, ["s", "t", "side", "turn"]).select("s", "t", "side", "vid")
    far = directed(by_degree.select("s", "t")).join(by_degree.select("s", "t", F.col("side").alias("far")), ["s", "t", "far"]).select("s", "t", "side")
    marks = marks.union(far.join(placed.select(F.col("cls").alias("side"), "vid"), "side").select("s", "t", "side", "vid"))
    if not chosen.isEmpty():
        marks = marks.union(source.anchor_sets(chosen, stats))
    return _rows(verdict, marks)


def check_spectral(source: Inner, placed: DataFrame, eps: float, large: float = 0.05) -> DataFrame:
    """Rows of ``check_pairs`` by the first singular value of every centred block of inner products."""
    stats = cut(pair_stats(source, placed))
    found, marks = source.spectral(stats, eps, large)
    status = F.when(F.col("gap").isNotNull(), blocks.WITNESS).when(F.col("bad"), blocks.UNVERIFIED).otherwise(blocks.UNIFORM)
    return _rows(stats.join(found, ["s", "t"]).select("s", "t", status.alias("status"), "d", F.coalesce("gap", F.lit(0.0)).alias("gap")), marks)
