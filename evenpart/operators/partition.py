"""Partition state, densities, energy, pair checks, refinement and the practical loop, on DataFrames."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from evenpart.functions import blocks
from evenpart.operators import large
from evenpart.operators.graphs import md5_coin
from evenpart.operators.local import MOST_CLASSES, min_class
from evenpart.plans.scratch import cut

#: Lots of classes that a small graph is dealt into, so that their pairs spread over tasks.
LOTS = 8
#: Names of new classes that are sent to all tasks; more are joined by a shuffle.
MOST_NAMES = 1_000_000
#: Vertices whose classes are sent to all tasks; more are joined by a shuffle.
MOST_PLACED = 1_000_000
#: Numbers of all points together that are sent to all tasks; more are dealt to the meetings of their lots.
MOST_NUMBERS = 32_000_000
#: Slices of the ids in a start by id.
SLICES_OF_IDS = 256


def order_key(vid: Column, seed: int) -> Column:
    return F.md5(F.concat_ws(":", vid.cast("string"), F.lit(str(seed))))


def rank_within(df: DataFrame, groups: list[str], key: str, tie: str) -> DataFrame:
    """Add ``rank`` (0, 1, ...) by (key, tie) inside each group, where ``key`` is hexadecimal and evenly spread (a digest).

    The first three digits of the key cut a group into 4096 buckets: counts give each bucket its offset, and rows are
    numbered inside buckets only, so that a group of any size is ranked by many tasks.
    """
    return _ranked(df.withColumn("_b", F.substring(key, 1, 3)), groups, key, tie)


def rank_by_number(df: DataFrame, number: str, slices: int = SLICES_OF_IDS) -> DataFrame:
    """Add ``rank`` (0, 1, ...) by a number, in slices between approximate quantiles, however the numbers are spread."""
    bounds = df.agg(F.percentile_approx(number, [i / slices for i in range(1, slices)], 10 * slices)).first()[0]
    edges = F.array(*[F.lit(b) for b in sorted(set(bounds or []))]) if bounds else F.array().cast("array<long>")
    slice_ = F.size(F.filter(edges, lambda b: b < F.col(number)))
    return _ranked(df.withColumns({"_b": slice_, "_g": F.lit(0)}), ["_g"], number, number).drop("_g")


def _ranked(held: DataFrame, groups: list[str], key: str, tie: str) -> DataFrame:
    counts = held.groupBy(*groups, "_b").agg(F.count("*").alias("_n"))
    before = Window.partitionBy(*groups).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.withColumn("_o", F.coalesce(F.sum("_n").over(before), F.lit(0))).drop("_n")
    inside = Window.partitionBy(*groups, "_b").orderBy(key, tie)
    return held.join(offsets, [*groups, "_b"]).withColumn("rank", F.col("_o") + F.row_number().over(inside) - 1).drop("_b", "_o")


def initial_partition(vertices: DataFrame, parts: int, order: str = "hash", seed: int = 42) -> DataFrame:
    """(vid, cls): ``parts`` classes of equal size in the order of a hash or of the ids; what is over is class 0."""
    n = vertices.count()
    if n < parts:
        raise ValueError(f"{n} vertices can't fill {parts} classes")
    size = n // parts
    if order == "hash":
        ranked = rank_within(vertices.select("vid", order_key(F.col("vid"), seed).alias("key"), F.lit(0).alias("g")), ["g"], "key", "vid")
    else:
        ranked = rank_by_number(vertices.select("vid"), "vid")
    return ranked.select("vid", F.when(F.col("rank") < parts * size, 1 + F.floor(F.col("rank") / size)).otherwise(0).cast("int").alias("cls"))


# ---- densities and energy ------------------------------------------------------------------------------------


def between_classes(edges: DataFrame, placed: DataFrame) -> DataFrame:
    """Edges with the classes (ca, cb) of both ends, those inside a class left out; edges are shuffled beyond ``MOST_PLACED`` vertices only."""
    sent = F.broadcast if placed.count() <= MOST_PLACED else (lambda df: df)
    a, b = placed.select(F.col("vid").alias("src"), F.col("cls").alias("ca")), placed.select(F.col("vid").alias("dst"), F.col("cls").alias("cb"))
    return edges.join(sent(a), "src").join(sent(b), "dst").where("ca <> cb")


def pair_density(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """(s, t, na, nb, e, e2, d) for all class pairs s < t; a pair without edges has density 0."""
    placed = assign.where("cls > 0")
    sums = between_classes(edges, placed).groupBy(F.least("ca", "cb").alias("s"), F.greatest("ca", "cb").alias("t")).agg(F.sum("w").alias("e"), F.sum(F.col("w") * F.col("w")).alias("e2"))
    sizes = placed.groupBy("cls").agg(F.count("*").alias("n"))
    grid = sizes.select(F.col("cls").alias("s"), F.col("n").alias("na")).join(sizes.select(F.col("cls").alias("t"), F.col("n").alias("nb")), F.col("s") < F.col("t"))
    e = F.coalesce("e", F.lit(0)).cast("double")
    return grid.join(sums, ["s", "t"], "left").select("s", "t", "na", "nb", e.alias("e"), F.coalesce("e2", F.lit(0)).cast("double").alias("e2"), (e / (F.col("na") * F.col("nb"))).alias("d"))


def self_density(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """(cls, n, e, d): density inside each class."""
    placed = assign.where("cls > 0")
    a, b = placed.select(F.col("vid").alias("src"), F.col("cls").alias("ca")), placed.select(F.col("vid").alias("dst"), F.col("cls").alias("cb"))
    sums = edges.join(a, "src").join(b, "dst").where("ca = cb").groupBy(F.col("ca").alias("cls")).agg(F.sum("w").cast("double").alias("e"))
    sizes = placed.groupBy("cls").agg(F.count("*").alias("n"))
    e = F.coalesce("e", F.lit(0.0))
    return sizes.join(sums, "cls", "left").select("cls", "n", e.alias("e"), F.when(F.col("n") > 1, 2 * e / (F.col("n") * (F.col("n") - 1))).otherwise(0.0).alias("d"))


def rect_density(edges: DataFrame, a: DataFrame, b: DataFrame) -> DataFrame:
    """(na, nb, e, d) of the sub-rectangle of two disjoint vertex sets."""
    both = edges.select("src", "dst", "w").union(edges.select("dst", "src", "w"))
    e = both.join(a.select(F.col("vid").alias("src")), "src", "left_semi").join(b.select(F.col("vid").alias("dst")), "dst", "left_semi").agg(F.coalesce(F.sum("w"), F.lit(0)).cast("double").alias("e"))
    na, nb = a.count(), b.count()
    return e.select(F.lit(na).cast("long").alias("na"), F.lit(nb).cast("long").alias("nb"), "e", (F.col("e") / max(na * nb, 1)).alias("d"))


def energy(stats: DataFrame, k: int) -> DataFrame:
    """(energy, energy_norm): (1/k^2) sum of d^2, at most 1/2, and its mean over pairs."""
    s = F.coalesce(F.sum(F.col("d") * F.col("d")), F.lit(0.0))
    return stats.agg((s / (k * k)).alias("energy"), (s / max(k * (k - 1) / 2, 1)).alias("energy_norm"))


def energy_mass(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """(energy_mass): d^2 over all ordered pairs of classes weighted by their cells, the classes themselves included.

    Refining a partition without a residue never lowers it (a mean of squares is at least the square of the mean).
    """
    between = pair_density(edges, assign).select((2 * F.col("na") * F.col("nb") * F.col("d") * F.col("d")).alias("m"))
    cells = F.col("n") * F.col("n")
    within = self_density(edges, assign).select((4 * F.col("e") * F.col("e") / cells).alias("m"))
    n = assign.where("cls > 0").agg(F.count("*").cast("double").alias("n"))
    return between.union(within).agg(F.sum("m").alias("m")).join(F.broadcast(n)).select(F.coalesce(F.col("m") / (F.col("n") * F.col("n")), F.lit(0.0)).alias("energy_mass"))  # a row each


def partition_is_uniform(assign: DataFrame, verdict: DataFrame, eps: float) -> DataFrame:
    """(k, residue, bad, uniform): the definition as printed, a residue below eps n and at most eps k^2 bad pairs."""
    sizes = assign.agg(F.countDistinct(F.when(F.col("cls") > 0, F.col("cls"))).alias("k"), F.count(F.when(F.col("cls") == 0, 1)).alias("residue"), F.count("*").alias("n"))
    bad = verdict.where(F.col("status").isNotNull()).agg(F.count(F.when(F.col("status") != blocks.UNIFORM, 1)).alias("bad"))
    return sizes.join(F.broadcast(bad)).select("k", "residue", "bad", ((F.col("residue") < eps * F.col("n")) & (F.col("bad") <= eps * F.col("k") * F.col("k"))).alias("uniform"))  # a row each


def check_equitable(assign: DataFrame, eps: float) -> DataFrame:
    """(k, least, most, residue, n, equal, small_residue)."""
    sizes = assign.groupBy("cls").agg(F.count("*").alias("n"))
    inside = F.col("cls") > 0
    got = sizes.agg(F.sum(F.when(inside, 1).otherwise(0)).alias("k"), F.min(F.when(inside, F.col("n"))).alias("least"), F.max(F.when(inside, F.col("n"))).alias("most"), F.coalesce(F.sum(F.when(~inside, F.col("n"))), F.lit(0)).alias("residue"), F.sum("n").alias("n"))
    return got.withColumn("equal", F.col("least") == F.col("most")).withColumn("small_residue", F.col("residue") < eps * F.col("n"))


def degrees(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """(vid, cls, other, deg): weight of each vertex into each other class, zeros included."""
    placed = assign.where("cls > 0")
    a, b = placed.select(F.col("vid").alias("src"), F.col("cls").alias("ca")), placed.select(F.col("vid").alias("dst"), F.col("cls").alias("cb"))
    cross = edges.join(a, "src").join(b, "dst").where("ca <> cb")
    seen = cross.select(F.col("src").alias("vid"), F.col("cb").alias("other"), "w").union(cross.select(F.col("dst"), F.col("ca"), "w")).groupBy("vid", "other").agg(F.sum("w").alias("deg"))
    grid = placed.join(F.broadcast(placed.select(F.col("cls").alias("other")).distinct()), F.col("cls") != F.col("other"))  # k rows
    return grid.join(seen, ["vid", "other"], "left").select("vid", "cls", "other", F.coalesce("deg", F.lit(0)).cast("double").alias("deg"))


def check_degree(edges: DataFrame, assign: DataFrame, eps: float) -> tuple[DataFrame, DataFrame]:
    """The degree step alone: (verdict rows s, t, mean_deg, n_high, n_low, status), witness rows (s, t, vid).

    For a pair s < t the vertices of t are looked at; the witness is the larger one-sided deviant set.
    """
    deg = degrees(edges, assign).select(F.col("other").alias("s"), F.col("cls").alias("t"), "vid", "deg").where("s < t")
    mean = deg.groupBy("s", "t").agg(F.avg("deg").alias("mean_deg"), F.count("*").alias("m"))
    off = deg.join(mean, ["s", "t"]).withColumn("off", F.col("deg") - F.col("mean_deg")).withColumn("edge", F.lit(eps**4) * F.col("m"))
    count = lambda c: F.sum(F.when(c, 1).otherwise(0))
    sums = off.groupBy("s", "t").agg(F.max("m").alias("m"), F.max("mean_deg").alias("mean_deg"), count(F.col("off") >= F.col("edge")).alias("n_high"), count(F.col("off") <= -F.col("edge")).alias("n_low"))
    bad = (F.col("mean_deg") >= eps**3 * F.col("m")) & (F.col("n_high") + F.col("n_low") >= eps**4 / 8 * F.col("m"))
    verdict = sums.select("s", "t", "m", "mean_deg", "n_high", "n_low", F.when(bad, blocks.WITNESS).otherwise(blocks.UNIFORM).alias("status"))
    chosen = verdict.where(F.col("status") == blocks.WITNESS).select("s", "t", (F.col("n_high") >= F.col("n_low")).alias("high"))
    witness = off.join(chosen, ["s", "t"]).where(F.when(F.col("high"), F.col("off") >= F.col("edge")).otherwise(F.col("off") <= -F.col("edge"))).select("s", "t", "vid")
    return verdict, witness


def frobenius_screen(stats: DataFrame, eps: float) -> DataFrame:
    """(s, t, norm, edge, settled): the Frobenius norm bounds the first singular value from above."""
    norm = F.sqrt(F.greatest(F.col("e2") - F.col("na") * F.col("nb") * F.col("d") * F.col("d"), F.lit(0.0)))
    edge = F.lit(eps**3) * F.sqrt(F.col("na") * F.col("nb"))
    return stats.select("s", "t", norm.alias("norm"), edge.alias("edge"), (norm < edge).alias("settled"))


# ---- block checks --------------------------------------------------------------------------------------------


def check_pairs(assign: DataFrame, eps: float, checker: str, edges: DataFrame | None = None, vertices: DataFrame | None = None, sigma: float | None = None, marks: bool = True, only: set[tuple[int, int]] | None = None, **options) -> DataFrame:
    """One row per pair (vid null: status, d, gap) and per witness vertex (vid, side class).

    Weights are ``edges``; or the Gaussian weights of ``vertices`` with ``sigma``; or, without one, the inner products of
    the vertices' features.  Classes are dealt into lots of at most ``large.SIDE`` members; two lots meet in a task, as one
    dense block from which every pair of their classes is cut.  Larger classes go to ``evenpart.operators.large``, which
    asks the same questions by tiles, joins or sums; ``density`` and ``power`` need no block on edges at any size.

    Points go to all tasks as they are, up to ``MOST_NUMBERS``, so that none is copied for each of its lots' meetings.  Blocks
    leave the witness out without ``marks``, and look at the pairs ``only`` where they are given.
    """
    if edges is not None and checker == "density":  # no block is looked at
        return pair_density(edges, assign).select("s", "t", F.lit(blocks.UNIFORM).alias("status"), "d", F.lit(0.0).alias("gap"), F.lit(None).cast("int").alias("side"), F.lit(None).cast("long").alias("vid"))
    if checker == "power":
        from evenpart.operators.power import check_power

        if edges is None:
            raise ValueError("power sweeps need an edge graph; inner products have the same answer without sweeps (sigma)")
        return check_power(edges, assign, eps, **options)
    placed = assign.where("cls > 0").select("vid", "cls")
    k, most = placed.groupBy("cls").agg(F.count("*").alias("n")).agg(F.max("cls"), F.max("n")).first()
    if k is None or k < 2:
        return assign.sparkSession.createDataFrame([], large.ROWS)
    if most > large.SIDE:
        return _check_large(placed, eps, checker, edges, vertices, sigma, **options)
    points = vertices is not None
    rows = placed.join(vertices.select("vid", "x"), "vid") if points else placed.withColumn("x", F.array().cast("array<double>"))
    # enough lots to spread the work, whole classes each, no more members than a side of a block
    per = max(1, min(large.SIDE // most, -(-k // LOTS)))
    lots = -(-k // per)
    lot = lambda c: F.floor((c - 1) / per).cast("int")
    names = ["s", "t", "status", "d", "gap", "side", "vid"]

    def solve(i: int, j: int, mc: np.ndarray, mv: np.ndarray, xs: np.ndarray | None, e: pd.DataFrame | None) -> pd.DataFrame:
        """Rows of two lots; members are ordered by (class, id)."""
        out, sides = [], []
        at = {int(c): slice(lo, hi) for c, lo, hi in zip(*_spans(mc), strict=True)}
        left, right = ([c for c in at if (c - 1) // per == x] for x in (i, j))
        if points:
            half = slice(0, int(np.searchsorted(mc, i * per + per, side="right"))), slice(0 if i == j else int(np.searchsorted(mc, j * per + 1)), len(mv))
            # few pairs are cut from their own points
            whole = None if only is not None else blocks.gaussian(xs[half[0]], xs[half[1]], sigma) if sigma is not None else xs[half[0]] @ xs[half[1]].T

            def cut_out(s, t):
                if whole is None:
                    return blocks.gaussian(xs[at[s]], xs[at[t]], sigma) if sigma is not None else xs[at[s]] @ xs[at[t]].T
                return whole[at[s], at[t].start - half[1].start : at[t].stop - half[1].start]
        else:
            order = np.argsort(mv)
            place = lambda v: order[np.searchsorted(mv, v, sorter=order)]
            pa, pb, ew = place(e["a"].to_numpy()), place(e["b"].to_numpy()), e["w"].to_numpy()
            pair = mc[pa].astype(np.int64) << 32 | mc[pb]
            by = np.argsort(pair, kind="stable")
            pa, pb, ew, pair = pa[by], pb[by], ew[by], pair[by]

            def cut_out(s, t):
                w = np.zeros((at[s].stop - at[s].start, at[t].stop - at[t].start))
                lo, hi = np.searchsorted(pair, [s << 32 | t, (s << 32 | t) + 1])
                w[pa[lo:hi] - at[s].start, pb[lo:hi] - at[t].start] = ew[lo:hi]
                return w

        for s in left:
            for t in right:
                if s < t and (only is None or (s, t) in only):
                    w = cut_out(s, t)
                    status, gap, ra, cb = blocks.check(w, eps, checker, **options)
                    out.append((s, t, status, float(w.mean()), float(gap), None, None))
                    if marks and status == blocks.WITNESS:
                        sides += [(s, t, s, mv[at[s]][ra]), (s, t, t, mv[at[t]][cb])]
        found = pd.DataFrame(out, columns=names).astype({"side": "Int64", "vid": "Int64"})
        if not sides:
            return found
        each = [np.repeat([mark[c] for mark in sides], [len(mark[3]) for mark in sides]) for c in range(3)]
        witness = pd.DataFrame(dict(zip(("s", "t", "side"), each, strict=True)) | {"vid": np.concatenate([mark[3] for mark in sides])})
        return pd.concat([found, witness.astype({"side": "Int64", "vid": "Int64"})])

    if points:
        n, short, p, odd = rows.agg(F.count("*"), F.min(F.size("x")), F.max(F.size("x")), F.count(F.when(F.exists("x", lambda z: z.isNull()), 1))).first()
        if p and short == p and not odd and n * p <= MOST_NUMBERS:
            return _sent_pairs(rows, n, p, per, lots, only, solve)
    members = rows.withColumn("mine", lot(F.col("cls"))).withColumn("o", F.explode(F.sequence(F.lit(0), F.lit(lots - 1))))
    members = members.select(F.least("mine", "o").alias("i"), F.greatest("mine", "o").alias("j"), "cls", "vid", "x")
    if points:
        between = assign.sparkSession.createDataFrame([], "i int, j int, a long, b long, w double")
    else:
        ends = [placed.select(F.col("vid").alias(v), F.col("cls").alias(c)) for v, c in (("src", "ca"), ("dst", "cb"))]
        e = edges.join(ends[0], "src").join(ends[1], "dst").where("ca <> cb")
        first = F.col("ca") < F.col("cb")
        between = e.select(F.least(lot(F.col("ca")), lot(F.col("cb"))).alias("i"), F.greatest(lot(F.col("ca")), lot(F.col("cb"))).alias("j"), F.when(first, F.col("src")).otherwise(F.col("dst")).alias("a"), F.when(first, F.col("dst")).otherwise(F.col("src")).alias("b"), F.col("w").cast("double").alias("w"))

    def run(key, m: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
        if not len(m):
            return pd.DataFrame([], columns=names).astype({"side": "Int64", "vid": "Int64"})
        m = m.sort_values(["cls", "vid"])
        return solve(int(key[0]), int(key[1]), m["cls"].to_numpy(), m["vid"].to_numpy(), np.stack(m["x"].to_list()) if points else None, e)

    return members.groupBy("i", "j").cogroup(between.groupBy("i", "j")).applyInPandas(run, large.ROWS)


def _sent_pairs(rows: DataFrame, n: int, p: int, per: int, lots: int, only: set[tuple[int, int]] | None, solve: Callable) -> DataFrame:
    """Rows that ``solve`` gives for every two lots of ``per`` classes, of points (vid, cls, x) that every task holds."""
    got = rows.select("cls", "vid", "x").orderBy("cls", "vid").toArrow()  # at most MOST_NUMBERS numbers
    held = got.column("cls").to_numpy(), got.column("vid").to_numpy(), np.concatenate([c.flatten().to_numpy() for c in got.column("x").chunks]).reshape(n, p)
    spark = rows.sparkSession
    sent = spark.sparkContext.broadcast(held)
    met = [(i, j) for i in range(lots) for j in range(i, lots)] if only is None else sorted({tuple(sorted(((s - 1) // per, (t - 1) // per))) for s, t in only})

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        mc, mv, xs = sent.value
        for f in frames:
            for at in f["id"]:
                i, j = met[int(at)]
                parts = [slice(*np.searchsorted(mc, [x * per + 1, x * per + per + 1])) for x in ((i,) if i == j else (i, j))]
                one = [np.concatenate([v[part] for part in parts]) for v in (mc, mv, xs)]
                if len(one[0]) and len(got := solve(i, j, *one, None)):
                    yield got

    tasks = min(len(met), large.MOST_TASKS)
    return spark.range(0, len(met), 1, max(tasks, 1)).mapInPandas(run, large.ROWS)


def _spans(values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Value, begin and end of each run of equal values."""
    begin = np.append(0, np.flatnonzero(values[1:] != values[:-1]) + 1)
    return values[begin], begin, np.append(begin[1:], len(values))


def _check_large(placed: DataFrame, eps: float, checker: str, edges: DataFrame | None, vertices: DataFrame | None, sigma: float | None, **options) -> DataFrame:
    if edges is not None:
        if checker == "sigma":  # the same singular value, by sweeps
            from evenpart.operators.power import check_power

            return check_power(edges, placed, eps, **options)
        source = large.Edges(placed, edges)
    else:
        source = large.Inner(placed, vertices) if sigma is None else large.Gaussian(placed, vertices, sigma)
    if checker == "density":
        none = F.lit(None)
        return large.pair_stats(source, placed).select("s", "t", F.lit(blocks.UNIFORM).alias("status"), "d", F.lit(0.0).alias("gap"), none.cast("int").alias("side"), none.cast("long").alias("vid"))
    if checker == "codegree":
        return large.check_codegree(source, placed, eps, **options)
    if checker == "sigma" and isinstance(source, large.Inner):
        return large.check_spectral(source, placed, eps, **options)
    if checker == "sigma":  # by sweeps over tiles of the kernel
        from evenpart.operators.power import check_power

        return check_power(source, placed, eps, **options)
    raise ValueError(f"{checker} of classes of more than {large.SIDE} points has no way on this graph")


# ---- refinement ----------------------------------------------------------------------------------------------


def pick_partner(verdict: DataFrame, pick: str = "random", seed: int = 42) -> DataFrame:
    """(cls, other): at most one bad partner of each class; q rows in, k rows out."""
    bad = verdict.where(F.col("status") == blocks.WITNESS)
    each = bad.select(F.col("s").alias("cls"), F.col("t").alias("other"), "gap").union(bad.select("t", "s", "gap"))
    key = {"random": F.md5(F.concat_ws(":", F.col("cls").cast("string"), F.col("other").cast("string"), F.lit(str(seed)))), "first": F.lpad(F.col("other").cast("string"), 10, "0"), "max_gap": F.lpad(F.round((F.lit(2.0) - F.col("gap")) * 1e12).cast("long").cast("string"), 20, "0")}[pick]
    return each.groupBy("cls").agg(F.min_by("other", F.struct(key, "other")).alias("other"))


def refine(assign: DataFrame, cells: DataFrame, fanout: int, recycle: str = "class", seed: int = 42) -> DataFrame:
    """(vid, cls) of the next partition; ``cells`` are (cls, vid) inside the chosen witness of their class."""
    size = assign.where("cls > 0").groupBy("cls").count().agg(F.max("count")).first()[0]
    m = size // fanout
    if m < 1:
        raise ValueError(f"classes of {size} can't be split by {fanout}")
    inside = cells.select("cls", "vid", F.lit(1).alias("in"))
    rows = assign.where("cls > 0").join(inside, ["cls", "vid"], "left").select("vid", "cls", F.coalesce("in", F.lit(0)).alias("cell"), order_key(F.col("vid"), seed).alias("key"))
    ranked = rank_within(rows, ["cls", "cell"], "key", "vid")
    counts = rows.groupBy("cls", "cell").agg(F.count("*").alias("cell_n"))
    chunked = cut(ranked.join(counts, ["cls", "cell"]).withColumn("chunk", F.floor(F.col("rank") / m)).withColumn("whole", F.col("chunk") < F.floor(F.col("cell_n") / m)).drop("rank", "cell_n"))
    done = chunked.where("whole").select("vid", "cls", (1 - F.col("cell")).alias("cell"), "chunk")
    left = chunked.where("not whole")
    if recycle != "none":
        pool = rank_within(left.select("vid", "cls", "key"), ["cls"], "key", "vid")
        full = left.groupBy("cls").count().where(F.col("count") >= m).select("cls")
        pooled = pool.where(F.col("rank") < m).join(full, "cls", "left_semi").select("vid", "cls", F.lit(2).alias("cell"), F.lit(0).cast("long").alias("chunk"))
        done = done.unionByName(pooled)
    if recycle == "global":
        rest = assign.select("vid").join(done.select("vid"), "vid", "left_anti").select("vid", order_key(F.col("vid"), seed).alias("key"), F.lit(0).alias("g"))
        n = rest.count()
        extra = rank_within(rest, ["g"], "key", "vid").where(F.col("rank") < n // m * m)
        done = done.unionByName(extra.select("vid", F.lit(2**30).alias("cls"), F.lit(3).alias("cell"), F.floor(F.col("rank") / m).alias("chunk")))
    names = done.select("cls", "cell", "chunk").distinct()  # at most fanout x k rows and a few
    dense = names.withColumn("new", F.row_number().over(Window.orderBy("cls", "cell", "chunk")).cast("int"))  # MOST_CLASSES rows
    placed = done.join(F.broadcast(dense), ["cls", "cell", "chunk"]).select("vid", "new")
    return assign.select("vid").join(placed, "vid", "left").select("vid", F.coalesce("new", F.lit(0)).alias("cls"))


def refine_full(assign: DataFrame, witness: DataFrame) -> DataFrame:
    """All witnesses at once: cells are the members' signatures over partners, chunks have floor(size / 4^k) vertices."""
    size, k = assign.where("cls > 0").groupBy("cls").count().agg(F.max("count"), F.count("*")).first()
    m = size // 4**k
    if m < 1:
        raise ValueError(f"infeasible: {k} classes need at least {4**k} vertices each, they have {size}")
    other = F.when(F.col("side") == F.col("s"), F.col("t")).otherwise(F.col("s"))
    marks = witness.select("vid", other.alias("o")).groupBy("vid").agg(F.array_join(F.array_sort(F.collect_set("o")), ",").alias("cell"))
    rows = assign.where("cls > 0").join(marks, "vid", "left").select("vid", "cls", F.coalesce("cell", F.lit("")).alias("cell"), order_key(F.col("vid"), 42).alias("key"))
    ranked = rank_within(rows, ["cls", "cell"], "key", "vid").join(rows.groupBy("cls", "cell").count(), ["cls", "cell"])
    done = ranked.withColumn("chunk", F.floor(F.col("rank") / m)).where(F.col("chunk") < F.floor(F.col("count") / m))
    dense = done.select("cls", "cell", "chunk").distinct().withColumn("new", F.row_number().over(Window.orderBy("cls", "cell", "chunk")).cast("int"))
    sent = F.broadcast(dense) if k * 4**k <= MOST_NAMES else dense  # at most k 4^k rows
    return assign.select("vid").join(done.join(sent, ["cls", "cell", "chunk"]).select("vid", "new"), "vid", "left").select("vid", F.coalesce("new", F.lit(0)).alias("cls"))


# ---- the loop ------------------------------------------------------------------------------------------------


@dataclass
class Partition:
    assign: DataFrame
    trace: list[dict]
    k: int


def practical_loop(
    vertices: DataFrame, eps: float, fanout: int, h: int | None = None, checker: str = "codegree", edges: DataFrame | None = None, sigma: float | None = None, stop_rule: str = "pair_fraction",
    recycle: str = "class", pick: str = "random", min_parts: int = 0, keep: str = "literal", seed: int = 42, max_classes: int = MOST_CLASSES, memo: dict | None = None, **options,
) -> Partition:
    """Start, test the size, check all pairs, count, refine; every round is written, so lineage stays one round long.

    Loops over the same vertices and graph that share a ``memo`` share their rounds as far as they go the same way.
    """
    def once(way: tuple, make: Callable):
        if memo is None:
            return make()
        if way not in memo:
            memo[way] = make()
        return memo[way]

    n = vertices.count()
    h = max(min_class(eps, fanout) if h is None else h, -(-n // max_classes))
    if edges is not None:
        weights_in_range(edges)
    way: tuple = (fanout, seed)  # what led to the partition
    assign = once(way, lambda: cut(initial_partition(vertices, fanout, seed=seed)))
    k, m, trace, before = fanout, n // fanout, [], None
    while True:
        began = time.monotonic()
        residue = assign.where("cls = 0").count()
        row = {"iter": len(trace) + 1, "k": k, "m": m, "residue": residue, "energy": None, "energy_norm": None, "pairs": k * (k - 1) // 2, "bad": None, "required": None, "stop": None}
        row["cells"], row["checked"] = row["pairs"] * m * m, row["pairs"] if m >= h else 0
        trace.append(row)
        # the size comes first; the densities of the last partition are wanted anyway, so its pairs are measured too
        check = lambda **more: check_pairs(assign, eps, checker if m >= h else "density", edges, None if edges is not None else vertices, sigma, **(options if m >= h else {}), **more)  # noqa: E731, B023
        # blocks of points are made again for the chosen pairs: the witnesses of all would be k n / 2 rows
        again = edges is None and checker != "power" and m <= large.SIDE
        asked = (*way, "check", checker if m >= h else "density", *((eps, *sorted(options.items())) if m >= h else ()))
        found = once(asked, lambda: cut(check(marks=not again) if again else check()))  # noqa: B023
        verdict = found.where(F.col("status").isNotNull())
        s2, bad = verdict.agg(F.sum(F.col("d") * F.col("d")), F.sum((F.col("status") != blocks.UNIFORM).cast("int"))).first()
        row["seconds"] = time.monotonic() - began
        row["energy"], row["energy_norm"] = (s2 or 0.0) / k**2, (s2 or 0.0) / max(row["pairs"], 1)
        if m < h:
            row["stop"] = "class_too_small"
            if keep == "last_valid" and before is not None:
                return Partition(before[0], trace, before[1])
            return Partition(assign, trace, k)
        limit = eps * k * k if stop_rule == "k_squared" else eps * row["pairs"]
        row["bad"], row["required"] = int(bad or 0), max(0, int(np.ceil(row["pairs"] - limit)))
        if row["bad"] <= limit and k >= min_parts:
            row["stop"] = "few_bad_pairs"
            return Partition(assign, trace, k)
        if m // fanout < 1 or k * fanout > max_classes:
            row["stop"] = "max_classes"
            return Partition(assign, trace, k)
        before = (assign, k)

        def refined() -> DataFrame:
            chosen, rows = pick_partner(verdict, pick, seed + len(trace)), found  # noqa: B023
            if again:  # noqa: B023
                chosen = cut(chosen)
                rows = cut(check(only={(min(r), max(r)) for r in chosen.select("cls", "other").collect()}))  # noqa: B023  a row a class
            marks = rows.where("vid is not null").select(F.col("side").alias("cls"), F.when(F.col("side") == F.col("s"), F.col("t")).otherwise(F.col("s")).alias("other"), "vid")
            return cut(refine(assign, marks.join(chosen, ["cls", "other"], "left_semi").select("cls", "vid"), fanout, recycle, seed + len(trace)))  # noqa: B023

        way = (*asked, "refine", pick, recycle)
        assign = once(way, refined)
        k, m = assign.agg(F.max("cls")).first()[0], m // fanout


def weights_in_range(edges: DataFrame) -> None:
    """Densities are shares of a full graph: a weight outside [0, 1] has no meaning in any check."""
    low, high = edges.agg(F.min("w"), F.max("w")).first()
    if low is not None and not 0 <= low <= high <= 1:
        raise ValueError(f"weights from {low} to {high}: scale them to [0, 1] (graphs.scaled) or make them 0 and 1 (graphs.binarize)")


def full_loop(vertices: DataFrame, eps: float, parts: int, checker: str = "codegree", edges: DataFrame | None = None, sigma: float | None = None, max_rounds: int = 3, seed: int = 42) -> Partition:
    """The unmodified loop: stops when at most eps k^2 pairs are bad, and raises where its classes can't be split.

    ``stop`` of the last round is ``few_bad_pairs``, or ``max_rounds`` where the loop was left early.
    """
    if edges is not None:
        weights_in_range(edges)
    assign, k, trace = cut(initial_partition(vertices, parts, seed=seed)), parts, []
    while True:
        found = cut(check_pairs(assign, eps, checker, edges, None if edges is not None else vertices, sigma))
        verdict = found.where(F.col("status").isNotNull())
        s2, bad = verdict.agg(F.sum(F.col("d") * F.col("d")), F.sum((F.col("status") != blocks.UNIFORM).cast("int"))).first()
        row = {"iter": len(trace) + 1, "k": k, "m": vertices.count() // k if not trace else trace[-1]["next"], "bad": int(bad or 0), "limit": eps * k * k, "energy": (s2 or 0.0) / k**2, "stop": None}
        trace.append(row)
        if row["bad"] <= row["limit"] or len(trace) >= max_rounds:
            row["stop"] = "few_bad_pairs" if row["bad"] <= row["limit"] else "max_rounds"
            return Partition(assign, trace, k)
        row["next"] = row["m"] // 4**k
        assign = cut(refine_full(assign, found.where("vid is not null").select("s", "t", "side", "vid")))
        k = assign.agg(F.max("cls")).first()[0]


def probe_gap(edges: DataFrame, assign: DataFrame, s: int, t: int, trials: int = 20, seed: int = 42) -> float:
    """Largest density gap over random halves of a pair: a lower bound on how uneven it is.

    Every vertex carries its coins of all trials, so that one pass over the edges gives the weights of all halves.
    """
    placed = assign.where(F.col("cls").isin(s, t))
    coin = lambda side: F.array(*[md5_coin(F.col("vid"), F.lit(f"{seed}:{i}:{side}")) < 0.5 for i in range(trials)])
    placed = cut(placed.select("vid", "cls", F.when(F.col("cls") == s, coin("a")).otherwise(coin("b")).alias("half")))
    counts = placed.groupBy("cls").agg(F.count("*").alias("n"), *[F.sum(F.col("half")[i].cast("long")).alias(f"n{i}") for i in range(trials)])
    n = {r["cls"]: r for r in counts.collect()}  # two rows
    half = lambda end: placed.select(F.col("vid").alias(end), F.col("half").alias(f"half_{end}"))
    sent = F.broadcast if placed.count() <= MOST_PLACED else (lambda df: df)
    met = between_classes(edges, placed.select("vid", "cls")).join(sent(half("src")), "src").join(sent(half("dst")), "dst")
    sums = met.agg(F.sum("w").alias("e"), *[F.sum(F.when(F.col("half_src")[i] & F.col("half_dst")[i], F.col("w"))).alias(f"e{i}") for i in range(trials)]).first()
    density = lambda e, a, b: float(e or 0.0) / max(a * b, 1)
    whole = density(sums["e"], n[s]["n"], n[t]["n"])
    return max((abs(density(sums[f"e{i}"], n[s][f"n{i}"], n[t][f"n{i}"]) - whole) for i in range(trials)), default=0.0)
