"""Vertices with features, and weighted graphs (src < dst, w)."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evenpart.plans.scratch import cut
from evenpart.sources.tables import read_table

#: The points of a complete graph are sent to every task up to this many.
MOST_BROADCAST = 200_000
#: Points of a task and of a tile of the complete graph.
PAIR_ROWS, PAIR_COLUMNS = 128, 2048
#: A product of two local scales at least: a point among many copies has scale 0, weight 1 to copies and 0 to all others.
LEAST_SCALE = 1e-300


def md5_coin(*parts: Column) -> Column:
    """A number in [0, 1) from the md5 of the parts joined by colons: the same in every SQL engine."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[p.cast("string") for p in parts])), 1, 8), 16, 10).cast("long") / F.lit(float(2**32))


def dist2(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)


# ---- vertices ------------------------------------------------------------------------------------------------

LETTERS = "eaionrstlduhc"


DIGITS, CAPITALS, MARKS, BLANKS = "0123456789", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", ".,;:!?", " \t\n\r\f\v"


def text_shape(text: Column) -> Column:
    """20 numbers of a text's shape: log length, words, lines, shares of kinds of characters and of 13 letters.

    A kind of characters is counted by what is left of the length when they are deleted, which needs no regular expression.
    """
    n = F.greatest(F.length(text), F.lit(1)).cast("double")
    share = lambda chars: (F.length(text) - F.length(F.translate(text, chars, ""))) / n
    plain = F.length(F.regexp_replace(text, r"[^\x00-\x7F]+", ""))
    return F.array(F.log(n + 1), share(BLANKS), share("\n"), share(DIGITS), share(CAPITALS), (F.length(text) - plain) / n, share(MARKS), *[share(c) for c in LETTERS])


def standardise(vertices: DataFrame, how: str | None = "z") -> DataFrame:
    """Scale every feature: z-scores, min-max, or unit length; constant features become 0."""
    if how is None:
        return vertices
    if how == "l2":
        norm = F.sqrt(F.aggregate("x", F.lit(0.0), lambda s, v: s + v * v))
        return vertices.withColumn("x", F.transform("x", lambda v: F.when(norm > 0, v / norm).otherwise(0.0)))
    vertices = cut(vertices)  # read for its size, for its sums and for the result
    head = vertices.select("x").first()
    if head is None:
        return vertices
    p = len(head[0])
    low = (lambda c: F.avg(c)) if how == "z" else (lambda c: F.min(c))
    size = (lambda c: F.stddev_pop(c)) if how == "z" else (lambda c: F.max(c) - F.min(c))
    got = vertices.agg(*[low(F.col("x")[i]).alias(f"a{i}") for i in range(p)], *[size(F.col("x")[i]).alias(f"b{i}") for i in range(p)]).first()
    return vertices.withColumn("x", F.array(*[(F.col("x")[i] - F.lit(got[f"a{i}"])) / F.lit(got[f"b{i}"]) if got[f"b{i}"] else F.lit(0.0) for i in range(p)]))


def doc_vertices(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    return standardise(docs.select(F.col("doc_id").alias("vid"), text_shape(F.col("text")).alias("x"), F.col("lang").alias("y")))


def emb_vertices(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("vid"), F.transform("embedding", lambda v: v.cast("double")).alias("x"), F.col("label").cast("string").alias("y"))


# ---- neighbours ----------------------------------------------------------------------------------------------


#: Points of a block of queries and of the base: a task holds the distances of one block to another.
KNN_BLOCK = 4096


#: Numbers of the base that are sent to all tasks; a larger base is dealt into blocks.
MOST_SENT = 24_000_000
#: Points of a box of the base at most; queries that a task looks at together; boxes that each looks at before all others.
BOX, ASKED, FIRST = 512, 2048, 4


def boxes(x: np.ndarray, vid: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, ends): points halved along their widest coordinate until no part has more than ``BOX``; ascending ids inside a part."""
    done, todo = [], [np.arange(len(x))]
    while todo:
        at = todo.pop()
        if len(at) <= BOX:
            done.append(at[np.argsort(vid[at], kind="stable")])
            continue
        part, half = x[at], len(at) // 2
        cut_at = np.argpartition(part[:, np.argmax(part.max(0) - part.min(0))], half)
        todo += [at[cut_at[half:]], at[cut_at[:half]]]
    return np.concatenate(done), np.cumsum([len(d) for d in done])


class Nearest:
    """The k nearest points of a base in boxes: a box is looked at for the queries it may hold a nearer point for."""

    def __init__(self, x: np.ndarray, vid: np.ndarray) -> None:
        order, ends = boxes(x, vid)
        self.x, self.vid, self.edges = x[order], vid[order], np.append(0, ends)
        self.low, self.high = (np.stack([f(self.x[a:b], axis=0) for a, b in zip(self.edges[:-1], self.edges[1:], strict=True)]) for f in (np.min, np.max))
        self.norm = (self.x**2).sum(1)

    def __call__(self, qid: np.ndarray, q: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """(vid, dist) of k places a query, ascending by (distance to 9 digits, vid); distance infinite where there are fewer."""
        n, size = len(q), (q**2).sum(1)
        dist, vid = np.full((n, k), np.inf), np.full((n, k), np.iinfo(np.int64).max)
        far = np.empty((n, len(self.low)))  # squared distances to the boxes
        for lo in range(0, n, 64):
            part = q[lo : lo + 64, None]
            far[lo : lo + 64] = (np.maximum(np.maximum(self.low - part, part - self.high), 0) ** 2).sum(2)
        seen = np.zeros(far.shape, bool)

        def most(rows: np.ndarray) -> np.ndarray:
            # roundings of the product and to 9 digits must not lose a point
            d = dist[rows, -1] + 2e-9
            return d**2 + 1e-12 * (size[rows] + 1)

        def look(b: int, rows: np.ndarray) -> None:
            a, z = self.edges[b], self.edges[b + 1]
            y, v = self.x[a:z], self.vid[a:z]
            seen[rows, b] = True
            near = self.norm[a:z][None] - 2 * q[rows] @ y.T + size[rows, None]
            hit = near <= most(rows)[:, None] + 1e-12 * self.norm[a:z][None]
            hit &= qid[rows, None] != v[None]
            some = hit.sum(1)
            few = hit[(some > 0) & (some <= k + 16)]
            if len(few):
                i, j = np.nonzero(few)
                mine = rows[(some > 0) & (some <= k + 16)]
                width = np.bincount(i, minlength=len(mine))
                place = np.arange(len(i)) - np.repeat(np.cumsum(width) - width, width)
                d, w = np.full((len(mine), width.max()), np.inf), np.full((len(mine), width.max()), np.iinfo(np.int64).max)
                d[i, place], w[i, place] = np.sqrt(((y[j] - q[mine[i]]) ** 2).sum(1)), v[j]
                keep(mine, d, w)
            many = rows[some > k + 16]
            for lo in range(0, len(many), 64):
                mine = many[lo : lo + 64]
                d = np.sqrt(((y[None] - q[mine, None]) ** 2).sum(2))
                d[qid[mine, None] == v[None]] = np.inf
                o = np.argsort(np.round(d, 9), axis=1, kind="stable")[:, :k]
                keep(mine, np.take_along_axis(d, o, 1), v[o])

        def keep(rows: np.ndarray, d: np.ndarray, v: np.ndarray) -> None:
            d, v = np.concatenate([dist[rows], d], axis=1), np.concatenate([vid[rows], v], axis=1)
            o = np.lexsort((v, np.round(d, 9)), axis=1)[:, :k]
            dist[rows], vid[rows] = np.take_along_axis(d, o, 1), np.take_along_axis(v, o, 1)

        nearest = np.argsort(far, axis=1, kind="stable")[:, :FIRST]
        for r in range(nearest.shape[1]):
            for b in np.unique(nearest[:, r]):
                rows = np.flatnonzero(nearest[:, r] == b)
                rows = rows[far[rows, b] <= most(rows)]
                if len(rows):
                    look(b, rows)
        for b in range(far.shape[1]):
            rows = np.flatnonzero(~seen[:, b] & (far[:, b] <= most(np.arange(n))))
            if len(rows):
                look(b, rows)
        return vid, dist


def knn(queries: DataFrame, base: DataFrame, k: int) -> DataFrame:
    """(qid, vid, dist, rank): the k nearest base points of each query but itself; ties by (distance, vid).

    The base goes to all tasks, in boxes that let a query pass by most of them, and nothing else is shuffled than the
    queries.  A base of more than ``MOST_SENT`` numbers, or with points that are null, is searched block by block.
    """
    whole = F.coalesce(F.col("vid").isNotNull() & F.forall("x", lambda z: z.isNotNull()), F.lit(False))
    n, short, p, odd = base.agg(F.count("*"), F.min(F.size("x")), F.max(F.size("x")), F.count(F.when(~whole, 1))).first()
    if not n or odd or short != p or not p or n * p > MOST_SENT:
        return _knn_blocks(queries, base, k)
    spark, got = queries.sparkSession, base.select(F.col("vid").cast("long").alias("vid"), F.col("x").cast("array<double>").alias("x")).toArrow()  # at most MOST_SENT numbers
    x = np.concatenate([c.flatten().to_numpy() for c in got.column("x").chunks]).reshape(n, p)
    held = spark.sparkContext.broadcast(Nearest(x, got.column("vid").to_numpy()))
    del got, x

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        search = held.value
        for batch in batches:
            for lo in range(0, batch.num_rows, ASKED):
                part = batch.slice(lo, ASKED)
                qid, q = part.column(0).to_numpy(), part.column(1).flatten().to_numpy().reshape(part.num_rows, p)
                vid, dist = search(qid, q, k)
                good = np.isfinite(dist)
                i, r = np.nonzero(good)
                yield pa.RecordBatch.from_arrays([pa.array(qid[i]), pa.array(vid[good]), pa.array(dist[good]), pa.array((r + 1).astype(np.int32))], names=["qid", "vid", "dist", "rank"])

    lots = 4 * spark.sparkContext.defaultParallelism
    asked = queries.select(F.col("vid").cast("long").alias("qid"), F.col("x").cast("array<double>").alias("x"))
    return asked.repartition(lots, "qid").mapInArrow(run, "qid long, vid long, dist double, rank int")


#: Points of a block of queries and of the base: a task holds the distances of one block to another.
KNN_BLOCK = 4096


def _knn_blocks(queries: DataFrame, base: DataFrame, k: int) -> DataFrame:
    """``knn`` of any base.

    Queries and base are dealt into blocks, every block of the one meets every block of the other (the work of an exact
    search) as one matrix product, and only k rows a query and block are shuffled.
    """
    lots = [max(1, -(-d.count() // KNN_BLOCK)) for d in (queries, base)]
    lot = lambda c, n: F.pmod(F.xxhash64(c), F.lit(n)).cast("int")
    asked = queries.select(F.col("vid").alias("qid"), "x", lot("vid", lots[0]).alias("i"), F.explode(F.sequence(F.lit(0), F.lit(lots[1] - 1))).alias("j"))
    blocks = base.select("vid", F.col("x").alias("y"), lot("vid", lots[1]).alias("j"), F.explode(F.sequence(F.lit(0), F.lit(lots[0] - 1))).alias("i"))

    def search(key: tuple, q: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(q) or not len(b):
            return pd.DataFrame({"qid": [], "vid": [], "dist": []}).astype({"qid": "int64", "vid": "int64", "dist": "float64"})
        b = b.sort_values("vid")
        x, y, vid, qid = np.stack(q["x"].to_list()), np.stack(b["y"].to_list()), b["vid"].to_numpy(), q["qid"].to_numpy()
        near = ((y**2).sum(1)[None] - 2 * x @ y.T) + (x**2).sum(1)[:, None]
        near[qid[:, None] == vid[None]] = np.inf
        # a few more than k by the product, whose rounding may turn close ones round; then k by exact distances
        some = min(k + 16, len(vid))
        at = np.argpartition(near, some - 1, axis=1)[:, :some]
        at.sort(axis=1)
        dist = np.sqrt(((y[at] - x[:, None]) ** 2).sum(2))
        dist[vid[at] == qid[:, None]] = np.inf
        order = np.argsort(np.round(dist, 9), axis=1, kind="stable")[:, :k]
        at, dist = np.take_along_axis(at, order, 1), np.take_along_axis(dist, order, 1)
        good = np.isfinite(dist)
        # ties beyond the extra places: the last place taken must be farther than the k-th
        edge = np.sort(near, axis=1)[:, min(k - 1, len(vid) - 1)]
        for r in np.flatnonzero((near <= edge[:, None] + 1e-9 * np.maximum(1, np.abs(edge[:, None]))).sum(1) > some):
            d = np.sqrt(((y - x[r]) ** 2).sum(1))
            d[vid == qid[r]] = np.inf
            o = np.argsort(np.round(d, 9), kind="stable")[: at.shape[1]]
            at[r], dist[r], good[r] = o, d[o], np.isfinite(d[o])
        return pd.DataFrame({"qid": np.repeat(qid, at.shape[1])[good.ravel()], "vid": vid[at].ravel()[good.ravel()], "dist": dist.ravel()[good.ravel()]})

    found = asked.groupBy("i", "j").cogroup(blocks.groupBy("i", "j")).applyInPandas(search, "qid long, vid long, dist double")
    order = Window.partitionBy("qid").orderBy(F.round("dist", 9), "vid")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def log_n(n: int) -> int:
    return max(1, round(math.log(max(n, 2))))


def knn_edges(near: DataFrame, symmetrize: str = "union") -> DataFrame:
    """(src, dst, dist) from a k-NN table, kept if either end (union) or both ends (mutual) list the other."""
    seen = near.select(F.least("qid", "vid").alias("src"), F.greatest("qid", "vid").alias("dst"), "dist").groupBy("src", "dst").agg(F.min("dist").alias("dist"), F.count("*").alias("n"))
    return seen.where("n >= 1" if symmetrize == "union" else "n = 2").drop("n")


# ---- graphs --------------------------------------------------------------------------------------------------


def affinity_pairs(vertices: DataFrame, sigma: float | None = None, scales: DataFrame | None = None, least: float | None = None) -> DataFrame:
    """Every pair's Gaussian weight: with one sigma, or self-tuned by (vid, s); only weights of at least ``least`` if it is given.

    Tasks take some points each and make the rows of their tiles; the squares are summed coordinate by coordinate, as an
    SQL engine sums them.  Points without or of unequal coordinates are joined pair by pair, and their weights may be null.
    """
    v = vertices.select("vid", "x") if scales is None else vertices.select("vid", "x").join(scales.select("vid", "s"), "vid")
    v = v.where("vid IS NOT NULL")
    whole = F.coalesce(F.forall("x", lambda z: z.isNotNull()), F.lit(False))
    n, short, long_, odd = v.agg(F.count("*"), F.min(F.size("x")), F.max(F.size("x")), F.count(F.when(~whole, 1))).first()
    if n > MOST_BROADCAST:
        raise ValueError(f"{n} points: use a k-NN graph or random features")
    if not n or odd or short != long_ or not short:
        w = _joined_pairs(v, sigma)
        return w if least is None else w.where(F.col("w") >= least)
    spark, got = v.sparkSession, v.orderBy("vid").toArrow()  # at most MOST_BROADCAST rows
    x = np.concatenate([c.flatten().to_numpy() for c in got.column("x").chunks]).reshape(n, short).T.copy()
    held = spark.sparkContext.broadcast((got.column("vid").to_numpy(), x, None if scales is None else got.column("s").to_numpy()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vid, x, s = held.value
        for batch in batches:
            for lo in (batch.column(0).to_numpy() * PAIR_ROWS).tolist():
                rows = slice(lo, min(lo + PAIR_ROWS, n))
                for at in range(lo, n, PAIR_COLUMNS):
                    cols = slice(at, min(at + PAIR_COLUMNS, n))
                    d2 = np.zeros((rows.stop - lo, cols.stop - at))
                    for z in x:
                        off = z[rows, None] - z[None, cols]
                        off *= off
                        d2 += off
                    w = np.exp(-d2 / (2.0 * sigma**2) if s is None else -d2 / np.maximum(s[rows, None] * s[None, cols], LEAST_SCALE))
                    keep = vid[rows, None] < vid[None, cols]
                    if least is not None:
                        keep &= w >= least
                    i, j = np.nonzero(keep)
                    yield pa.RecordBatch.from_arrays([pa.array(vid[lo + i]), pa.array(vid[at + j]), pa.array(w[i, j])], names=["src", "dst", "w"])

    lots = -(-n // PAIR_ROWS)
    form = v.schema["vid"].dataType.simpleString()
    return spark.range(0, lots, 1, lots).mapInArrow(run, f"src {form}, dst {form}, w double")


def _joined_pairs(v: DataFrame, sigma: float | None) -> DataFrame:
    extra = [c for c in v.columns if c == "s"]
    a = v.select(F.col("vid").alias("src"), F.col("x").alias("xa"), *[F.col(c).alias("sa") for c in extra])
    b = v.select(F.col("vid").alias("dst"), F.col("x").alias("xb"), *[F.col(c).alias("sb") for c in extra])
    d2 = dist2(F.col("xa"), F.col("xb"))
    w = F.exp(-d2 / F.greatest(F.col("sa") * F.col("sb"), F.lit(LEAST_SCALE))) if extra else F.exp(-d2 / F.lit(2.0 * sigma**2))
    return a.join(b, F.col("src") < F.col("dst")).select("src", "dst", w.alias("w"))


def local_scales(vertices: DataFrame, rank: int = 7) -> DataFrame:
    """(vid, s): distance to the rank-th neighbour."""
    return knn(vertices, vertices, rank).where(F.col("rank") == rank).select(F.col("qid").alias("vid"), F.col("dist").alias("s"))


def binarize(edges: DataFrame, tau: float) -> DataFrame:
    return edges.where(F.col("w") >= tau).select("src", "dst", F.lit(1.0).alias("w"))


#: Members of a hub that one task pairs with as many others; larger hubs are dealt into parts.
HUB_PART = 2048


#: Pairs that meet in hubs, counted again for each hub, up to which members are sent with their lists; memberships that are sent to all tasks beyond it.
MOST_LISTED, MOST_HELD = 20_000_000, 10_000_000


def co_occurrence(rows: DataFrame, entity: str, hub: str) -> DataFrame:
    """(src, dst, w): how many hubs two entities share.  The cost is the sum of squared hub degrees.

    The members of a hub are dealt into parts of about ``HUB_PART``, and every two parts meet on a key of their own, so that
    no task pairs out a hot hub alone.  A member goes to its own task with the list of larger members it meets; pairs
    are made and counted there and cross no exchange.  Where these lists would be long but the memberships are few, all
    tasks get the memberships instead and nothing else is dealt.
    """
    held = cut(rows.select(F.col(entity).alias("v"), F.col(hub).alias("hub")).where("v IS NOT NULL AND hub IS NOT NULL").distinct())
    n, met = held.groupBy("hub").agg(F.count("*").alias("n")).agg(F.sum("n"), F.sum(F.col("n").cast("double") * (F.col("n") - 1) / 2)).first()
    if n and n <= MOST_HELD and met > MOST_LISTED and held.schema["v"].dataType.simpleString() in ("int", "bigint"):
        return _counted(held)
    large = held.groupBy("hub").agg(F.count("*").alias("n")).where(F.col("n") > HUB_PART).select("hub", F.ceil(F.col("n") / HUB_PART).cast("int").alias("parts"))
    dealt = held.join(large, "hub", "left").withColumn("parts", F.coalesce("parts", F.lit(1))).withColumn("part", F.pmod(F.xxhash64("v"), "parts").cast("int"))
    lists = dealt.groupBy("hub", "part", "parts").agg(F.sort_array(F.collect_list("v")).alias("l"))
    # the only part of a hub: a sorted list, so that the larger members are what follows
    one = lists.where("parts = 1").select(F.posexplode("l").alias("i", "src"), "l").where(F.col("i") < F.size("l") - 1).select("src", F.slice("l", F.col("i") + 2, F.size("l")).alias("b"))
    parts = lists.where("parts > 1").withColumn("o", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    far = parts.select("hub", F.col("o").alias("p"), F.col("part").alias("q"), F.col("l").alias("b"))
    many = parts.select("hub", F.col("part").alias("p"), F.col("o").alias("q"), "l").join(far, ["hub", "p", "q"]).select(F.explode("l").alias("src"), "b")
    met = one.union(many.select("src", F.filter("b", lambda z: z > F.col("src")).alias("b")))
    return met.repartition("src").select("src", F.explode("b").alias("dst")).groupBy("src", "dst").agg(F.count("*").alias("w"))


def _counted(held: DataFrame) -> DataFrame:
    """``co_occurrence`` of distinct (v, hub) that every task can hold: it counts the larger members of the hubs of its own entities."""
    spark, form, got = held.sparkSession, held.schema["v"].dataType.simpleString(), held.toArrow()  # at most MOST_HELD rows
    vid, v = np.unique(got.column("v").to_numpy(), return_inverse=True)
    _, h = np.unique(got.column("hub").to_numpy(), return_inverse=True)
    del got
    by_hub = np.lexsort((v, h))
    members, ends = v[by_hub].astype(np.int32), np.cumsum(np.bincount(h))
    # of every entity: where the larger members of its hubs begin and end in ``members``
    order = np.argsort(members, kind="stable")
    first, last, edges = (order + 1).astype(np.int32), ends[h[by_hub][order]].astype(np.int32), np.append(0, np.cumsum(np.bincount(v, minlength=len(vid))))
    sent = spark.sparkContext.broadcast((vid, members, first, last, edges))
    lots = max(4 * spark.sparkContext.defaultParallelism, len(vid) // 256)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vid, members, first, last, edges = sent.value
        src, dst, w, size = [], [], [], 0

        def out() -> pa.RecordBatch:
            cols = [np.repeat(vid[src], [len(d) for d in dst]), vid[np.concatenate(dst)], np.concatenate(w).astype(np.int64)]
            return pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["src", "dst", "w"])

        for batch in batches:
            for lot in batch.column(0).to_pylist():
                for i in range(lot, len(vid), lots):
                    a, b = edges[i], edges[i + 1]
                    count = np.bincount(np.concatenate([members[x:y] for x, y in zip(first[a:b].tolist(), last[a:b].tolist(), strict=True)]), minlength=len(vid))
                    src.append(i)
                    dst.append(np.flatnonzero(count))
                    w.append(count[dst[-1]])
                    size += len(dst[-1])
                    if size >= 200_000:
                        yield out()
                        src, dst, w, size = [], [], [], 0
        if size:
            yield out()

    return spark.range(0, lots, 1, lots).mapInArrow(run, f"src {form}, dst {form}, w long")


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    bought = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").join(read_table(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return co_occurrence(bought, "o_custkey", "l_partkey")


def scaled(edges: DataFrame) -> DataFrame:
    """Weights divided by the largest, so that they lie in [0, 1]."""
    most = edges.agg(F.max("w")).first()[0] or 1
    return edges.select("src", "dst", (F.col("w") / F.lit(float(most))).alias("w"))


def planted(spark: SparkSession, n: int, blocks: int, p_in: float, p_out: float, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """Vertices (vid, y) in blocks of consecutive ids and a 0/1 graph from md5 coins."""
    size = -(-n // blocks)
    v = spark.range(n).select(F.col("id").alias("vid"), F.floor(F.col("id") / size).cast("int").alias("y"))
    a, b = v.select(F.col("vid").alias("src"), F.col("y").alias("ya")), v.select(F.col("vid").alias("dst"), F.col("y").alias("yb"))
    coin = md5_coin(F.col("src"), F.col("dst"), F.lit(seed))
    e = a.join(b, F.col("src") < F.col("dst")).where(coin < F.when(F.col("ya") == F.col("yb"), p_in).otherwise(p_out))
    return v, e.select("src", "dst", F.lit(1.0).alias("w"))


def planted_on(pairs: DataFrame, blocks: int, p_in: float, p_out: float, seed: int = 42) -> DataFrame:
    """A 0/1 graph on the distinct pairs (src, dst) with src < dst: md5 coins, heavier where both ids leave one remainder by ``blocks``."""
    held = pairs.where("src < dst").distinct()
    same = F.col("src") % blocks == F.col("dst") % blocks
    return held.where(md5_coin(F.col("src"), F.col("dst"), F.lit(seed)) < F.when(same, p_in).otherwise(p_out)).select("src", "dst", F.lit(1.0).alias("w"))


def random_features(vertices: DataFrame, sigma: float, dims: int = 256, seed: int = 42) -> DataFrame:
    """(vid, phi): phi(x) . phi(y) approaches the Gaussian weight, so densities become products of class means."""
    p = len(vertices.select("x").first()[0])
    rng = np.random.default_rng(seed)
    w, b = rng.normal(size=(p, dims)) / sigma, rng.uniform(0, 2 * np.pi, dims)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            if len(f):
                yield pd.DataFrame({"vid": f["vid"], "phi": list(np.sqrt(2 / dims) * np.cos(np.stack(f["x"].to_list()) @ w + b))})

    return vertices.select("vid", "x").mapInPandas(run, "vid long, phi array<double>")


def sample_edges(edges: DataFrame, rate: float, seed: int = 42) -> DataFrame:
    """A fixed share of the edges, by md5 coin; weights are scaled so that densities keep their mean."""
    return edges.where(md5_coin(F.col("src"), F.col("dst"), F.lit(seed)) < rate).withColumn("w", F.col("w") / rate)
