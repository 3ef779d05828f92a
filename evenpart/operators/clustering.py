"""Summary graph, its clustering, lifting back, the residue's vote, baselines and measures."""

from __future__ import annotations

import json
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.ml.clustering import GaussianMixture, KMeans, PowerIterationClustering
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evenpart.functions import blocks
from evenpart.operators import graphs
from evenpart.operators.local import MOST_CLASSES
from evenpart.operators.partition import Partition, check_pairs, initial_partition, practical_loop
from evenpart.plans.scratch import cut, release


#: All pairs of a table of this many points are looked at; of larger ones the pairs inside hashed groups of ``SCALE_GROUP``.
ALL_PAIRS, SCALE_GROUP = 2048, 256


def median_scale(vertices: DataFrame, seed: int = 42) -> float:
    """Median distance over pairs of points, every point of the table being in as many of them as any other."""
    n = vertices.count()
    group = F.lit(0) if n <= ALL_PAIRS else F.pmod(F.xxhash64("vid", F.lit(seed)), F.lit(n // SCALE_GROUP))

    def distances(f: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(f["x"].to_list())
        return pd.DataFrame({"dist": np.concatenate([np.zeros(0), *[np.sqrt(((x[i + 1 :] - x[i]) ** 2).sum(1)) for i in range(len(x) - 1)]])})

    pairs = vertices.select("x", group.alias("g")).groupBy("g").applyInPandas(distances, "dist double")
    got = pairs.agg(F.percentile_approx("dist", 0.5, 100_000)).first()[0]
    return float(got or 0.0) or 1.0


def summary_graph(verdict: DataFrame, edges: str = "all", d_min: float = 0.0) -> DataFrame:
    """(s, t, w, uniform): all pairs by density, or the uniform pairs above ``d_min`` only."""
    out = verdict.where(F.col("status").isNotNull()).select("s", "t", F.col("d").alias("w"), (F.col("status") == blocks.UNIFORM).alias("uniform"))
    return out if edges == "all" else out.where(F.col("uniform") & (F.col("w") > d_min))


def matrix(summary: DataFrame, k: int) -> np.ndarray:
    if k > MOST_CLASSES:
        raise ValueError(f"{k} classes: raise h")
    a, got = np.zeros((k, k)), summary.select("s", "t", "w").toArrow()  # k(k-1)/2 rows
    s, t, w = (got.column(i).to_numpy() for i in range(3))
    a[s - 1, t - 1] = a[t - 1, s - 1] = w
    return a


def cluster_summary(summary: DataFrame, k: int, c: int, method: str = "spectral", seed: int = 42) -> np.ndarray:
    a = matrix(summary, k)
    return blocks.dominant_set_labels(a, c) if method == "dominant" else blocks.spectral_labels(a, c, seed)


def lift(assign: DataFrame, labels: np.ndarray) -> DataFrame:
    """(vid, cls, cluster): members inherit their class's cluster; the residue has none yet."""
    table = assign.sparkSession.createDataFrame([(i + 1, int(x)) for i, x in enumerate(labels)], "cls int, cluster int")
    return assign.join(F.broadcast(table), "cls", "left").select("vid", "cls", "cluster")


def vote(queries: DataFrame, labelled: DataFrame, vote_k: int = 5) -> DataFrame:
    """(vid, cluster) of each query by its nearest labelled points; ties: smaller mean distance, smaller label."""
    near = graphs.knn(queries, labelled.select("vid", "x"), vote_k).join(labelled.select("vid", "cluster"), "vid")
    counts = near.groupBy("qid", "cluster").agg(F.count("*").alias("n"), F.avg("dist").alias("mean"))
    best = Window.partitionBy("qid").orderBy(F.desc("n"), F.round("mean", 9), "cluster")
    return counts.withColumn("r", F.row_number().over(best)).where("r = 1").select(F.col("qid").alias("vid"), "cluster")


def edge_vote(residue: DataFrame, labelled: DataFrame, edges: DataFrame) -> DataFrame:
    """(vid, cluster) of residue vertices of an edge graph by total weight; without neighbours, the largest cluster."""
    both = edges.select(F.col("src").alias("vid"), F.col("dst").alias("o"), "w").union(edges.select("dst", "src", "w"))
    sums = both.join(residue.select("vid"), "vid", "left_semi").join(labelled.select(F.col("vid").alias("o"), "cluster"), "o").groupBy("vid", "cluster").agg(F.sum("w").alias("w"))
    top = sums.groupBy("vid").agg(F.max_by("cluster", F.struct("w", -F.col("cluster"))).alias("cluster"))
    largest = labelled.groupBy("cluster").count().orderBy(F.desc("count"), "cluster").first()["cluster"]
    return residue.select("vid").join(top, "vid", "left").select("vid", F.coalesce("cluster", F.lit(largest)).alias("cluster"))


@dataclass
class Model:
    """A fitted clustering: labels (vid, cls, cluster, via), the trace and the summary's labels."""

    labels: DataFrame
    partition: Partition
    classes: np.ndarray
    vertices: DataFrame

    def predict(self, points: DataFrame, vote_k: int = 5) -> DataFrame:
        return vote(points, self.labels.join(self.vertices.select("vid", "x"), "vid"), vote_k)

    def save(self, path: str) -> None:
        """Labelled points, classes and trace under ``path``; ``load`` gives the model back."""
        self.labels.join(self.vertices.select("vid", *[c for c in ("x", "y") if c in self.vertices.columns]), "vid").write.mode("overwrite").parquet(f"{path}/labels")
        self.partition.assign.write.mode("overwrite").parquet(f"{path}/assign")
        meta = json.dumps({"trace": self.partition.trace, "k": int(self.partition.k), "classes": [int(c) for c in self.classes]})
        self.labels.sparkSession.createDataFrame([(meta,)], "meta string").coalesce(1).write.mode("overwrite").json(f"{path}/meta")


def load(spark: SparkSession, path: str) -> Model:
    """A saved model, which predicts as the one that was saved."""
    labelled, meta = spark.read.parquet(f"{path}/labels"), json.loads(spark.read.json(f"{path}/meta").first()["meta"])
    vertices = labelled.drop("cls", "cluster", "via")
    return Model(labelled.select("vid", "cls", "cluster", "via"), Partition(spark.read.parquet(f"{path}/assign"), meta["trace"], meta["k"]), np.array(meta["classes"]), vertices)


def kernel_points(vertices: DataFrame, sigma: float, kernel: str = "exact", dims: int = 128, seed: int = 42) -> tuple[DataFrame, float | None]:
    """Points and scale as ``check_pairs`` takes them: the points themselves, or random features whose inner products approach the weights.

    ``features`` makes every pass over the complete graph one pass over the points, so that its cost is linear in them.
    """
    if kernel == "exact":
        return vertices, sigma
    if kernel != "features":
        raise ValueError(f"kernel {kernel}: exact or features")
    return cut(graphs.random_features(vertices, sigma, dims, seed).withColumnRenamed("phi", "x")), None


def fit(
    vertices: DataFrame, c: int, eps: float = 0.3, fanout: int = 2, h: int | None = None, edges: DataFrame | None = None, sigma: float | None = None, method: str = "spectral", vote_k: int = 5, seed: int = 42,
    partition: Partition | None = None, kernel: str = "exact", dims: int = 128, **options,
) -> Model:
    """Both phases: partition, summary, its clustering, lift, residue.

    Without ``edges`` the graph is the Gaussian kernel of the points.  The residue joins by a vote of its nearest
    neighbours where the vertices have features, else by the weights of its edges.
    """
    points, scale = None, None
    if edges is None:
        points, scale = kernel_points(vertices, median_scale(vertices) if sigma is None else sigma, kernel, dims, seed)
    options.setdefault("min_parts", max(fanout, c + 1))
    part = partition or practical_loop(vertices if points is None else points, eps, fanout, h, edges=edges, sigma=scale, seed=seed, **options)
    found = check_pairs(part.assign, eps, "density", edges, points, scale).where("status is not null")
    classes = cluster_summary(summary_graph(found), part.k, c, method, seed)
    lifted = lift(part.assign, classes)
    inside = cut(lifted.where("cls > 0").withColumn("via", F.lit("class")))
    rest = lifted.where("cls = 0").select("vid")
    if "x" in vertices.columns:
        voted = vote(vertices.join(rest, "vid", "left_semi"), inside.join(vertices.select("vid", "x"), "vid"), vote_k)
    else:
        voted = edge_vote(rest, inside, edges)
    labels = inside.unionByName(voted.select("vid", F.lit(0).alias("cls"), "cluster", F.lit("vote").alias("via")))
    return Model(labels, part, classes, vertices)


# ---- measures ------------------------------------------------------------------------------------------------


def confusion(labels: DataFrame, truth: DataFrame) -> DataFrame:
    return labels.join(truth.select("vid", "y"), "vid").groupBy("cluster", "y").agg(F.count("*").alias("n"))


def quality(table: DataFrame) -> dict:
    """Accuracy under the best one-to-one map, beside majority rate, purity, NMI, ARI and clusters in use."""
    rows = table.collect()  # clusters x classes
    cs, ys = sorted({r["cluster"] for r in rows}), sorted({str(r["y"]) for r in rows})
    m = np.zeros((len(cs), len(ys)))
    for r in rows:
        m[cs.index(r["cluster"]), ys.index(str(r["y"]))] += r["n"]
    return {k: float(v) for k, v in blocks.scores(m).items()}


def compression(n: int, k: int) -> dict:
    return {"size": f"{n}-{k}", "ratio": n / k, "cells": (n / k) ** 2}


# ---- baselines -----------------------------------------------------------------------------------------------


def _vectors(vertices: DataFrame) -> DataFrame:
    return vertices.withColumn("features", array_to_vector("x"))


def kmeans(vertices: DataFrame, c: int, seed: int = 42) -> DataFrame:
    v = _vectors(vertices)
    return KMeans(k=c, seed=seed, featuresCol="features", predictionCol="cluster").fit(v).transform(v).select("vid", "cluster")


def gmm(vertices: DataFrame, c: int, seed: int = 42) -> DataFrame:
    v = _vectors(vertices)
    return GaussianMixture(k=c, seed=seed, featuresCol="features", predictionCol="cluster", maxIter=30).fit(v).transform(v).select("vid", "cluster")


def lloyd(vertices: DataFrame, c: int, steps: int = 5) -> DataFrame:
    """(vid, cluster) by Lloyd steps from the c smallest ids; centres are c rows of the driver."""
    centres = [r["x"] for r in vertices.orderBy("vid").limit(c).collect()]
    p, placed = len(centres[0]), None
    for step in range(steps + 1):
        dist = [graphs.dist2(F.col("x"), F.array(*map(F.lit, z))) for z in centres]
        best = F.array_min(F.array(*[F.struct(F.round(d, 9).alias("d"), F.lit(j).alias("j")) for j, d in enumerate(dist)]))["j"]
        placed = vertices.withColumn("cluster", best)
        if step < steps:
            got = {r["cluster"]: r["m"] for r in placed.groupBy("cluster").agg(F.array(*[F.avg(F.col("x")[i]) for i in range(p)]).alias("m")).collect()}
            centres = [got.get(j, z) for j, z in enumerate(centres)]
    return placed.select("vid", "cluster")


#: Numbers of all vectors together that are sent to all tasks; longer ones stay distributed.
MOST_VECTORS = 16_000_000
#: Sources of a lot of edges.
SOURCES = 20_000


def spectral(edges: DataFrame, vertices: DataFrame, c: int, seed: int = 42, sweeps: int = 30) -> DataFrame:
    """Normalised spectral clustering of an edge graph by subspace iteration: c products with the graph a sweep.

    The edges are dealt once, by their source, and stay where they are; the vectors, c numbers a vertex, are sent to
    all tasks, which give the products of their edges back.  Vectors of more than ``MOST_VECTORS`` numbers stay
    distributed.  The rows, scaled to unit length, are clustered by k-means.
    """
    if not edges.__dict__.get("_scratch"):
        edges = cut(edges)  # read for the degrees and for the products
    held = vertices.select("vid", F.array(*[graphs.md5_coin(F.col("vid"), F.lit(j), F.lit(seed)) - 0.5 for j in range(c)]).alias("q")).where("vid IS NOT NULL")
    if held.count() * c > MOST_VECTORS:
        return _spectral_joined(edges, vertices, c, seed, sweeps)
    spark, got = vertices.sparkSession, held.orderBy("vid").toArrow()  # at most MOST_VECTORS numbers
    vid, q = got.column("vid").to_numpy(), np.concatenate([z.flatten().to_numpy() for z in got.column("q").chunks] or [np.zeros(0)]).reshape(-1, c)
    both = edges.select("src", "dst", "w").union(edges.select("dst", "src", "w"))
    lots = max(spark.sparkContext.defaultParallelism, len(vid) // SOURCES)
    placed = cut(both.repartition(lots, "src").sortWithinPartitions("src"))
    ids = spark.sparkContext.broadcast(vid)

    def times(values: np.ndarray) -> np.ndarray:
        sent, width = spark.sparkContext.broadcast(values), values.shape[1]

        def run(batches):
            vid, v = ids.value, sent.value
            for batch in batches:
                src, dst, w = (batch.column(i).to_numpy() for i in range(3))
                i, j = (np.minimum(np.searchsorted(vid, z), len(vid) - 1) for z in (src, dst))
                known = (vid[i] == src) & (vid[j] == dst)
                i, j, w = i[known], j[known], w[known]
                at = np.flatnonzero(np.append(True, i[1:] != i[:-1])) if len(i) else np.zeros(0, int)
                if len(at):
                    total = np.add.reduceat(w[:, None] * v[j], at, axis=0)
                    yield pa.RecordBatch.from_arrays([pa.array(i[at]), *[pa.array(total[:, r]) for r in range(width)]], names=["at", *[f"c{r}" for r in range(width)]])

        parts = placed.mapInArrow(run, ", ".join(["at long", *[f"c{r} double" for r in range(width)]])).toArrow()  # a row a vertex, and one more at the edges of batches
        sent.destroy()
        return np.stack([np.bincount(parts.column(0).to_numpy(), parts.column(r + 1).to_numpy(), minlength=len(vid)) for r in range(width)], axis=1)

    deg = times(np.ones((len(vid), 1)))
    r = np.where(deg > 0, 1 / np.sqrt(np.maximum(deg, 1e-300)), 0.0)
    for _ in range(sweeps // 5):
        for _ in range(5):
            # A + I keeps the order of the eigenvalues and makes the largest ones largest in size
            q = q + r * times(r * q)
        vals, vecs = np.linalg.eigh(q.T @ q)
        q = q @ (vecs / np.sqrt(np.maximum(vals, 1e-30)))
    ids.destroy()
    release(placed)
    found = pa.table({"vid": vid, "x": pa.FixedSizeListArray.from_arrays(pa.array(q.ravel()), c).cast(pa.list_(pa.float64()))})
    return kmeans(graphs.standardise(cut(spark.createDataFrame(found)), "l2"), c, seed)


def _spectral_joined(edges: DataFrame, vertices: DataFrame, c: int, seed: int, sweeps: int) -> DataFrame:
    """``spectral`` with distributed vectors: a sweep is one join and one aggregation over the edges, and the driver sees a c x c matrix only."""
    both = edges.select("src", "dst", "w").union(edges.select("dst", "src", "w"))
    deg = both.groupBy("src").agg(F.sum("w").alias("deg"))
    scale = cut(vertices.select("vid").join(deg.withColumnRenamed("src", "vid"), "vid", "left").select("vid", F.coalesce(1 / F.sqrt("deg"), F.lit(0.0)).alias("r")))
    norm = cut(both.join(scale.select(F.col("vid").alias("src"), F.col("r").alias("a")), "src").join(scale.select(F.col("vid").alias("dst"), F.col("r").alias("b")), "dst").select("src", "dst", (F.col("w") * F.col("a") * F.col("b")).alias("w")))
    q = cut(scale.select("vid", F.array(*[graphs.md5_coin(F.col("vid"), F.lit(j), F.lit(seed)) - 0.5 for j in range(c)]).alias("q")))
    for _ in range(sweeps // 5):
        for _ in range(5):
            # A + I keeps the order of the eigenvalues and makes the largest ones largest in size
            moved = norm.join(q.withColumnRenamed("vid", "dst"), "dst").groupBy("src").agg(*[F.sum(F.col("w") * F.col("q")[j]).alias(f"c{j}") for j in range(c)])
            q = q.join(moved.withColumnRenamed("src", "vid"), "vid", "left").select("vid", F.array(*[F.col("q")[j] + F.coalesce(F.col(f"c{j}"), F.lit(0.0)) for j in range(c)]).alias("q"))
        q = cut(q)
        g = q.agg(*[F.sum(F.col("q")[i] * F.col("q")[j]).alias(f"g{i}_{j}") for i in range(c) for j in range(c)]).first()
        gram = np.array([[g[f"g{i}_{j}"] for j in range(c)] for i in range(c)])
        vals, vecs = np.linalg.eigh(gram)
        t = vecs / np.sqrt(np.maximum(vals, 1e-30))
        q = q.select("vid", F.array(*[sum((F.col("q")[i] * F.lit(float(t[i, j])) for i in range(c)), F.lit(0.0)) for j in range(c)]).alias("q"))
    return kmeans(graphs.standardise(q.withColumnRenamed("q", "x"), "l2"), c, seed)


#: Rows and columns of a tile of the complete kernel.
TILE_ROWS, TILE_COLUMNS = 1024, 4096


def spectral_kernel(vertices: DataFrame, c: int, sigma: float | None = None, scales: DataFrame | None = None, seed: int = 42, sweeps: int = 30) -> DataFrame:
    """``spectral`` of the complete Gaussian graph, with one sigma or self-tuned by (vid, s): every pair counts in every product.

    The n x n weights are stored nowhere: a task makes them tile by tile for its rows and multiplies them at once.  The
    points and c numbers a point are sent to all tasks, so memory grows with n, whatever it is, while the work grows with
    its square.
    """
    spark = vertices.sparkSession
    start = F.array(*[graphs.md5_coin(F.col("vid"), F.lit(j), F.lit(seed)) - 0.5 for j in range(c)]).alias("q")
    held = vertices.select("vid", "x") if scales is None else vertices.select("vid", "x").join(scales.select("vid", "s"), "vid")
    got = held.select("*", start).orderBy("vid").toArrow()  # features of n points
    vid, n = got.column("vid").to_numpy(), got.num_rows
    x, q = (np.concatenate([z.flatten().to_numpy() for z in got.column(name).chunks]).reshape(n, -1) for name in ("x", "q"))
    points = spark.sparkContext.broadcast((x, None if scales is None else got.column("s").to_numpy()))

    def times(values: np.ndarray) -> np.ndarray:
        sent = spark.sparkContext.broadcast(values)

        def run(batches):
            (x, s), v = points.value, sent.value
            for batch in batches:
                for lo in (batch.column(0).to_numpy() * TILE_ROWS).tolist():
                    rows = slice(lo, min(lo + TILE_ROWS, len(x)))
                    total = np.zeros((rows.stop - lo, v.shape[1]))
                    for at in range(0, len(x), TILE_COLUMNS):
                        cols = slice(at, min(at + TILE_COLUMNS, len(x)))
                        w = blocks.gaussian(x[rows], x[cols], sigma) if s is None else blocks.gaussian(x[rows], x[cols], s[rows], s[cols])
                        own = np.arange(max(lo, at), min(rows.stop, cols.stop))
                        w[own - lo, own - at] = 0.0
                        total += w @ v[cols]
                    yield pa.RecordBatch.from_arrays([pa.array([lo]), pa.array([total.ravel()])], names=["lo", "v"])

        lots = -(-n // TILE_ROWS)
        parts = spark.range(0, lots, 1, lots).mapInArrow(run, "lo long, v array<double>").toArrow().sort_by("lo")  # n x c numbers
        sent.destroy()
        return np.concatenate([p.reshape(-1, values.shape[1]) for p in parts.column("v").to_numpy()])

    deg = times(np.ones((n, 1)))
    r = np.where(deg > 0, 1 / np.sqrt(np.maximum(deg, 1e-300)), 0.0)
    for _ in range(sweeps // 5):
        for _ in range(5):
            q = q + r * times(r * q)
        vals, vecs = np.linalg.eigh(q.T @ q)
        q = q @ (vecs / np.sqrt(np.maximum(vals, 1e-30)))
    points.destroy()
    found = pa.table({"vid": vid, "x": pa.FixedSizeListArray.from_arrays(pa.array(q.ravel()), c).cast(pa.list_(pa.float64()))})
    return kmeans(graphs.standardise(cut(spark.createDataFrame(found)), "l2"), c, seed)


def landmark(vertices: DataFrame, c: int, sample: int = 300, seed: int = 42, sigma: float | None = None) -> DataFrame:
    """Spectral clustering of a bounded sample (smallest md5), extended to all by the nearest sampled points."""
    drawn = vertices.orderBy(F.md5(F.concat_ws(":", F.col("vid").cast("string"), F.lit(str(seed)))), "vid").limit(sample).select("vid", "x").collect()
    from evenpart.operators.local import affinity

    drawn = sorted(drawn, key=lambda r: r["vid"])
    labels = blocks.spectral_labels(affinity(np.array([r["x"] for r in drawn]), "median" if sigma is None else sigma), c, seed)
    base = vertices.sparkSession.createDataFrame([(r["vid"], list(r["x"]), int(v)) for r, v in zip(drawn, labels, strict=True)], "vid long, x array<double>, cluster int")
    rest = vote(vertices.join(F.broadcast(base.select("vid")), "vid", "left_anti"), base, 1)
    return base.select("vid", "cluster").union(rest)


def spectral_on_centroids(vertices: DataFrame, c: int, k: int, seed: int = 42) -> DataFrame:
    """(vid, cluster): k-means compresses the points to ``k`` centres, spectral clustering groups the centres."""
    from evenpart.operators.local import affinity

    v = _vectors(vertices)
    fitted = KMeans(k=k, seed=seed, featuresCol="features", predictionCol="cls").fit(v)
    labels = blocks.spectral_labels(affinity(np.array(fitted.clusterCenters())), c, seed)  # k rows
    return lift(fitted.transform(v).select("vid", (F.col("cls") + 1).alias("cls")), labels).select("vid", "cluster")


def cost(partition: Partition) -> DataFrame:
    """(iter, k, pairs, checked, cells, seconds) of each round: pairs looked at, pairs tested, cells they span."""
    spark = partition.assign.sparkSession
    rows = [(r["iter"], r["k"], r["pairs"], r["checked"], r["cells"], r["seconds"]) for r in partition.trace]
    return spark.createDataFrame(rows, "iter int, k int, pairs long, checked long, cells long, seconds double")


def power_iteration(edges: DataFrame, c: int) -> DataFrame:
    # the graph's parts are dropped when memory is short and made again from the edges, which must not make these again
    return PowerIterationClustering(k=c, maxIter=20, weightCol="w").assignClusters(cut(edges)).select(F.col("id").alias("vid"), "cluster")


def random_partition(vertices: DataFrame, k: int, seed: int = 42) -> Partition:
    return Partition(initial_partition(vertices, k, seed=seed), [], k)


def random_labels(vertices: DataFrame, c: int, seed: int = 42) -> DataFrame:
    """(vid, cluster) by md5 coin."""
    return vertices.select("vid", F.floor(graphs.md5_coin(F.col("vid"), F.lit(seed)) * c).cast("int").alias("cluster"))


def majority_rate(vertices: DataFrame) -> DataFrame:
    n = vertices.groupBy("y").agg(F.count("*").alias("n"))
    return n.agg((100.0 * F.max("n") / F.sum("n")).alias("rate"), F.count("*").alias("classes"), F.sum("n").alias("n"))
