"""The published experiment workloads on the given tables (no table of the publication is available offline)."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpart.operators import graphs as G
from evenpart.operators.clustering import confusion, fit, median_scale, quality, summary_graph
from evenpart.operators.grids import cross_validate, grid
from evenpart.operators.partition import check_pairs, initial_partition
from evenpart.plans.scratch import cut
from evenpart.queries.registry import registry
from evenpart.sources.tables import read_table

QUERIES, ORACLES, query = registry()

#: The published grid: 25 evenly spaced values of eps and 6 of the refinement number.
EPS, FANOUT = tuple(round(0.15 + 0.35 * i / 24, 6) for i in range(25)), (2, 3, 4, 5, 6, 7)
#: The engine's choice of a partner and of the kept partition, and the boxed procedure's own.
OURS = {"pick": "max_gap", "keep": "last_valid", "sigma": "median"}
BOXED = {"pick": "random", "keep": "literal", "sigma": "median", "policy": "lemma_order", "anchors": "typical"}


def _labelled(spark, sf, column):
    docs = read_table(spark, sf, "documents", "doc_id", "text").join(read_table(spark, sf, "labels", "doc_id", column), "doc_id").where(F.col(column).isNotNull())
    return cut(G.standardise(docs.select(F.col("doc_id").alias("vid"), G.text_shape(F.col("text")).alias("x"), F.col(column).cast("string").alias("y"))))


def _turns(spark, sf):
    t = read_table(spark, sf, "conversations", "conv_id", "turn", "role", "text").where("role IS NOT NULL")
    return cut(G.standardise(t.select((F.col("conv_id") * 1000 + F.col("turn")).alias("vid"), G.text_shape(F.col("text")).alias("x"), F.col("role").alias("y"))))


def _pages(spark, sf):
    p = read_table(spark, sf, "pages", "page_id", "html").withColumn("y", F.regexp_extract("html", r"<html[^>]*\blang=.([a-z]+)", 1)).where("y <> ''")
    return cut(G.standardise(p.select(F.col("page_id").alias("vid"), G.text_shape(F.col("html")).alias("x"), "y")))


def _segments(spark, sf):
    """Customers by balance and by number, sum and mean price of their orders; the market segment is unrelated to these."""
    o = read_table(spark, sf, "orders", "o_custkey", "o_totalprice").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").cast("double").alias("n"), F.sum("o_totalprice").alias("s"), F.avg("o_totalprice").alias("a"))
    c = read_table(spark, sf, "customer", "c_custkey", "c_acctbal", "c_mktsegment").join(o, "c_custkey", "left").na.fill(0.0, ["c_acctbal", "n", "s", "a"])
    return cut(G.standardise(c.select(F.col("c_custkey").alias("vid"), F.array("c_acctbal", "n", "s", "a").alias("x"), F.col("c_mktsegment").alias("y"))))


def _part_types(spark, sf):
    p = read_table(spark, sf, "part", "p_partkey", "p_size", "p_retailprice", "p_type")
    return cut(G.standardise(p.select(F.col("p_partkey").alias("vid"), F.array(F.col("p_size").cast("double"), F.col("p_retailprice").cast("double")).alias("x"), F.col("p_type").alias("y"))))


def _rings(spark):
    """Two rings of 200 points, one inside the other: shapes no centroid method separates."""
    v = spark.range(400).withColumn("a", F.col("id") * 2 * 3.141592653589793 / 200)
    r = F.when(F.col("id") < 200, 1.0).otherwise(4.0) + (G.md5_coin(F.col("id"), F.lit(7)) - 0.5) / 5
    return v.select(F.col("id").alias("vid"), F.array(r * F.cos("a"), r * F.sin("a")).alias("x"), F.when(F.col("id") < 200, "in").otherwise("out").alias("y"))


def _languages(spark, sf):
    """Documents by language, the task with the clearest structure."""
    return cut(G.doc_vertices(spark, sf))


def _blocks(spark):
    """240 points of a graph planted in four blocks: a point's features are its ties to 24 fixed points."""
    v, e = G.planted(spark, 240, 4, 0.8, 0.2)
    ties = e.select(F.col("src").alias("vid"), F.col("dst").alias("o")).union(e.select("dst", "src")).where("o % 10 = 0")
    held = ties.groupBy("vid").agg(F.collect_set("o").alias("os"))
    x = F.array(*[F.array_contains(F.coalesce("os", F.array().cast("array<long>")), F.lit(10 * i)).cast("double") for i in range(24)])
    return cut(v.join(held, "vid", "left").select("vid", x.alias("x"), F.col("y").cast("string").alias("y")))


def _field(name: str, kind: str):
    return F.from_json("setting", f"{name} {kind}")[name].alias(name)


def _pairs(**more):
    return [{**OURS, "eps": e, "fanout": f, **more} for e in EPS for f in FANOUT]


def _joined(parts):
    out = None
    for part in parts:
        out = part if out is None else out.unionByName(part)
    return out


SCORES = ("accuracy", "majority", "purity", "nmi", "ari")


def _tasks(spark, sf):
    """(name, points, clusters)."""
    return [
        ("languages", _languages(spark, sf), 4), ("quality", _labelled(spark, sf, "quality"), 2), ("toxic", _labelled(spark, sf, "toxic"), 2), ("roles", _turns(spark, sf), 3), ("pages", _pages(spark, sf), 4),
        ("embeddings", cut(G.emb_vertices(spark, sf)), 10), ("rings", _rings(spark), 2), ("blocks", _blocks(spark), 4),
    ]


# ---- accuracy surface and tables of sizes, energy and stop counts --------------------------------------------------


def surface(vertices: DataFrame, clusters: tuple[int, ...], eps=EPS, fanout=FANOUT) -> DataFrame:
    """eps, fanout, c, k, accuracy of the method, and the flat planes of self-tuned spectral clustering (complete and k-NN graph) and k-means."""
    settings = [{**OURS, "eps": e, "fanout": f, "c": c} for c in clusters for e in eps for f in fanout]
    flat = [{"method": "spectral", "self_tuned": True, "c": c, **knn} for c in clusters for knn in ({}, {"knn": "log_n"})] + [{"method": "kmeans", "c": c} for c in clusters]
    got = grid(vertices, settings + flat)
    method = F.coalesce(F.get_json_object("setting", "$.method"), F.lit("proposed"))
    return got.select(method.alias("method"), _field("knn", "string"), _field("eps", "double"), _field("fanout", "int"), _field("c", "int"), "n", "k", F.round("accuracy", 4).alias("accuracy"), F.round("majority", 4).alias("majority"))


query(name="exp_accuracy_surface")(lambda spark, sf: surface(_labelled(spark, sf, "quality"), (2, 4)))
query(name="exp_accuracy_surface_languages")(lambda spark, sf: surface(_languages(spark, sf), (4,), EPS[::4]))


def _each_task(spark, sf, settings, view, names=None):
    return _joined(view(grid(points, [{**s, "c": c} for s in settings])).select(F.lit(name).alias("task"), "*") for name, points, c in _tasks(spark, sf) if names is None or name in names)


@query()
def exp_summary_sizes(spark: SparkSession, sf: str) -> DataFrame:
    """Classes by eps and fanout on every task: more for larger eps at a small fanout, and k = fanout^i."""
    settings = [{**OURS, "eps": e, "fanout": f, "keep": "literal"} for e in (0.15, 0.33, 0.5) for f in FANOUT]
    return _each_task(spark, sf, settings, lambda g: g.select(_field("eps", "double"), _field("fanout", "int"), "n", "k", "iters", "stop"), ("quality", "toxic", "pages", "rings", "blocks"))


@query()
def exp_energy_partitions(spark: SparkSession, sf: str) -> DataFrame:
    """Energy of the first partitions at fanout 2, with both picks and both checkers."""
    settings = [{**how, "eps": e, "fanout": 2, "keep": "literal", "checker": checker} for e in (0.15, 0.33, 0.5) for checker in ("codegree", "sigma") for how in (OURS, {"pick": "random", "sigma": "median"})]

    def view(got):
        each = got.select(_field("eps", "double"), _field("checker", "string"), _field("pick", "string"), F.posexplode(F.arrays_zip("energy", "energy_norm")).alias("at", "e"))
        return each.select("eps", "checker", "pick", (F.col("at") + 1).alias("partition"), F.round("e.energy", 6).alias("energy"), F.round("e.energy_norm", 6).alias("energy_norm")).where("partition <= 4")

    return _each_task(spark, sf, settings, view, ("quality", "toxic", "pages", "blocks"))


@query()
def exp_stop_table(spark: SparkSession, sf: str) -> DataFrame:
    """Uniform pairs required and present where the loop stops, under both stop rules and both checkers."""
    settings = [{**OURS, "eps": e, "fanout": f, "min_parts": 0, "stop_rule": rule, "checker": checker} for e, f in ((0.6, 2), (0.7, 6), (0.7, 7)) for rule in ("pair_fraction", "k_squared") for checker in ("codegree", "sigma")]
    view = lambda g: g.select(_field("eps", "double"), _field("fanout", "int"), _field("stop_rule", "string"), _field("checker", "string"), F.element_at("required", -1).alias("required"), (F.element_at("pairs", -1) - F.element_at("bad", -1)).alias("present"), "iters", "stop")
    return _joined(
        view(grid(points, [{**s, "c": 2} for s in settings])).select(F.lit(name).alias("task"), "*") for name, points, _ in _tasks(spark, sf) if name in ("quality", "toxic", "pages")
    )


@query()
def exp_ablation(spark: SparkSession, sf: str) -> DataFrame:
    """Each modification taken out in turn: the pick, the recycled residue, the partition kept, the anchors; and no refinement at all."""
    base = {**OURS, "eps": 0.3, "fanout": 4}
    kinds = {
        "ours": base, "boxed": {**BOXED, "eps": 0.3, "fanout": 4}, "random_pick": {**base, "pick": "random"}, "first_pick": {**base, "pick": "first"}, "no_recycling": {**base, "recycle": "none"},
        "global_recycling": {**base, "recycle": "global"}, "literal_stop": {**base, "keep": "literal"}, "fanout_2": {**base, "fanout": 2}, "sampled_anchors": {**base, "anchors": 16},
        "random_classes": {"method": "random_partition", "k": 16, "sigma": "median"},
    }
    parts = []
    for name, points, c in _tasks(spark, sf):
        if name in ("quality", "toxic", "pages", "rings", "blocks"):
            got = grid(points, [{**s, "c": c, "kind": kind} for kind, s in kinds.items()])
            parts.append(got.select(F.lit(name).alias("task"), _field("kind", "string"), "n", "k", "iters", *[F.round(x, 4).alias(x) for x in SCORES], "clusters"))
    return _joined(parts)


# ---- comparisons ---------------------------------------------------------------------------------------------------


def _methods(c: int) -> list[dict]:
    ours = {**OURS, "eps": 0.3, "fanout": 4}
    return [
        {**ours, "checker": "codegree"}, {**ours, "checker": "sigma"}, {**BOXED, "eps": 0.3, "fanout": 4, "checker": "codegree"}, {"method": "spectral", "knn": "log_n"}, {"method": "spectral"}, {"method": "spectral", "self_tuned": True},
        {"method": "spectral", "self_tuned": True, "knn": "log_n"}, {"method": "kmeans"}, {"method": "landmark", "sample": 100}, {"method": "random_partition", "k": 4 * c, "sigma": "median"}, {"method": "random_labels"},
    ]


def head_to_head(tasks) -> DataFrame:
    return _joined(grid(points, [{**s, "c": c} for s in _methods(c)]).select(F.lit(name).alias("task"), "setting", "n", "k", *[F.round(s, 4).alias(s) for s in SCORES], "clusters") for name, points, c in tasks)


query(name="exp_head_to_head")(lambda spark, sf: head_to_head(_tasks(spark, sf)))
query(name="exp_relational_null")(lambda spark, sf: head_to_head([("segments", _segments(spark, sf), 5), ("part_types", _part_types(spark, sf), 6)]))
query(name="exp_synthetic")(lambda spark, sf: head_to_head([("rings", _rings(spark), 2), ("blocks", _blocks(spark), 4)]))


def _over_folds(points: DataFrame, c: int, settings: list[dict], select=("accuracy",)) -> DataFrame:
    """Mean and deviation over the five turns, and the settings they learned."""
    got = cross_validate(points, c, settings, select=select)
    learned = F.array_sort(F.collect_set(F.concat_ws(" ", F.round("eps", 4).cast("string"), F.col("fanout").cast("string"), "method", "keep")))
    return got.groupBy("chosen_by").agg(F.count("*").alias("folds"), F.round(F.avg("accuracy"), 4).alias("accuracy"), F.round(F.stddev_pop("accuracy"), 4).alias("deviation"), F.round(F.avg("majority"), 4).alias("majority"), learned.alias("learned"))


@query()
def exp_five_fold(spark: SparkSession, sf: str) -> DataFrame:
    """The published protocol on the whole grid: each fold in turn learns (eps, fanout), by labels and by energy, and the rest of the data scores."""
    tasks = [("quality", _labelled(spark, sf, "quality"), 2), ("pages", _pages(spark, sf), 4)]
    return _joined(_over_folds(points, c, _pairs(), ("accuracy", "energy")).select(F.lit(name).alias("task"), "*") for name, points, c in tasks)


@query()
def exp_five_fold_wide(spark: SparkSession, sf: str) -> DataFrame:
    """The learning fold also picks how the summary is clustered, the checker and which partition is kept, on every sixth eps of the grid."""
    wide = [{**s, "method": m, "keep": keep, "checker": checker} for s in _pairs() if s["eps"] in EPS[::6] for m in ("proposed", "dominant") for keep in ("literal", "last_valid") for checker in ("codegree", "sigma")]
    return _joined(_over_folds(points, c, wide).select(F.lit(name).alias("task"), "*") for name, points, c in _tasks(spark, sf) if name in ("quality", "toxic"))


@query()
def exp_dominant_summary(spark: SparkSession, sf: str) -> DataFrame:
    """The summary clustered by dominant sets instead of eigenvectors, on all tasks."""
    settings = [{**OURS, "eps": 0.3, "fanout": 4, "method": m} for m in ("proposed", "dominant")]
    return _each_task(spark, sf, settings, lambda g: g.select(_field("method", "string"), "n", "k", *[F.round(s, 4).alias(s) for s in SCORES], "clusters"))


@query()
def exp_checker_agreement(spark: SparkSession, sf: str) -> DataFrame:
    """How often the two checkers put a pair of points together or apart alike (pair counts from the table of labels)."""
    got = grid(_labelled(spark, sf, "quality"), [{**OURS, "eps": e, "fanout": 4, "c": 2, "checker": k} for e in (0.2, 0.3, 0.4) for k in ("codegree", "sigma")])
    flat = got.select(_field("eps", "double"), _field("checker", "string"), F.posexplode("labels").alias("i", "label"))
    both = flat.groupBy("eps", "i").agg(F.max(F.when(F.col("checker") == "codegree", F.col("label"))).alias("a"), F.max(F.when(F.col("checker") == "sigma", F.col("label"))).alias("b"))
    two = lambda c: F.sum(c * (c - 1) / 2)
    cells = cut(both.groupBy("eps", "a", "b").agg(F.count("*").alias("m")))
    joint = cells.groupBy("eps").agg(two(F.col("m")).alias("ab"), F.sum("m").alias("n"))
    one = lambda c: cells.groupBy("eps", c).agg(F.sum("m").alias("m")).groupBy("eps").agg(two(F.col("m")).alias(f"p{c}"))
    total = F.col("n") * (F.col("n") - 1) / 2
    return joint.join(one("a"), "eps").join(one("b"), "eps").select("eps", "n", F.round((total + 2 * F.col("ab") - F.col("pa") - F.col("pb")) / total, 6).alias("agreement"))


@query()
def exp_summary_literal(spark: SparkSession, sf: str) -> DataFrame:
    """The summary as defined (uniform pairs above 1/2) beside all pairs by density: edges, and classes left without one."""
    v, k, out = G.doc_vertices(spark, sf), 16, None
    v, scale = cut(v), median_scale(v)
    assign = cut(initial_partition(v, k))
    classes = spark.range(1, k + 1).select(F.col("id").cast("int").alias("cls"))
    for eps in (0.3, 0.5, 0.6):
        verdict = cut(check_pairs(assign, eps, "sigma", None, v, scale).where("status IS NOT NULL"))
        for edges in ("all", "uniform"):
            g = summary_graph(verdict, edges, 0.5)
            met = g.select(F.col("s").alias("cls")).union(g.select("t")).distinct()
            row = g.agg(F.count("*").alias("edges")).join(F.broadcast(classes.join(met, "cls", "left_anti").agg(F.count("*").alias("isolated"))))  # a row each
            row = row.select(F.lit(eps).alias("eps"), F.lit(edges).alias("summary"), F.lit(k).alias("k"), "edges", "isolated")
            out = row if out is None else out.unionByName(row)
    return out


@query()
def exp_scale(spark: SparkSession, sf: str) -> DataFrame:
    """Points, pairs of points and pairs of classes at a fixed number of classes: what the summary saves (arithmetic only)."""
    n = read_table(spark, sf, "documents", "doc_id").agg(F.count("*").alias("n"))
    k = F.explode(F.array(*map(F.lit, (16, 64, 256)))).alias("k")
    return n.select("n", k).select("n", "k", (F.col("n") * (F.col("n") - 1) / 2).alias("point_pairs"), (F.col("k") * (F.col("k") - 1) / 2).alias("class_pairs"), F.round(F.pow(F.col("n") / F.col("k"), 2), 6).alias("cells"))


ORACLES["exp_scale"] = "SELECT n, k, n * (n - 1) / 2 AS point_pairs, k * (k - 1) / 2 AS class_pairs, round((n / k) ** 2, 6) AS cells FROM (SELECT count(*) AS n FROM documents), (VALUES (16), (64), (256)) t(k)"


def growing_points(spark: SparkSession, n: int, c: int = 4, p: int = 8) -> DataFrame:
    """(vid, x, y): ``n`` points around ``c`` centres, from md5 coins."""
    side = F.col("id") % c
    x = F.array(*[4.0 * (side == i % c).cast("double") + 2 * (G.md5_coin(F.col("id"), F.lit(f"a{i}")) + G.md5_coin(F.col("id"), F.lit(f"b{i}")) - 1) for i in range(p)])
    return spark.range(n).select(F.col("id").alias("vid"), x.alias("x"), side.cast("string").alias("y"))


def fit_growing(spark: SparkSession, sizes: tuple[int, ...], dims: int = 64) -> DataFrame:
    """(n, k, seconds, seconds_graph, accuracy): the whole method at a fixed number of classes as the points grow, on kernel features."""
    rows = []
    for n in sizes:
        v = cut(growing_points(spark, n))
        began = time.monotonic()
        m = fit(v, 4, 0.3, 2, n // 8, sigma=3.0, kernel="features", dims=dims, checker="sigma", pick="max_gap", vote_k=1)
        score = quality(confusion(m.labels, v))["accuracy"]
        rows.append((n, int(m.partition.k), time.monotonic() - began, float(sum(r["seconds"] for r in m.partition.trace)), score))
    return spark.createDataFrame(rows, "n long, k int, seconds double, seconds_graph double, accuracy double")


@query()
def exp_growth(spark: SparkSession, sf: str) -> DataFrame:
    """Time and classes as the points grow fourfold from the number of documents of the table."""
    n = read_table(spark, sf, "documents", "doc_id").count()
    return fit_growing(spark, (n, 4 * n))
