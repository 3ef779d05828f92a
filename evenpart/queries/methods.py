"""Graph construction, partition state, checks, refinement, loops, clustering, baselines and measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpart.functions.blocks import class_sizes, theory
from evenpart.operators import clustering as C
from evenpart.operators import graphs as G
from evenpart.operators import partition as P
from evenpart.plans.scratch import cut
from evenpart.sources.tables import read_table

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


# ---- graphs --------------------------------------------------------------------------------------------------
CP = "cp AS (SELECT DISTINCT o_custkey AS c, l_partkey AS p FROM lineitem JOIN orders ON l_orderkey = o_orderkey), e AS (SELECT a.c AS src, b.c AS dst, count(*) AS w FROM cp a JOIN cp b ON a.p = b.p AND a.c < b.c GROUP BY 1, 2)"
D2 = "list_sum(list_transform(list_zip(a.x, b.x), lambda z: (z[1] - z[2]) * (z[1] - z[2])))"
EV = "v AS (SELECT vec_id AS vid, list_transform(embedding, lambda z: CAST(z AS DOUBLE)) AS x, label AS y FROM embeddings)"


@query(f"WITH {CP} SELECT * FROM e")
def graph_copurchase(spark: SparkSession, sf: str) -> DataFrame:
    return G.copurchase(spark, sf)


@query(f"WITH {CP} SELECT src, dst, round(w / (SELECT max(w) FROM e), 9) AS w FROM e")
def graph_copurchase_scaled(spark: SparkSession, sf: str) -> DataFrame:
    return G.scaled(G.copurchase(spark, sf)).withColumn("w", F.round("w", 9))


@query("WITH h AS (SELECT DISTINCT user_id AS u, date_trunc('hour', ts) AS h FROM events) SELECT a.u AS src, b.u AS dst, count(*) AS w FROM h a JOIN h b ON a.h = b.h AND a.u < b.u GROUP BY 1, 2")
def graph_cohour(spark: SparkSession, sf: str) -> DataFrame:
    return G.co_occurrence(read_table(spark, sf, "events", "user_id", "ts").withColumn("h", F.date_trunc("hour", "ts")), "user_id", "h")


@query("WITH h AS (SELECT DISTINCT l_suppkey AS u, l_partkey AS h FROM lineitem) SELECT a.u AS src, b.u AS dst, count(*) AS w FROM h a JOIN h b ON a.h = b.h AND a.u < b.u GROUP BY 1, 2")
def graph_cosupply(spark: SparkSession, sf: str) -> DataFrame:
    return G.co_occurrence(read_table(spark, sf, "lineitem", "l_suppkey", "l_partkey"), "l_suppkey", "l_partkey")


COIN = "('0x' || substr(md5(a.id || ':' || b.id || ':42'), 1, 8))::BIGINT / 4294967296.0"


@query("SELECT DISTINCT l_suppkey AS src, l_partkey AS dst, 1.0::DOUBLE AS w FROM lineitem WHERE l_suppkey < l_partkey AND ('0x' || substr(md5(l_suppkey || ':' || l_partkey || ':42'), 1, 8))::BIGINT / 4294967296.0 < CASE WHEN l_suppkey % 4 = l_partkey % 4 THEN 0.9 ELSE 0.1 END")
def graph_planted(spark: SparkSession, sf: str) -> DataFrame:
    pairs = read_table(spark, sf, "lineitem", F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst"))
    return G.planted_on(pairs, 4, 0.9, 0.1)


def _folded(spark: SparkSession, sf: str, n: int) -> tuple[DataFrame, DataFrame]:
    """A graph of n vertices folded from all orders: two are joined if at least as many orders meet in them as in a mean pair."""
    ends = read_table(spark, sf, "orders", (F.col("o_custkey") % n).alias("a"), (F.col("o_orderkey") % n).alias("b")).where("a <> b")
    met = ends.groupBy(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).agg(F.count("*").alias("c"))
    edges = met.join(F.broadcast(met.agg(F.avg("c").alias("mean"))), F.col("c") >= F.col("mean"))  # one row
    return spark.range(n).select(F.col("id").alias("vid")), cut(edges.select("src", "dst", F.lit(1.0).alias("w")))


@query(f"WITH {EV} SELECT a.vid AS src, b.vid AS dst, round(exp(-{D2} / 4.0), 6) AS w FROM v a JOIN v b ON a.vid < b.vid")
def affinity_full_emb(spark: SparkSession, sf: str) -> DataFrame:
    return G.affinity_pairs(G.emb_vertices(spark, sf), sigma=2**0.5).withColumn("w", F.round("w", 6))


KNN = f"n AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(dist, 9), vid) AS rank FROM (SELECT a.vid AS qid, b.vid AS vid, sqrt({D2}) AS dist FROM v a JOIN v b ON a.vid <> b.vid))"


@query(f"WITH {EV}, {KNN}, s AS (SELECT qid AS vid, dist AS s FROM n WHERE rank = 7) SELECT a.vid AS src, b.vid AS dst, round(exp(-{D2} / (sa.s * sb.s)), 6) AS w FROM v a JOIN v b ON a.vid < b.vid JOIN s sa ON sa.vid = a.vid JOIN s sb ON sb.vid = b.vid")
def affinity_self_tuned_emb(spark: SparkSession, sf: str) -> DataFrame:
    v = G.emb_vertices(spark, sf)
    return G.affinity_pairs(v, scales=G.local_scales(v)).withColumn("w", F.round("w", 6))


@query(f"WITH {EV} SELECT a.vid AS src, b.vid AS dst, 1.0::DOUBLE AS w FROM v a JOIN v b ON a.vid < b.vid WHERE exp(-{D2} / 4.0) >= 0.65")
def affinity_threshold(spark: SparkSession, sf: str) -> DataFrame:
    return G.binarize(G.affinity_pairs(G.emb_vertices(spark, sf), sigma=2**0.5, least=0.65), 0.65)


def _knn(spark, sf, k):
    v = G.emb_vertices(spark, sf)
    return G.knn(v, v, k)


@query(f"WITH {EV}, {KNN} SELECT qid, vid, round(dist, 6) AS dist, rank FROM n WHERE rank <= 5")
def knn_exact(spark: SparkSession, sf: str) -> DataFrame:
    return _knn(spark, sf, 5).withColumn("dist", F.round("dist", 6))


@query(f"WITH {EV}, {KNN} SELECT qid, vid, rank FROM n WHERE rank <= (SELECT round(ln(count(*))) FROM v)")
def knn_log_n(spark: SparkSession, sf: str) -> DataFrame:
    return _knn(spark, sf, G.log_n(G.emb_vertices(spark, sf).count())).drop("dist")


_SEEN = "SELECT least(qid, vid) AS src, greatest(qid, vid) AS dst, count(*) AS c FROM n WHERE rank <= 5 GROUP BY 1, 2"


@query(f"WITH {EV}, {KNN} SELECT src, dst FROM ({_SEEN})")
def knn_union(spark: SparkSession, sf: str) -> DataFrame:
    return G.knn_edges(_knn(spark, sf, 5), "union").drop("dist")


@query(f"WITH {EV}, {KNN} SELECT src, dst FROM ({_SEEN}) WHERE c = 2")
def knn_mutual(spark: SparkSession, sf: str) -> DataFrame:
    return G.knn_edges(_knn(spark, sf, 5), "mutual").drop("dist")


def _part(spark, sf):
    return read_table(spark, sf, "part").select(F.col("p_partkey").alias("vid"), F.array(F.col("p_size").cast("double"), F.col("p_retailprice").cast("double")).alias("x"))


def _xy(df):
    return df.select("vid", F.round(F.col("x")[0], 6).alias("x0"), F.round(F.col("x")[1], 6).alias("x1"))


PV = "v AS (SELECT p_partkey AS vid, p_size::DOUBLE AS a, p_retailprice::DOUBLE AS b FROM part)"


@query(f"WITH {PV} SELECT vid, round((a - avg(a) OVER ()) / stddev_pop(a) OVER (), 6) AS x0, round((b - avg(b) OVER ()) / stddev_pop(b) OVER (), 6) AS x1 FROM v")
def features_zscore(spark: SparkSession, sf: str) -> DataFrame:
    return _xy(G.standardise(_part(spark, sf), "z"))


@query(f"WITH {PV} SELECT vid, round((a - min(a) OVER ()) / (max(a) OVER () - min(a) OVER ()), 6) AS x0, round((b - min(b) OVER ()) / (max(b) OVER () - min(b) OVER ()), 6) AS x1 FROM v")
def features_minmax(spark: SparkSession, sf: str) -> DataFrame:
    return _xy(G.standardise(_part(spark, sf), "minmax"))


@query(f"WITH {PV} SELECT vid, round(a / sqrt(a * a + b * b), 6) AS x0, round(b / sqrt(a * a + b * b), 6) AS x1 FROM v")
def features_l2(spark: SparkSession, sf: str) -> DataFrame:
    return _xy(G.standardise(_part(spark, sf), "l2"))


@query("SELECT doc_id AS vid, round(ln(greatest(length(text), 1) + 1.0), 6) AS x0, round(len(regexp_extract_all(text, '\\s')) / greatest(length(text), 1), 6) AS x1 FROM documents")
def features_text(spark: SparkSession, sf: str) -> DataFrame:
    return _xy(read_table(spark, sf, "documents", "doc_id", "text").select(F.col("doc_id").alias("vid"), G.text_shape(F.col("text")).alias("x")))


@query()
def affinity_random_features(spark: SparkSession, sf: str) -> DataFrame:
    return G.random_features(G.emb_vertices(spark, sf), 2**0.5, 64)


@query(f"WITH {CP} SELECT a.src, a.dst, a.w / 0.1 AS w FROM e a WHERE ('0x' || substr(md5(a.src || ':' || a.dst || ':42'), 1, 8))::BIGINT / 4294967296.0 < 0.1")
def sample_edges_hash(spark: SparkSession, sf: str) -> DataFrame:
    return G.sample_edges(G.copurchase(spark, sf), 0.1)


# ---- partition state -----------------------------------------------------------------------------------------
K = 6
CV = "v AS (SELECT DISTINCT c AS vid FROM cp)"
AS = f"r AS (SELECT vid, row_number() OVER (ORDER BY md5(vid || ':42'), vid) - 1 AS rank, count(*) OVER () AS n FROM v), g AS (SELECT vid, CASE WHEN rank < {K} * (n // {K}) THEN 1 + rank // (n // {K}) ELSE 0 END::INT AS cls FROM r)"
ST = "sz AS (SELECT cls, count(*) AS n FROM g WHERE cls > 0 GROUP BY 1), ab AS (SELECT least(a.cls, b.cls) AS s, greatest(a.cls, b.cls) AS t, sum(w) AS e, sum(w * w) AS e2 FROM e JOIN g a ON a.vid = src JOIN g b ON b.vid = dst WHERE a.cls > 0 AND b.cls > 0 AND a.cls <> b.cls GROUP BY 1, 2), st AS (SELECT x.cls AS s, y.cls AS t, x.n AS na, y.n AS nb, coalesce(e, 0)::DOUBLE AS e, coalesce(e2, 0)::DOUBLE AS e2, coalesce(e, 0) / (x.n * y.n) AS d FROM sz x JOIN sz y ON x.cls < y.cls LEFT JOIN ab ON ab.s = x.cls AND ab.t = y.cls)"
BASE = f"WITH {CP}, {CV}, {AS}, {ST}"


def _graph(spark, sf):
    e = cut(G.copurchase(spark, sf))  # every query below reads the edges more than once
    v = e.select(F.col("src").alias("vid")).union(e.select("dst")).distinct()
    return e, v, cut(P.initial_partition(v, K))


@query(f"WITH {CP}, {CV}, {AS} SELECT vid, cls FROM g")
def part_initial_hash(spark: SparkSession, sf: str) -> DataFrame:
    return _graph(spark, sf)[2]


@query(f"WITH v AS (SELECT c_custkey AS vid FROM customer), {AS.replace(chr(109) + 'd5(vid || ' + chr(39) + ':42' + chr(39) + '), vid', 'vid')} SELECT vid, cls FROM g")
def part_initial_vid(spark: SparkSession, sf: str) -> DataFrame:
    return P.initial_partition(read_table(spark, sf, "customer").select(F.col("c_custkey").alias("vid")), K, order="vid")


@query(f"{BASE} SELECT s, t, na, nb, e, e2, round(d, 9) AS d FROM st")
def dens_pairs(spark: SparkSession, sf: str) -> DataFrame:
    e, _, a = _graph(spark, sf)
    return P.pair_density(e, a).withColumn("d", F.round("d", 9))


@query(f"{BASE} SELECT cls, n, coalesce(e, 0)::DOUBLE AS e, round(2 * coalesce(e, 0) / (n * (n - 1)), 9) AS d FROM sz LEFT JOIN (SELECT a.cls AS c, sum(w) AS e FROM e JOIN g a ON a.vid = src JOIN g b ON b.vid = dst WHERE a.cls = b.cls GROUP BY 1) ON c = cls")
def dens_self(spark: SparkSession, sf: str) -> DataFrame:
    e, _, a = _graph(spark, sf)
    return P.self_density(e, a).withColumn("d", F.round("d", 9))


@query(f"{BASE}, x AS (SELECT vid FROM g WHERE cls = 1 AND vid % 2 = 0), y AS (SELECT vid FROM g WHERE cls = 2 AND vid % 2 = 0), z AS (SELECT coalesce(sum(w), 0)::DOUBLE AS e FROM (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e) WHERE src IN (SELECT vid FROM x) AND dst IN (SELECT vid FROM y)) SELECT (SELECT count(*) FROM x) AS na, (SELECT count(*) FROM y) AS nb, e, round(e / greatest((SELECT count(*) FROM x) * (SELECT count(*) FROM y), 1), 9) AS d FROM z")
def dens_rect(spark: SparkSession, sf: str) -> DataFrame:
    e, _, a = _graph(spark, sf)
    return P.rect_density(e, a.where("cls = 1 AND vid % 2 = 0"), a.where("cls = 2 AND vid % 2 = 0")).withColumn("d", F.round("d", 9))


@query(f"{BASE} SELECT round(sum(d * d) / {K * K}, 6) AS energy, round(sum(d * d) / {K * (K - 1) // 2}, 6) AS energy_norm FROM st")
def energy_initial(spark: SparkSession, sf: str) -> DataFrame:
    e, _, a = _graph(spark, sf)
    return P.energy(P.pair_density(e, a), K).select(F.round("energy", 6).alias("energy"), F.round("energy_norm", 6).alias("energy_norm"))


@query(f"{BASE} SELECT count(*) FILTER (cls > 0) AS k, min(n) FILTER (cls > 0) AS least, max(n) FILTER (cls > 0) AS most, coalesce(sum(n) FILTER (cls = 0), 0)::BIGINT AS residue, sum(n)::BIGINT AS n, min(n) FILTER (cls > 0) = max(n) FILTER (cls > 0) AS equal, coalesce(sum(n) FILTER (cls = 0), 0) < 0.3 * sum(n) AS small_residue FROM (SELECT cls, count(*) AS n FROM g GROUP BY 1)")
def check_equitable(spark: SparkSession, sf: str) -> DataFrame:
    return P.check_equitable(_graph(spark, sf)[2], 0.3)


@query(f"{BASE} SELECT s, t, round(sqrt(greatest(e2 - na * nb * d * d, 0)), 6) AS norm, round(0.027 * sqrt(na * nb), 6) AS edge, sqrt(greatest(e2 - na * nb * d * d, 0)) < 0.027 * sqrt(na * nb) AS settled FROM st")
def check_frobenius_screen(spark: SparkSession, sf: str) -> DataFrame:
    e, _, a = _graph(spark, sf)
    return P.frobenius_screen(P.pair_density(e, a), 0.3).select("s", "t", F.round("norm", 6).alias("norm"), F.round("edge", 6).alias("edge"), "settled")


@query(f"{BASE}, i AS (SELECT cls AS c, sum(w)::DOUBLE AS e FROM e JOIN g a ON a.vid = src JOIN (SELECT vid, cls AS cb FROM g) b ON b.vid = dst WHERE cls = cb AND cls > 0 GROUP BY 1) SELECT round(((SELECT sum(2 * na * nb * d * d) FROM st) + (SELECT sum(4 * e * e / (n * n)) FROM sz JOIN i ON c = cls)) / (SELECT sum(n) * sum(n) FROM sz), 6)::DOUBLE AS energy_mass FROM (SELECT 1)")
def energy_mass(spark: SparkSession, sf: str) -> DataFrame:
    e, _, a = _graph(spark, sf)
    return P.energy_mass(e, a).select(F.round("energy_mass", 6).alias("energy_mass"))


EPS4 = 0.3**4
DEG = f"bth AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e), dg AS (SELECT o.s, y.cls AS t, y.vid, coalesce(c, 0) AS deg FROM g y JOIN (SELECT DISTINCT cls AS s FROM g WHERE cls > 0) o ON o.s < y.cls LEFT JOIN (SELECT b.src AS vid, x.cls AS s, count(*) AS c FROM bth b JOIN g x ON x.vid = b.dst GROUP BY 1, 2) q ON q.vid = y.vid AND q.s = o.s), mn AS (SELECT s, t, avg(deg) AS mean_deg, count(*) AS m FROM dg GROUP BY 1, 2), vd AS (SELECT s, t, m, mean_deg, count(*) FILTER (deg - mean_deg >= {EPS4!r} * m) AS n_high, count(*) FILTER (deg - mean_deg <= -{EPS4!r} * m) AS n_low FROM dg JOIN mn USING (s, t) GROUP BY 1, 2, 3, 4), ver AS (SELECT *, CASE WHEN mean_deg >= {0.3**3!r} * m AND n_high + n_low >= {EPS4 / 8!r} * m THEN 'WITNESS' ELSE 'UNIFORM' END AS status FROM vd)"


@query(f"{BASE}, {DEG} SELECT s, t, m, round(mean_deg, 6) AS mean_deg, n_high, n_low, status FROM ver")
def check_degree_deviants(spark: SparkSession, sf: str) -> DataFrame:
    e, _, a = _graph(spark, sf)
    return P.check_degree(e.withColumn("w", F.lit(1.0)), a, 0.3)[0].withColumn("mean_deg", F.round("mean_deg", 6))


@query(f"{BASE}, {DEG} SELECT s, t, vid FROM dg JOIN ver USING (s, t) WHERE status = 'WITNESS' AND CASE WHEN n_high >= n_low THEN deg - ver.mean_deg >= {EPS4!r} * m ELSE deg - ver.mean_deg <= -{EPS4!r} * m END")
def check_degree_witness(spark: SparkSession, sf: str) -> DataFrame:
    e, _, a = _graph(spark, sf)
    return P.check_degree(e.withColumn("w", F.lit(1.0)), a, 0.3)[1]


@query(f"{BASE}, {DEG} SELECT (SELECT count(*) FROM sz) AS k, (SELECT count(*) FROM g WHERE cls = 0) AS residue, (SELECT count(*) FROM ver WHERE status <> 'UNIFORM') AS bad, (SELECT count(*) FROM g WHERE cls = 0) < 0.3 * (SELECT count(*) FROM g) AND (SELECT count(*) FROM ver WHERE status <> 'UNIFORM') <= 0.3 * {K * K} AS uniform")
def check_partition_uniform(spark: SparkSession, sf: str) -> DataFrame:
    e, _, a = _graph(spark, sf)
    return P.partition_is_uniform(a, P.check_degree(e.withColumn("w", F.lit(1.0)), a, 0.3)[0], 0.3)


def _verdicts(checker, **options):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        e, _, a = _graph(spark, sf)
        return P.check_pairs(a, 0.3, checker, G.binarize(e, 1), **options).where("status is not null").drop("side", "vid")

    return run


for _n, _f in {
    "check_codegree_verdicts": _verdicts("codegree"), "check_codegree_lemma_order": _verdicts("codegree", policy="lemma_order", anchors="typical"),
    "check_sigma_verdicts": _verdicts("sigma"), "check_sigma_noise_adjusted": _verdicts("sigma", noise_adjust=True),
    "check_codegree_sampled": _verdicts("codegree", anchors=64), "check_sigma_power": _verdicts("power", sweeps=8),
}.items():
    query(name=_n)(_f)


@query()
def check_exhaustive_small(spark: SparkSession, sf: str) -> DataFrame:
    v, e = _folded(spark, sf, 16)
    return P.check_pairs(P.initial_partition(v, 2), 0.3, "exhaustive", e).where("status is not null").drop("side", "vid")


@query()
def probe_density_gap(spark: SparkSession, sf: str) -> DataFrame:
    e, _, a = _graph(spark, sf)
    return spark.createDataFrame([(1, 2, P.probe_gap(G.binarize(e, 1), a, 1, 2, trials=5))], "s int, t int, gap double")


@query("SELECT eps, round(eps ** 4 / 16, 12) AS gamma_a, round(eps ** 9 / 108, 12) AS gamma_b, round(eps ** 4, 12) AS witness_gap FROM (SELECT DISTINCT l_quantity / 100 AS eps FROM lineitem WHERE l_quantity > 0)")
def theory_table(spark: SparkSession, sf: str) -> DataFrame:
    """The constants at every quantity of an item taken as percent."""
    held = read_table(spark, sf, "lineitem", (F.col("l_quantity") / 100).alias("eps")).where("eps > 0").distinct().collect()  # 50 quantities at any scale
    rows = [(e, t["gamma_a"], t["gamma_b"], t["witness_gap"]) for e, t in ((r.eps, theory(r.eps, 2, 100)) for r in held)]
    return spark.createDataFrame([(e, *[round(x, 12) for x in more]) for e, *more in rows], "eps double, gamma_a double, gamma_b double, witness_gap double")


@query("WITH RECURSIVE n AS (SELECT count(DISTINCT o_custkey) AS n FROM orders), r(fanout, k, m, residue) AS (SELECT l, l, n // l, n - l * (n // l) FROM n, range(2, 8) t(l) UNION ALL SELECT fanout, k * fanout, m // fanout, n - k * fanout * (m // fanout) FROM r, n WHERE m >= 50) SELECT fanout, k, m, residue FROM r")
def loop_sizes(spark: SparkSession, sf: str) -> DataFrame:
    """Classes of every round over the customers that order."""
    n = read_table(spark, sf, "orders", "o_custkey").agg(F.countDistinct("o_custkey")).first()[0]
    return spark.createDataFrame([(f, *row) for f in range(2, 8) for row in class_sizes(n, f, 50)], "fanout long, k long, m long, residue long")


# ---- refinement from degree witnesses, exact in SQL ------------------------------------------------------------
PK = f"{BASE}, {DEG}, wit AS (SELECT s, t, vid FROM dg JOIN ver USING (s, t) WHERE status = 'WITNESS' AND CASE WHEN n_high >= n_low THEN deg - ver.mean_deg >= {EPS4!r} * m ELSE deg - ver.mean_deg <= -{EPS4!r} * m END), pick AS (SELECT t AS cls, min(s) AS other FROM ver WHERE status = 'WITNESS' GROUP BY 1), cel AS (SELECT g.vid, g.cls, (w.vid IS NOT NULL)::INT AS cell, md5(g.vid || ':42') AS key FROM g LEFT JOIN pick p ON p.cls = g.cls LEFT JOIN wit w ON w.vid = g.vid AND w.t = p.cls AND w.s = p.other WHERE g.cls > 0), mm AS (SELECT max(n) // 2 AS m FROM sz), ck AS (SELECT *, (row_number() OVER (PARTITION BY cls, cell ORDER BY key, vid) - 1) // (SELECT m FROM mm) AS chunk, count(*) OVER (PARTITION BY cls, cell) // (SELECT m FROM mm) AS chunks FROM cel), lf AS (SELECT vid, cls, key, row_number() OVER (PARTITION BY cls ORDER BY key, vid) AS r, count(*) OVER (PARTITION BY cls) AS n FROM ck WHERE chunk >= chunks)"
DONE = "d1 AS (SELECT vid, cls, 1 - cell AS cell, chunk FROM ck WHERE chunk < chunks)"
POOL = "d2 AS (SELECT * FROM d1 UNION ALL SELECT vid, cls, 2, 0 FROM lf WHERE n >= (SELECT m FROM mm) AND r <= (SELECT m FROM mm))"
REST = "rs AS (SELECT vid, row_number() OVER (ORDER BY md5(vid || ':42'), vid) - 1 AS r, count(*) OVER () AS n FROM v WHERE vid NOT IN (SELECT vid FROM d2)), d3 AS (SELECT * FROM d2 UNION ALL SELECT vid, 1073741824, 3, r // (SELECT m FROM mm) FROM rs WHERE r < n // (SELECT m FROM mm) * (SELECT m FROM mm))"


def _named(d):
    return f"nm AS (SELECT vid, dense_rank() OVER (ORDER BY cls, cell, chunk)::INT AS new FROM {d}) SELECT v.vid, coalesce(new, 0) AS cls FROM v LEFT JOIN nm ON nm.vid = v.vid"


def _refined(spark, sf, recycle):
    e, _, a = _graph(spark, sf)
    verdict, witness = P.check_degree(e.withColumn("w", F.lit(1.0)), a, 0.3)
    pick = verdict.where("status = 'WITNESS'").groupBy(F.col("t").alias("cls")).agg(F.min("s").alias("s"))
    cells = witness.withColumnRenamed("t", "cls").join(pick, ["cls", "s"], "left_semi").select("cls", "vid")
    return P.refine(a, cells, 2, recycle)


@query(f"{PK}, {DONE}, {POOL}, {_named('d2')}")
def refine_modified(spark: SparkSession, sf: str) -> DataFrame:
    return _refined(spark, sf, "class")


@query(f"{PK}, {DONE}, {_named('d1')}")
def refine_recycle_none(spark: SparkSession, sf: str) -> DataFrame:
    return _refined(spark, sf, "none")


@query(f"{PK}, {DONE}, {POOL}, {REST}, {_named('d3')}")
def refine_recycle_global(spark: SparkSession, sf: str) -> DataFrame:
    return _refined(spark, sf, "global")


@query()
def refine_full_toy(spark: SparkSession, sf: str) -> DataFrame:
    v, e = _folded(spark, sf, 64)
    a = P.initial_partition(v, 2)
    return P.refine_full(a, P.check_pairs(a, 0.3, "codegree", e).where("vid is not null"))


# ---- loops and clustering --------------------------------------------------------------------------------------
TRACE = "iter int, k int, m int, energy double, energy_norm double, pairs int, bad int, required int, stop string"


def _trace(spark, part):
    return spark.createDataFrame([tuple(r[c.split(" ")[0]] for c in TRACE.split(", ")) for r in part.trace], TRACE)


def _loop(spark, sf, **options):
    v = G.doc_vertices(spark, sf)
    return _trace(spark, P.practical_loop(v, 0.3, 3, 30, sigma=C.median_scale(v), **options))


query(name="loop_a")(lambda spark, sf: _loop(spark, sf, checker="codegree"))
query(name="loop_b")(lambda spark, sf: _loop(spark, sf, checker="sigma"))
query(name="loop_cost")(lambda spark, sf: C.cost(P.practical_loop(v := G.doc_vertices(spark, sf), 0.3, 3, 30, sigma=C.median_scale(v))))
query(name="loop_stop_k_squared")(lambda spark, sf: _loop(spark, sf, checker="sigma", stop_rule="k_squared"))


@query()
def loop_b_power(spark: SparkSession, sf: str) -> DataFrame:
    """The spectral-norm loop on edges by power sweeps: no dense blocks."""
    e, v, _ = _graph(spark, sf)
    return _trace(spark, P.practical_loop(v, 0.3, 2, 40, "power", G.binarize(e, 1)))


@query()
def loop_full_toy(spark: SparkSession, sf: str) -> DataFrame:
    v, e = _folded(spark, sf, 64)
    return spark.createDataFrame([(r["iter"], r["k"], r["bad"]) for r in P.full_loop(v, 0.5, 2, "sigma", e).trace], "iter int, k int, bad int")


@query()
def energy_trace(spark: SparkSession, sf: str) -> DataFrame:
    from pyspark.sql import Window

    t = _loop(spark, sf, checker="codegree")
    return t.select("iter", "k", "energy", "energy_norm", (F.col("energy") - F.lag("energy").over(Window.orderBy("iter"))).alias("gain"))


SCORES = "accuracy double, majority double, purity double, clusters double, nmi double, ari double"


def _scored(spark, labels, truth, **more):
    q = C.quality(C.confusion(labels, truth))
    return spark.createDataFrame([(*[q[c.split(" ")[0]] for c in SCORES.split(", ")], *more.values())], ", ".join([SCORES, *[f"{k} {'string' if isinstance(x, str) else 'double'}" for k, x in more.items()]]))


def _fit_docs(spark, sf, checker):
    v = G.doc_vertices(spark, sf).cache()
    m = C.fit(v, 4, 0.3, 4, 12, checker=checker, sigma=C.median_scale(v) / 2, pick="max_gap", keep="last_valid")
    return _scored(spark, m.labels, v, classes=float(m.partition.k), compression=C.compression(v.count(), m.partition.k)["size"])


query(name="cluster_documents_a")(lambda spark, sf: _fit_docs(spark, sf, "codegree"))
query(name="cluster_documents_b")(lambda spark, sf: _fit_docs(spark, sf, "sigma"))


@query()
def cluster_embeddings_a(spark: SparkSession, sf: str) -> DataFrame:
    v = G.emb_vertices(spark, sf).cache()
    return _scored(spark, C.fit(v, 10, 0.3, 4, 10).labels, v)


@query()
def cluster_copurchase_a(spark: SparkSession, sf: str) -> DataFrame:
    e, v, _ = _graph(spark, sf)
    return C.fit(v, 3, 0.3, 4, 40, edges=G.binarize(e, 1).cache()).labels


@query()
def predict_benchmark(spark: SparkSession, sf: str) -> DataFrame:
    docs = read_table(spark, sf, "documents", "doc_id", "text").select(F.col("doc_id").alias("vid"), G.text_shape(F.col("text")).alias("x"))
    new = read_table(spark, sf, "benchmark").select((F.col("item_id") + 10**12).alias("vid"), G.text_shape(F.col("text")).alias("x"))
    both = G.standardise(docs.union(new)).cache()
    return C.fit(both.where("vid < 1000000000000"), 4, 0.3, 4, 20).predict(both.where("vid >= 1000000000000"))


def _baseline(make):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        v = G.doc_vertices(spark, sf).cache()
        return _scored(spark, make(v), v)

    return run


def _knn_graph(v, self_tuned=False):
    near = G.knn(v, v, G.log_n(v.count()))
    e = G.knn_edges(near)
    if not self_tuned:
        s = C.median_scale(v)
        return e.select("src", "dst", F.exp(-F.col("dist") ** 2 / (2 * s * s)).alias("w"))
    s = G.local_scales(v)
    return e.join(s.select(F.col("vid").alias("src"), F.col("s").alias("a")), "src").join(s.select(F.col("vid").alias("dst"), F.col("s").alias("b")), "dst").select("src", "dst", F.exp(-F.col("dist") ** 2 / F.greatest(F.col("a") * F.col("b"), F.lit(G.LEAST_SCALE))).alias("w"))


def _random(v):
    return C.fit(v, 4, 0.3, 4, partition=C.random_partition(v, 64)).labels


for _n, _f in {
    "base_kmeans_ml": lambda v: C.kmeans(v, 4), "base_gmm": lambda v: C.gmm(v, 4), "base_kmeans_lloyd": lambda v: C.lloyd(v, 4), "base_landmark": lambda v: C.landmark(v, 4),
    "base_spectral_full": lambda v: C.spectral_kernel(v, 4, C.median_scale(v)), "base_spectral_knn": lambda v: C.spectral(_knn_graph(v), v, 4),
    "base_spectral_knn_self_tuned": lambda v: C.spectral(_knn_graph(v, True), v, 4), "base_spectral_self_tuned": lambda v: C.spectral_kernel(v, 4, scales=G.local_scales(v)),
    "base_random_partition": _random, "base_pic": lambda v: C.power_iteration(_knn_graph(v), 4), "base_dominant_sets": lambda v: C.fit(v, 4, 0.3, 4, 20, method="dominant").labels,
    "base_centroids_spectral": lambda v: C.spectral_on_centroids(v, 4, 64),
}.items():
    query(name=_n)(_baseline(_f))


@query("SELECT round(100.0 * max(n) / sum(n), 6)::DOUBLE AS rate, count(*) AS classes, sum(n)::BIGINT AS n FROM (SELECT count(*) AS n FROM documents GROUP BY lang)")
def base_majority(spark: SparkSession, sf: str) -> DataFrame:
    return C.majority_rate(read_table(spark, sf, "documents", "lang").withColumnRenamed("lang", "y")).withColumn("rate", F.round("rate", 6))


# ---- measures on an assignment known to SQL: three clusters by source ------------------------------------------
LAB = "l AS (SELECT doc_id % 3 AS cluster, lang AS y FROM documents), c AS (SELECT cluster, y, count(*) AS n FROM l GROUP BY 1, 2)"


def _labels(spark, sf):
    d = read_table(spark, sf, "documents", "doc_id", "lang")
    return d.select(F.col("doc_id").alias("vid"), (F.col("doc_id") % 3).alias("cluster")), d.select(F.col("doc_id").alias("vid"), F.col("lang").alias("y"))


@query(f"WITH {LAB} SELECT * FROM c")
def eval_confusion(spark: SparkSession, sf: str) -> DataFrame:
    return C.confusion(*_labels(spark, sf))


_ACC = "SELECT max(a.n + b.n + d.n) FROM c a, c b, c d WHERE a.cluster = 0 AND b.cluster = 1 AND d.cluster = 2 AND a.y <> b.y AND a.y <> d.y AND b.y <> d.y"


@query(f"WITH {LAB}, t AS (SELECT sum(n) AS n FROM c), h AS (SELECT (SELECT -sum(p * ln(p)) FROM (SELECT sum(n) / (SELECT n FROM t) AS p FROM c GROUP BY cluster)) AS hr, (SELECT -sum(p * ln(p)) FROM (SELECT sum(n) / (SELECT n FROM t) AS p FROM c GROUP BY y)) AS hc, (SELECT -sum(p * ln(p)) FROM (SELECT n / (SELECT n FROM t) AS p FROM c)) AS hj), i AS (SELECT (SELECT sum(n * (n - 1) / 2) FROM c) AS x, (SELECT sum(n * (n - 1) / 2) FROM (SELECT sum(n) AS n FROM c GROUP BY cluster)) AS a, (SELECT sum(n * (n - 1) / 2) FROM (SELECT sum(n) AS n FROM c GROUP BY y)) AS b, (SELECT n * (n - 1) / 2 FROM t) AS m) SELECT round(100.0 * ({_ACC}) / (SELECT n FROM t), 6)::DOUBLE AS accuracy, round(100.0 * (SELECT sum(m) FROM (SELECT max(n) AS m FROM c GROUP BY cluster)) / (SELECT n FROM t), 6)::DOUBLE AS purity, round((hr + hc - hj) / sqrt(hr * hc), 6) AS nmi, round((x - a * b / m) / ((a + b) / 2 - a * b / m), 6) AS ari FROM h, i")
def eval_scores(spark: SparkSession, sf: str) -> DataFrame:
    return _scored(spark, *_labels(spark, sf)).select(*[F.round(c, 6).alias(c) for c in ("accuracy", "purity", "nmi", "ari")])
