"""Steps of the method whose rows SQL can state in full: anchors' sets, picks, summaries, lifting, votes, traces, Lloyd."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpart.operators import clustering as C
from evenpart.operators import graphs as G
from evenpart.operators import large
from evenpart.operators import partition as P
from evenpart.plans.scratch import cut
from evenpart.queries import methods as M
from evenpart.queries.registry import registry
from evenpart.sources.tables import read_table

QUERIES, ORACLES, query = registry()

ONES = M.BASE.replace("sum(w)", "count(*)").replace("sum(w * w)", "count(*)")
ANCHORS = 8
BAR = f"2 * {M.EPS4!r} * na + d * d * na"


def _ones(spark, sf):
    e, v, a = M._graph(spark, sf)
    return e.withColumn("w", F.lit(1.0)), v, a


def _common(select: str) -> str:
    """Codegrees of the anchors of both classes of every pair, and what is read from them."""
    return f"""{ONES}, x AS (SELECT least(a.cls, b.cls) AS s, greatest(a.cls, b.cls) AS t, a.cls AS side, e.src AS vid, e.dst AS near FROM (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e) e JOIN g a ON a.vid = e.src JOIN g b ON b.vid = e.dst WHERE a.cls > 0 AND b.cls > 0 AND a.cls <> b.cls),
an AS (SELECT cls AS side, vid AS y FROM (SELECT *, row_number() OVER (PARTITION BY cls ORDER BY ('0x' || substr(md5(vid || ':anchor:42'), 1, 8))::BIGINT / 4294967296.0, vid) AS r FROM g WHERE cls > 0) WHERE r <= {ANCHORS}),
n AS (SELECT p.s, p.t, p.side, p.vid AS y, q.vid, count(*) AS n FROM x p JOIN an ON an.side = p.side AND an.y = p.vid JOIN x q ON q.s = p.s AND q.t = p.t AND q.side = p.side AND q.near = p.near AND q.vid <> p.vid GROUP BY ALL), {select}"""


@query(_common(f"b AS (SELECT s, t, side, y, count(*) AS size_b, sum(n)::DOUBLE AS inn FROM n JOIN st USING (s, t) WHERE d >= {0.3**3!r} AND n >= {BAR} GROUP BY ALL), h AS (SELECT s, t, side, vid AS y, count(*) AS size_a FROM x JOIN st USING (s, t) WHERE d < 1 GROUP BY ALL) SELECT s, t, side, y, size_a, size_b, inn AS inner_weight FROM b JOIN h USING (s, t, side, y)"))
def check_codegree_anchor_sets(spark: SparkSession, sf: str) -> DataFrame:
    """Sizes of the neighbourhood and of the codegree set of sampled anchors, and the weight between them, by joins over edges."""
    e, _, a = _ones(spark, sf)
    placed = a.where("cls > 0")
    source = large.Edges(placed, e)
    m = F.col("na").cast("double")
    stats = large.pair_stats(source, placed).where(F.col("d") >= 0.3**3).withColumn("bar", F.lit(2 * M.EPS4) * m + F.col("d") * F.col("d") * m)
    return source.anchor_sums(large.choose_anchors(placed, ANCHORS), stats, 0.3).withColumnRenamed("inner", "inner_weight")


@query(_common("c AS (SELECT s, t, side, y, count(*) AS met, sum(n)::BIGINT AS common, max(n) AS most FROM n GROUP BY ALL) SELECT * FROM c"))
def check_codegree_counts(spark: SparkSession, sf: str) -> DataFrame:
    e, _, a = _ones(spark, sf)
    placed = a.where("cls > 0")
    source = large.Edges(placed, e)
    stats = large.pair_stats(source, placed)
    asked = large.directed(stats).join(stats, ["s", "t"]).join(large.choose_anchors(placed, ANCHORS).withColumnRenamed("cls", "side"), "side").select("s", "t", "side", "y", "d")
    return source._common(cut(asked)).groupBy("s", "t", "side", "y").agg(F.count("*").alias("met"), F.sum("n").cast("long").alias("common"), F.max("n").cast("long").alias("most"))


# ---- picks, summary, lift, votes ---------------------------------------------------------------------------------
EACH = f"{M.BASE}, {M.DEG}, bd AS (SELECT s AS cls, t AS other, (n_high + n_low) / m / 10.0 AS gap FROM ver WHERE status = 'WITNESS' UNION ALL SELECT t, s, (n_high + n_low) / m / 10.0 FROM ver WHERE status = 'WITNESS')"
_ORDER = {"random": "md5(cls || ':' || other || ':42'), other", "first": "other", "max_gap": "round((2.0 - gap) * 1e12), other"}


def _degree_verdict(spark, sf):
    e, _, a = _ones(spark, sf)
    return P.check_degree(e, a, 0.3)[0].withColumn("gap", (F.col("n_high") + F.col("n_low")) / F.col("m") / 10.0), a, e


for _pick, _by in _ORDER.items():
    query(f"{EACH} SELECT cls, other FROM (SELECT *, row_number() OVER (PARTITION BY cls ORDER BY {_by}) AS r FROM bd) WHERE r = 1", name=f"refine_pick_{_pick}")(lambda spark, sf, pick=_pick: P.pick_partner(_degree_verdict(spark, sf)[0], pick))


def _summary(edges: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        verdict, a, e = _degree_verdict(spark, sf)
        both = verdict.select("s", "t", "status").join(P.pair_density(e, a).select("s", "t", "d"), ["s", "t"])
        return C.summary_graph(both, edges, 0.4).withColumn("w", F.round("w", 9))

    return run


_SUM = f"{ONES}, {M.DEG} SELECT s, t, round(d, 9) AS w, status = 'UNIFORM' AS uniform FROM st JOIN ver USING (s, t)"
query(_SUM, name="summary_all")(_summary("all"))
query(f"{_SUM} WHERE status = 'UNIFORM' AND d > 0.4", name="summary_uniform_only")(_summary("uniform"))


@query(f"WITH {M.CP}, {M.CV}, {M.AS} SELECT vid, cls, CASE WHEN cls > 0 THEN (2 * cls) % 3 END AS cluster FROM g")
def lift_labels(spark: SparkSession, sf: str) -> DataFrame:
    return C.lift(M._graph(spark, sf)[2], [(2 * c) % 3 for c in range(1, M.K + 1)])


@query(f"WITH {M.EV}, {M.KNN.replace('FROM v a JOIN v b ON a.vid <> b.vid', 'FROM v a JOIN v b ON a.vid % 10 = 0 AND b.vid % 10 <> 0')}, c AS (SELECT qid, v.y AS cluster, count(*) AS k, avg(dist) AS mean FROM n JOIN v ON v.vid = n.vid WHERE rank <= 5 GROUP BY ALL) SELECT qid AS vid, cluster FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY k DESC, round(mean, 9), cluster) AS r FROM c) WHERE r = 1")
def residue_vote(spark: SparkSession, sf: str) -> DataFrame:
    v = G.emb_vertices(spark, sf).select("vid", "x", F.col("y").cast("long").alias("cluster"))
    return C.vote(v.where("vid % 10 = 0"), v.where("vid % 10 <> 0"))


@query(f"WITH {M.CP}, {M.CV}, {M.AS}, b AS (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e), s AS (SELECT q.vid, l.cls AS cluster, sum(w) AS w FROM g q JOIN b ON b.src = q.vid JOIN g l ON l.vid = b.dst WHERE q.cls = 1 AND l.cls > 1 GROUP BY ALL), top AS (SELECT vid, cluster FROM (SELECT *, row_number() OVER (PARTITION BY vid ORDER BY w DESC, cluster) AS r FROM s) WHERE r = 1) SELECT q.vid, coalesce(top.cluster, 2) AS cluster FROM g q LEFT JOIN top USING (vid) WHERE q.cls = 1")
def residue_edge_vote(spark: SparkSession, sf: str) -> DataFrame:
    e, _, a = M._graph(spark, sf)
    return C.edge_vote(a.where("cls = 1"), a.where("cls > 1").select("vid", F.col("cls").alias("cluster")), e)


# ---- traces, baselines, measures ---------------------------------------------------------------------------------


def _state(g: str, n: str) -> str:
    """Pair densities of the assignment ``g`` under names that end in ``n``."""
    return f"z{n} AS (SELECT cls, count(*) AS n FROM {g} WHERE cls > 0 GROUP BY 1), q{n} AS (SELECT least(a.cls, b.cls) AS s, greatest(a.cls, b.cls) AS t, count(*) AS e FROM e JOIN {g} a ON a.vid = src JOIN {g} b ON b.vid = dst WHERE a.cls > 0 AND b.cls > 0 AND a.cls <> b.cls GROUP BY 1, 2), u{n} AS (SELECT coalesce(e, 0) / (x.n * y.n) AS d, (SELECT count(*) FROM z{n}) AS k FROM z{n} x JOIN z{n} y ON x.cls < y.cls LEFT JOIN q{n} ON q{n}.s = x.cls AND q{n}.t = y.cls)"


_NAMED = M._named("d2").replace(") SELECT v.vid", "), g2 AS (SELECT v.vid", 1) + ")"


@query(f"{M.PK}, {M.DONE}, {M.POOL}, {_NAMED}, {_state('g', '1')}, {_state('g2', '2')} SELECT 1 AS iter, max(k) AS k, round(sum(d * d) / (max(k) * max(k)), 6) AS energy FROM u1 UNION ALL SELECT 2, max(k), round(sum(d * d) / (max(k) * max(k)), 6) FROM u2")
def energy_trace_degree(spark: SparkSession, sf: str) -> DataFrame:
    """Classes and energy before and after one modified refinement from degree witnesses."""
    e, _, a = _ones(spark, sf)
    out = None
    for i, assign in enumerate((a, M._refined(spark, sf, "class")), 1):
        k = assign.agg(F.max("cls")).first()[0]
        row = P.energy(P.pair_density(e, assign), k).select(F.lit(i).alias("iter"), F.lit(k).cast("long").alias("k"), F.round("energy", 6).alias("energy"))
        out = row if out is None else out.union(row)
    return out


def _lloyd_sql(c: int, steps: int) -> str:
    parts = [f"WITH {M.PV}, c0 AS (SELECT row_number() OVER (ORDER BY vid) - 1 AS j, a, b FROM (SELECT * FROM v ORDER BY vid LIMIT {c}))"]
    for i in range(steps + 1):
        parts.append(f"p{i} AS (SELECT vid, v.a, v.b, j FROM (SELECT v.*, c.j, row_number() OVER (PARTITION BY vid ORDER BY round((v.a - c.a) ** 2 + (v.b - c.b) ** 2, 9), c.j) AS r FROM v CROSS JOIN c{i} c) v WHERE r = 1)")
        parts.append(f"c{i + 1} AS (SELECT c.j, coalesce(m.a, c.a) AS a, coalesce(m.b, c.b) AS b FROM c{i} c LEFT JOIN (SELECT j, avg(a) AS a, avg(b) AS b FROM p{i} GROUP BY 1) m USING (j))")
    return ", ".join(parts) + f" SELECT vid, j AS cluster FROM p{steps}"


query(_lloyd_sql(3, 3), name="base_lloyd_parts")(lambda spark, sf: C.lloyd(M._part(spark, sf), 3, 3))
query("SELECT doc_id AS vid, floor(('0x' || substr(md5(doc_id || ':42'), 1, 8))::BIGINT / 4294967296.0 * 4)::INT AS cluster FROM documents", name="base_random_labels")(
    lambda spark, sf: C.random_labels(read_table(spark, sf, "documents", "doc_id").withColumnRenamed("doc_id", "vid"), 4)
)


@query(f"WITH {M.CP}, {M.CV} SELECT count(*) || '-{M.K}' AS size, count(*) / {M.K}.0::DOUBLE AS ratio, (count(*) / {M.K}.0::DOUBLE) ** 2 AS cells FROM v")
def eval_compression(spark: SparkSession, sf: str) -> DataFrame:
    a = M._graph(spark, sf)[2]
    got = C.compression(a.count(), a.agg(F.max("cls")).first()[0])
    return spark.createDataFrame([tuple(got.values())], "size string, ratio double, cells double")


@query(f"{EACH} SELECT count(*) AS pairs, count(*) FILTER (status <> 'UNIFORM') AS bad, ceil(count(*) * 0.7)::BIGINT AS required, count(*) FILTER (status = 'UNIFORM') AS present, count(*) FILTER (status <> 'UNIFORM') <= 0.3 * count(*) AS halts FROM ver")
def eval_stop_report(spark: SparkSession, sf: str) -> DataFrame:
    """Uniform pairs required by the pair-fraction rule at eps 0.3, present, and whether the loop would halt."""
    count = lambda c: F.count(F.when(c, 1))
    even = F.col("status") == "UNIFORM"
    got = _degree_verdict(spark, sf)[0].agg(F.count("*").alias("pairs"), count(~even).alias("bad"), F.ceil(F.count("*") * 0.7).alias("required"), count(even).alias("present"))
    return got.withColumn("halts", F.col("bad") <= 0.3 * F.col("pairs"))


# ---- relational forms --------------------------------------------------------------------------------------------


@query("SELECT a.toxic, count(*) AS n FROM labels a JOIN (SELECT DISTINCT toxic FROM labels) b ON a.toxic IS NOT DISTINCT FROM b.toxic GROUP BY 1")
def join_null_safe(spark: SparkSession, sf: str) -> DataFrame:
    a = read_table(spark, sf, "labels", "toxic")
    b = a.distinct().withColumnRenamed("toxic", "b")
    return a.join(b, a["toxic"].eqNullSafe(b["b"])).groupBy("toxic").agg(F.count("*").alias("n"))


@query("SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey <> b.n_regionkey")
def join_theta(spark: SparkSession, sf: str) -> DataFrame:
    n = read_table(spark, sf, "nation", "n_nationkey", "n_regionkey")
    a, b = n.toDF("a", "ra"), F.broadcast(n.toDF("b", "rb"))  # 25 rows at every scale
    return a.join(b, (F.col("a") < F.col("b")) & (F.col("ra") != F.col("rb"))).select("a", "b")


@query("SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1 HAVING count(*) > (SELECT avg(c) FROM (SELECT count(*) AS c FROM lineitem GROUP BY l_suppkey))")
def agg_having(spark: SparkSession, sf: str) -> DataFrame:
    n = read_table(spark, sf, "lineitem", "l_suppkey").groupBy("l_suppkey").agg(F.count("*").alias("n"))
    return n.join(F.broadcast(n.agg(F.avg("n").alias("mean"))), F.col("n") > F.col("mean")).select("l_suppkey", "n")  # one row


@query("SELECT round(corr(l_quantity, l_extendedprice), 6) AS c, round(covar_pop(l_quantity::DOUBLE, l_discount::DOUBLE), 6) AS v FROM lineitem")
def agg_corr_covar(spark: SparkSession, sf: str) -> DataFrame:
    return read_table(spark, sf, "lineitem", "l_quantity", "l_extendedprice", "l_discount").agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("c"), F.round(F.covar_pop("l_quantity", "l_discount"), 6).alias("v"))


@query("SELECT n_name AS name, n_nationkey AS key FROM nation UNION ALL BY NAME SELECT r_regionkey AS key, r_name AS name FROM region")
def set_union_by_name(spark: SparkSession, sf: str) -> DataFrame:
    n = read_table(spark, sf, "nation").select(F.col("n_name").alias("name"), F.col("n_nationkey").alias("key"))
    return n.unionByName(read_table(spark, sf, "region").select(F.col("r_regionkey").alias("key"), F.col("r_name").alias("name")))
