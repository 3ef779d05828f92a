"""Relational queries around the methods: filters, joins, aggregation, windows, sets, functions, subqueries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evenpart.operators.joins import asof_last, band_join, within
from evenpart.queries.registry import registry
from evenpart.sources.tables import read_table as T

QUERIES, ORACLES, query = registry()


def _n(c: Column) -> Column:
    return F.sum(F.when(c, 1).otherwise(0))


# ---- projection and filters ------------------------------------------------------------------------------------


@query("SELECT p_partkey, p_size::DOUBLE AS size, p_retailprice AS price FROM part")
def proj_features(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "part", "p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))


@query("SELECT p_partkey, p_retailprice FROM part WHERE p_retailprice BETWEEN 905 AND 950")
def filter_price_band(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "part", "p_partkey", "p_retailprice").where(F.col("p_retailprice").between(905, 950))


@query("SELECT p_partkey, p_type FROM part WHERE p_type IN ('SMALL', 'ECONOMY') AND p_name LIKE '%ring%' AND p_brand IS NOT NULL")
def filter_in_like_null(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "part").where(F.col("p_type").isin("SMALL", "ECONOMY") & F.col("p_name").like("%ring%") & F.col("p_brand").isNotNull()).select("p_partkey", "p_type")


@query("SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1997-01-01'")
def filter_date_range(spark: SparkSession, sf: str) -> DataFrame:
    day = lambda d: F.lit(d).cast("timestamp_ntz")
    return T(spark, sf, "lineitem").where((F.col("l_shipdate") >= day("1996-01-01")) & (F.col("l_shipdate") < day("1997-01-01"))).select("l_orderkey", "l_linenumber", "l_quantity")


@query("SELECT CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS bucket, count(*) AS n FROM part GROUP BY 1")
def case_bucket(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "part", "p_size").groupBy(F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "medium").otherwise("large").alias("bucket")).agg(F.count("*").alias("n"))


# ---- joins -----------------------------------------------------------------------------------------------------


@query("SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey")
def join_order_customer(spark: SparkSession, sf: str) -> DataFrame:
    c = T(spark, sf, "customer", F.col("c_custkey").alias("o_custkey"), "c_mktsegment")
    return T(spark, sf, "orders", "o_orderkey", "o_custkey").join(c, "o_custkey").select("o_orderkey", "c_mktsegment")


@query("SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def join_broadcast_nation_region(spark: SparkSession, sf: str) -> DataFrame:
    r = T(spark, sf, "region").withColumnRenamed("r_regionkey", "n_regionkey")
    return T(spark, sf, "nation").join(F.broadcast(r), "n_regionkey").select("n_name", "r_name")  # five rows at any scale


def _hinted(hint: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        o = T(spark, sf, "orders", F.col("o_orderkey").alias("l_orderkey"), "o_orderstatus").hint(hint)
        return T(spark, sf, "lineitem", "l_orderkey", "l_quantity").join(o, "l_orderkey").groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))

    return run


_BY_STATUS = "SELECT o_orderstatus, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"
query(_BY_STATUS, "join_sortmerge_lineitem_orders")(_hinted("merge"))
query(_BY_STATUS, "join_shuffle_hash")(_hinted("shuffle_hash"))


@query("SELECT d.doc_id, toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def join_left_unlabelled_docs(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "documents", "doc_id").join(T(spark, sf, "labels", "doc_id", "toxic"), "doc_id", "left")


@query("SELECT coalesce(u, c_custkey) AS id, n, c_mktsegment FROM (SELECT user_id AS u, count(*) AS n FROM events GROUP BY 1) FULL JOIN customer ON u = c_custkey")
def join_full_outer(spark: SparkSession, sf: str) -> DataFrame:
    seen = T(spark, sf, "events", F.col("user_id").alias("id")).groupBy("id").agg(F.count("*").alias("n"))
    return seen.join(T(spark, sf, "customer", F.col("c_custkey").alias("id"), "c_mktsegment"), "id", "full")


@query("SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi_labelled(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "documents", "doc_id", "lang").join(T(spark, sf, "labels", "doc_id"), "doc_id", "left_semi")


@query("SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti_residue(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "documents", "doc_id", "lang").join(T(spark, sf, "labels", "doc_id"), "doc_id", "left_anti")


@query("SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def join_theta_pairs(spark: SparkSession, sf: str) -> DataFrame:
    n = T(spark, sf, "nation", "n_nationkey", "n_regionkey")
    return n.withColumnRenamed("n_nationkey", "a").join(n.withColumnRenamed("n_nationkey", "b"), "n_regionkey").where("a < b").select("a", "b")


@query("SELECT p_partkey, range AS band FROM part, range(200) WHERE p_retailprice >= 900 + 10 * range AND p_retailprice < 915 + 10 * range")
def join_range_price_band(spark: SparkSession, sf: str) -> DataFrame:
    bands = spark.range(200).select(F.col("id").alias("band"), (900.0 + 10 * F.col("id")).alias("lo"), (915.0 + 10 * F.col("id")).alias("hi"))
    return band_join(T(spark, sf, "part", "p_partkey", "p_retailprice"), bands, "p_retailprice", "lo", "hi", 10.0).select("p_partkey", "band")


@query("SELECT e.event_id, c.event_id AS click_id FROM (SELECT * FROM events WHERE event_type = 'error') e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON e.user_id = c.user_id AND e.ts >= c.ts")
def join_asof_event_prev(spark: SparkSession, sf: str) -> DataFrame:
    e = T(spark, sf, "events", "event_id", "user_id", "ts", "event_type")
    clicks = e.where("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("click_id"))
    return asof_last(e.where("event_type = 'error'").select("event_id", "user_id", "ts"), clicks, "user_id", "ts", "click_id").select("event_id", "click_id")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def join_interval_events(spark: SparkSession, sf: str) -> DataFrame:
    return within(T(spark, sf, "events", "event_id", "user_id", "ts"), "user_id", "ts", "event_id", 600)


@query("SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM customer JOIN orders ON c_custkey = o_custkey) WHERE r <= 2")
def join_lateral_topk(spark: SparkSession, sf: str) -> DataFrame:
    r = F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))
    top = T(spark, sf, "orders", "o_custkey", "o_orderkey", "o_totalprice").withColumn("r", r).where("r <= 2")
    return T(spark, sf, "customer", "c_custkey").join(top, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey")


# ---- aggregation -----------------------------------------------------------------------------------------------


@query("SELECT l_returnflag, l_linestatus, sum(l_quantity) AS sum_qty, round(avg(l_discount), 6) AS avg_disc, count(*) AS n FROM lineitem GROUP BY 1, 2")
def agg_partial_final(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("sum_qty"), F.round(F.avg("l_discount"), 6).alias("avg_disc"), F.count("*").alias("n"))


@query("SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
def agg_distinct_parts(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "lineitem", "l_suppkey", "l_partkey").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"))


@query()
def agg_approx_distinct(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "lineitem", "l_suppkey", "l_partkey").groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@query("SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def agg_rollup_region_nation(spark: SparkSession, sf: str) -> DataFrame:
    # the counts are made by nation first: 25 rows meet the names
    by = T(spark, sf, "customer", "c_nationkey").groupBy("c_nationkey").agg(F.count("*").alias("c"))
    named = by.join(T(spark, sf, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(T(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return named.rollup("r_name", "n_name").agg(F.sum("c").alias("n"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube_flag_status(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "lineitem", "l_returnflag", "l_linestatus").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def agg_grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    d = T(spark, sf, "documents", "lang", "source")
    return d.groupingSets([[F.col("lang")], [F.col("source")], []], "lang", "source").agg(F.count("*").alias("n"))


@query("SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'fr') AS fr, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'es') AS es FROM documents GROUP BY 1")
def agg_pivot_confusion(spark: SparkSession, sf: str) -> DataFrame:
    langs = ["en", "fr", "de", "es"]
    p = T(spark, sf, "documents", "source", "lang").groupBy("source").pivot("lang", langs).agg(F.count(F.lit(1)))
    return p.select("source", *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in langs])


@query("SELECT source, arg_max(lang, (n, lang)) AS lang FROM (SELECT source, lang, count(*) AS n FROM documents GROUP BY 1, 2) GROUP BY 1")
def agg_mode(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "documents", "source", "lang").groupBy("source", "lang").agg(F.count("*").alias("n")).groupBy("source").agg(F.max_by("lang", F.struct("n", "lang")).alias("lang"))


@query("SELECT p_type, round(quantile_cont(p_retailprice, 0.25), 6) AS q1, round(quantile_cont(p_retailprice, 0.5), 6) AS q2, round(quantile_cont(p_retailprice, 0.75), 6) AS q3 FROM part GROUP BY 1")
def agg_percentile(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "part", "p_type", "p_retailprice").groupBy("p_type").agg(*[F.round(F.percentile("p_retailprice", q), 6).alias(f"q{i}") for i, q in ((1, 0.25), (2, 0.5), (3, 0.75))])


@query("SELECT p_type, round(avg(p_size), 6) AS mean, round(stddev_pop(p_size), 6) AS sd, round((max(p_size) - avg(p_size)) / stddev_pop(p_size), 6) AS top_z FROM part GROUP BY 1")
def agg_stddev_z(spark: SparkSession, sf: str) -> DataFrame:
    m, s = F.avg("p_size"), F.stddev_pop("p_size")
    return T(spark, sf, "part", "p_type", "p_size").groupBy("p_type").agg(F.round(m, 6).alias("mean"), F.round(s, 6).alias("sd"), F.round((F.max("p_size") - m) / s, 6).alias("top_z"))


@query("SELECT user_id, count(*) FILTER (event_type = 'error') AS errors, count(*) FILTER (event_type = 'click') AS clicks FROM events GROUP BY 1")
def agg_filter_clause(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "events", "user_id", "event_type").groupBy("user_id").agg(_n(F.col("event_type") == "error").alias("errors"), _n(F.col("event_type") == "click").alias("clicks"))


@query("SELECT l_suppkey, string_agg(DISTINCT l_returnflag, ',' ORDER BY l_returnflag) AS flags FROM lineitem GROUP BY 1")
def agg_collect_sorted(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "lineitem", "l_suppkey", "l_returnflag").groupBy("l_suppkey").agg(F.array_join(F.array_sort(F.collect_set("l_returnflag")), ",").alias("flags"))


@query("SELECT o_custkey, arg_max(o_orderkey, (o_orderdate, o_orderkey)) AS last_order FROM orders GROUP BY 1")
def agg_max_by(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "orders", "o_custkey", "o_orderkey", "o_orderdate").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_orderdate", "o_orderkey")).alias("last_order"))


# ---- windows: every one has a partition key, so that no task sorts a whole table -----------------------------------

_OVER = "OVER (PARTITION BY user_id ORDER BY ts, event_id)"


def _user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


def _window(name: str, sql: str, make) -> None:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        return T(spark, sf, "events", "event_id", "user_id", "ts", "value").select("event_id", make().alias("got"))

    query(f"SELECT event_id, {sql} AS got FROM events", name)(run)


_window("win_row_number_chunk", f"(row_number() {_OVER} - 1) // 5", lambda: F.floor((F.row_number().over(_user()) - 1) / 5))
_window("win_ntile", f"ntile(4) {_OVER}", lambda: F.ntile(4).over(_user()).cast("long"))
_window("win_lag_energy", f"round(value - lag(value) {_OVER}, 6)", lambda: F.round(F.col("value") - F.lag("value").over(_user()), 6))
_window("win_running_sum", f"round(sum(value) {_OVER}, 4)", lambda: F.round(F.sum("value").over(_user()), 4))
_window("win_rows_frame", "round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4)", lambda: F.round(F.avg("value").over(_user().rowsBetween(-2, 0)), 4))
_window("win_range_frame", "count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW)", lambda: F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)))
_window("win_first_last", "last_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) - first_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id)", lambda: F.last("event_id").over(_user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)) - F.first("event_id").over(_user()))
_window("win_percent_rank_cume", f"round(percent_rank() {_OVER} + cume_dist() {_OVER}, 6)", lambda: F.round(F.percent_rank().over(_user()) + F.cume_dist().over(_user()), 6))


@query("SELECT p_partkey, rank() OVER (PARTITION BY p_type ORDER BY p_size) AS r, dense_rank() OVER (PARTITION BY p_type ORDER BY p_size) AS d FROM part")
def win_rank_dense(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("p_type").orderBy("p_size")
    return T(spark, sf, "part", "p_partkey", "p_type", "p_size").select("p_partkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("d"))


# ---- order, limits and sets --------------------------------------------------------------------------------------


@query("SELECT c_custkey, c_acctbal FROM customer ORDER BY c_mktsegment, c_acctbal DESC, c_custkey")
def sort_multi(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "customer").orderBy("c_mktsegment", F.desc("c_acctbal"), "c_custkey").select("c_custkey", "c_acctbal")


_SHARED = "SELECT a.u AS src, b.u AS dst, count(*) AS w FROM (SELECT DISTINCT l_suppkey AS u, l_partkey AS h FROM lineitem) a JOIN (SELECT DISTINCT l_suppkey AS u, l_partkey AS h FROM lineitem) b ON a.h = b.h AND a.u < b.u GROUP BY 1, 2"


def _shared(spark, sf):
    from evenpart.operators.graphs import co_occurrence

    return co_occurrence(T(spark, sf, "lineitem", "l_suppkey", "l_partkey"), "l_suppkey", "l_partkey")


@query(f"SELECT * FROM ({_SHARED}) ORDER BY w DESC, src, dst LIMIT 20")
def topk_global_edges(spark: SparkSession, sf: str) -> DataFrame:
    return _shared(spark, sf).orderBy(F.desc("w"), "src", "dst").limit(20)


@query(f"SELECT src, dst, w FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS r FROM ({_SHARED})) WHERE r <= 3")
def topk_per_vertex(spark: SparkSession, sf: str) -> DataFrame:
    return _shared(spark, sf).withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("w"), "dst"))).where("r <= 3").drop("r")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")
def limit_offset(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(10)


def _sets(name: str, sql: str, make) -> None:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        a = T(spark, sf, "customer", F.col("c_nationkey").alias("k"))
        return make(a, T(spark, sf, "supplier", F.col("s_nationkey").alias("k")))

    query(f"SELECT c_nationkey AS k FROM customer {sql} SELECT s_nationkey FROM supplier", name)(run)


_sets("set_union_all", "UNION ALL", lambda a, b: a.unionAll(b))
_sets("set_union_distinct", "UNION", lambda a, b: a.union(b).distinct())
_sets("set_intersect", "INTERSECT", lambda a, b: a.intersect(b))
_sets("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b))
_sets("set_except", "EXCEPT", lambda a, b: a.subtract(b))
_sets("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))


# ---- scalar functions --------------------------------------------------------------------------------------------


@query("SELECT p_partkey, length(p_name) AS len, md5(p_name) AS m, translate(p_brand, '#', '-') AS brand, regexp_extract(p_brand, '([0-9]+)', 1) AS no, split_part(p_name, ' ', 1) AS head, upper(substr(p_type, 1, 2)) AS pre FROM part")
def fn_string(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "part", "p_partkey", "p_name", "p_brand", "p_type").select(
        "p_partkey", F.length("p_name").cast("long").alias("len"), F.md5("p_name").alias("m"), F.translate("p_brand", "#", "-").alias("brand"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("no"),
        F.split_part("p_name", F.lit(" "), F.lit(1)).alias("head"), F.upper(F.substring("p_type", 1, 2)).alias("pre"),
    )


@query("SELECT event_id, hour(ts) AS h, isodow(ts) AS dow, date_diff('day', DATE '2024-01-01', ts::DATE) AS days, strftime(date_trunc('day', ts + INTERVAL 12 HOUR), '%Y-%m-%d') AS noon FROM events")
def fn_date(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "events", "event_id", "ts").select(
        "event_id", F.hour("ts").cast("long").alias("h"), (F.weekday("ts") + 1).cast("long").alias("dow"), F.datediff("ts", F.lit("2024-01-01").cast("date")).cast("long").alias("days"),
        F.date_format(F.date_trunc("day", F.col("ts") + F.expr("INTERVAL 12 HOURS")), "yyyy-MM-dd").alias("noon"),
    )


@query("SELECT p_partkey, round(exp(-p_size / 10.0), 6) AS e, round(sqrt(p_retailprice), 6) AS s, round(ln(p_retailprice), 6) AS l, greatest(p_size, 20) AS g, least(p_size, 20) AS m, p_partkey % 7 AS r FROM part")
def fn_math(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "part", "p_partkey", "p_size", "p_retailprice").select(
        "p_partkey", F.round(F.exp(-F.col("p_size") / 10.0), 6).alias("e"), F.round(F.sqrt("p_retailprice"), 6).alias("s"), F.round(F.log("p_retailprice"), 6).alias("l"),
        F.greatest("p_size", F.lit(20)).alias("g"), F.least("p_size", F.lit(20)).alias("m"), F.pmod("p_partkey", F.lit(7)).alias("r"),
    )


@query("SELECT vec_id, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda v: v::DOUBLE * v::DOUBLE)), 5) AS norm, len(list_filter(embedding, lambda v: v > 0)) AS positive, round(list_max(embedding)::DOUBLE, 6) AS most FROM embeddings")
def fn_array(spark: SparkSession, sf: str) -> DataFrame:
    x = F.transform("embedding", lambda v: v.cast("double"))
    return T(spark, sf, "embeddings", "vec_id", "embedding").select(
        "vec_id", F.size("embedding").cast("long").alias("n"), F.round(F.aggregate(x, F.lit(0.0), lambda a, v: a + v * v), 5).alias("norm"),
        F.size(F.filter("embedding", lambda v: v > 0)).cast("long").alias("positive"), F.round(F.array_max(x), 6).alias("most"),
    )


@query("SELECT event_id, k, v FROM (SELECT event_id, 'user' AS k, user_id AS v FROM events UNION ALL SELECT event_id, 'k', (props->>'$.k')::BIGINT FROM events)")
def fn_map(spark: SparkSession, sf: str) -> DataFrame:
    held = F.map_from_arrays(F.array(F.lit("user"), F.lit("k")), F.array("user_id", F.get_json_object("props", "$.k").cast("long")))
    return T(spark, sf, "events", "event_id", "user_id", "props").select("event_id", F.explode(held).alias("k", "v"))


@query("SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events")
def fn_json_struct(spark: SparkSession, sf: str) -> DataFrame:
    return T(spark, sf, "events", "event_id", "props").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


# ---- subqueries ----------------------------------------------------------------------------------------------------


def _sql(name: str, spark_sql: str, tables: tuple[str, ...], duck_sql: str | None = None) -> None:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        return spark.sql(spark_sql, **{t: T(spark, sf, t) for t in tables})

    query(duck_sql or spark_sql.replace("{", "").replace("}", ""), name)(run)


_sql("sub_scalar", "SELECT p_partkey FROM {part} WHERE p_retailprice > (SELECT avg(p_retailprice) FROM {part})", ("part",))
_sql("sub_exists", "SELECT c_custkey FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 400000)", ("customer", "orders"))
_sql("sub_in", "SELECT s_suppkey FROM {supplier} WHERE s_nationkey IN (SELECT n_nationkey FROM {nation} WHERE n_regionkey = 1)", ("supplier", "nation"))
_sql("cte_recursive", "WITH RECURSIVE r(k, m) AS (SELECT CAST(2 AS BIGINT), count(DISTINCT o_custkey) FROM {orders} UNION ALL SELECT k * 2, CAST(floor(m / 2) AS BIGINT) FROM r WHERE m > 128) SELECT k, m FROM r", ("orders",))
