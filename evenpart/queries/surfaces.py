"""Streaming queries, user-defined functions, readers and sinks."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpart.functions import udfs
from evenpart.operators import clustering as C
from evenpart.operators import graphs as G
from evenpart.plans.scratch import shared_dir
from evenpart.queries.registry import registry
from evenpart.sources.planted import PlantedSource
from evenpart.sources.tables import FORMATS, read_edge_text, read_table, read_with, write_table
from evenpart.streaming import replay

QUERIES, ORACLES, query = registry()

# ---- streams: each equals a batch statement over the whole table ----------------------------------------------------

_HOURS = "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M') AS start, user_id % 4 AS cls, count(*) AS n FROM events GROUP BY 1, 2"

query(_HOURS, "stream_activity")(lambda spark, sf: replay.activity(spark, sf))
query(f"WITH c AS ({_HOURS}) SELECT a.start, a.cls AS s, b.cls AS t, a.n * b.n AS pairs FROM c a JOIN c b ON a.start = b.start AND a.cls < b.cls", "stream_density")(lambda spark, sf: replay.densities(replay.activity(spark, sf)))
query(
    "SELECT strftime(date_trunc('hour', ts) - h * INTERVAL 1 HOUR, '%Y-%m-%d %H:%M') AS start, user_id % 4 AS cls, count(*) AS n FROM events, (SELECT unnest(range(6)) AS h) GROUP BY 1, 2", "stream_density_sliding"
)(lambda spark, sf: replay.activity(spark, sf, width="6 hours", slide="1 hour"))
query(
    "WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 10 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) "
    "SELECT user_id, count(*) AS n, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS first FROM s GROUP BY user_id, k HAVING max(ts) + INTERVAL 10 MINUTE <= (SELECT max(ts) - INTERVAL 10 MINUTE FROM events)", "stream_session"
)(lambda spark, sf: replay.sessions(spark, sf))
query("SELECT DISTINCT event_id, user_id FROM events", "stream_dedup")(lambda spark, sf: replay.deduplicated(spark, sf))
query(
    "SELECT c.event_id AS click_id, e.event_id AS error_id FROM events c JOIN events e ON c.user_id = e.user_id AND c.event_type = 'click' AND e.event_type = 'error' AND e.ts >= c.ts AND e.ts <= c.ts + INTERVAL 10 MINUTE", "stream_join"
)(lambda spark, sf: replay.clicks_before_errors(spark, sf))
query("SELECT user_id % 4 AS cls, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY 1", "stream_drift")(lambda spark, sf: replay.drift(spark, sf).select("cls", "n", F.round("mean", 6).alias("mean")))


@query()
def stream_assign(spark: SparkSession, sf: str) -> DataFrame:
    """Benchmark texts as they come, each given the language most of its nearest documents have."""
    docs = read_table(spark, sf, "documents", "doc_id", "text", "lang").select(F.col("doc_id").alias("vid"), G.text_shape(F.col("text")).alias("x"), F.col("lang").alias("cluster"))
    new = replay.open_stream(spark, sf, "benchmark").select(F.col("item_id").alias("vid"), G.text_shape(F.col("text")).alias("x"))
    # ids of new points may equal ids of documents, which a vote would take for the point itself
    shifted = docs.withColumn("vid", -1 - F.col("vid"))
    return replay.assigned(new, lambda batch: C.vote(batch, shifted))


# ---- user-defined functions -------------------------------------------------------------------------------------------


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda v: v::DOUBLE * v::DOUBLE))), 5) AS dist FROM embeddings")
def udf_anchor_distance(spark: SparkSession, sf: str) -> DataFrame:
    """Distance of each point to the nearest of the anchors; here the origin."""
    v = G.emb_vertices(spark, sf)
    return v.select(F.col("vid").alias("vec_id"), F.round(udfs.anchor_distance([[0.0] * 64])("x"), 5).alias("dist"))


@query("SELECT source, round(-sum(p * ln(p)), 6) AS h FROM (SELECT source, count(*) / sum(count(*)) OVER (PARTITION BY source) AS p FROM documents GROUP BY source, lang) GROUP BY 1")
def udf_group_entropy(spark: SparkSession, sf: str) -> DataFrame:
    counts = read_table(spark, sf, "documents", "source", "lang").groupBy("source", "lang").agg(F.count("*").cast("double").alias("n"))
    return counts.groupBy("source").agg(F.round(udfs.entropy_of_counts("n"), 6).alias("h"))


@query("SELECT round(0.15 + e * 0.35 / 24, 6) AS eps, l::INT AS fanout FROM range(25) a(e), range(2, 8) b(l)")
def udtf_expand_grid(spark: SparkSession, sf: str) -> DataFrame:
    udfs.register(spark)
    return spark.sql("SELECT eps, fanout FROM expand_grid(0.15D, 0.50D, 25, 2, 7)")


@query("SELECT eps, round(eps ** 4 / 16, 12) AS gamma_a, round(eps ** 9 / 108, 12) AS gamma_b FROM (VALUES (0.3::DOUBLE)) t(eps)")
def udtf_theory_table(spark: SparkSession, sf: str) -> DataFrame:
    udfs.register(spark)
    return spark.sql("SELECT 0.3D AS eps, round(gamma_a, 12) AS gamma_a, round(gamma_b, 12) AS gamma_b FROM theory_table(0.3D, 4, 1000)")


@query("SELECT o_orderstatus, round(count(*) / (3.0 * 5.0), 6) AS d, round(count(*) * 1.0 * count(*) / 9, 6) AS e FROM orders GROUP BY 1")
def udf_sql_functions(spark: SparkSession, sf: str) -> DataFrame:
    """The SQL functions for a density (edges over the product of sizes) and for an energy term (d^2 over k^2)."""
    udfs.register(spark)
    held = read_table(spark, sf, "orders", "o_orderstatus").groupBy("o_orderstatus").agg(F.count("*").cast("double").alias("n"))
    return spark.sql("SELECT o_orderstatus, round(ep_density(n, 3, 5), 6) AS d, round(ep_energy(n, 3), 6) AS e FROM {held}", held=held)


@query("SELECT a.user_id AS cls, a.n * b.n AS cells FROM (SELECT user_id, count(*) AS n FROM events WHERE event_type = 'click' GROUP BY 1) a JOIN (SELECT user_id, count(*) AS n FROM events WHERE event_type = 'error' GROUP BY 1) b ON a.user_id = b.user_id")
def udf_cogroup_blocks(spark: SparkSession, sf: str) -> DataFrame:
    """Two sides of a block meet in one task; counts stand in for a kernel on the block."""
    e = read_table(spark, sf, "events", F.col("user_id").alias("cls"), "event_type", "event_id")

    def block(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"cls": [key[0]] if len(a) and len(b) else [], "cells": [len(a) * len(b)] if len(a) and len(b) else []}).astype("int64")

    a, b = e.where("event_type = 'click'").groupBy("cls"), e.where("event_type = 'error'").groupBy("cls")
    return a.cogroup(b).applyInPandas(block, "cls long, cells long")


# ---- readers and sinks ------------------------------------------------------------------------------------------------


def _round_trip(form: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        path = f"{shared_dir(spark)}/evenpart-io-{uuid.uuid4().hex}"
        part = read_table(spark, sf, "part", "p_partkey", "p_type", "p_size")
        write_table(part, path, form, partition_by=("p_type",))
        return read_with(spark, path, form, "p_partkey long, p_size int, p_type string").select("p_partkey", "p_type", "p_size")

    return run


for _form in FORMATS:
    query("SELECT p_partkey, p_type, p_size FROM part", f"io_{_form}")(_round_trip(_form))


@query("SELECT DISTINCT least(user_id, event_id) AS src, greatest(user_id, event_id) AS dst, 1.0::DOUBLE AS w FROM events WHERE user_id <> event_id")
def io_edge_text(spark: SparkSession, sf: str) -> DataFrame:
    path = f"{shared_dir(spark)}/evenpart-io-{uuid.uuid4().hex}"
    read_table(spark, sf, "events", F.concat_ws(" ", "user_id", "event_id").alias("value")).write.text(path)
    return read_edge_text(spark, path).distinct()


@query("WITH p AS (SELECT a.range AS src, b.range AS dst, 1.0::DOUBLE AS w FROM range(256) a JOIN range(256) b ON a.range < b.range WHERE ('0x' || substr(md5(a.range || ':' || b.range || ':42'), 1, 8))::BIGINT / 4294967296.0 < CASE WHEN a.range // 64 = b.range // 64 THEN 0.9 ELSE 0.1 END), i AS (SELECT least(l_suppkey % 256, l_partkey % 256) AS src, greatest(l_suppkey % 256, l_partkey % 256) AS dst, count(*) AS n FROM lineitem GROUP BY 1, 2) SELECT p.src, p.dst, n::DOUBLE AS w FROM p JOIN i ON i.src = p.src AND i.dst = p.dst")
def io_planted_source(spark: SparkSession, sf: str) -> DataFrame:
    """A block graph read from the engine's own data source, weighted by the items of lineitem that meet on its edges."""
    spark.dataSource.register(PlantedSource)
    links = spark.read.format("planted").options(n=256, blocks=4).load().select("src", "dst")
    ends = read_table(spark, sf, "lineitem", (F.col("l_suppkey") % 256).cast("long").alias("a"), (F.col("l_partkey") % 256).cast("long").alias("b"))
    items = ends.groupBy(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).agg(F.count("*").cast("double").alias("w"))
    return links.join(items, ["src", "dst"])
