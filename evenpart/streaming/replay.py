"""Structured Streaming around the method: replays of a stored table, and results that equal a batch run.

``drain`` runs a stream until its input is used up.  Each micro-batch goes to a folder named by its number and replaces
what a failed try left there, so a batch that is run again changes nothing; for updates the last batch of a key wins.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpart.plans.scratch import shared_dir

#: Rows may come this late; later ones are dropped by the stateful operators.
LATENESS = "10 minutes"


def open_stream(spark: SparkSession, sf_dir: str, name: str, files_per_trigger: int = 1000) -> DataFrame:
    """The table's files as a stream, a bounded number of files a micro-batch."""
    path = f"{sf_dir}/{name}.parquet"
    return spark.readStream.schema(spark.read.parquet(path).schema).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{path}*")


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return open_stream(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", LATENESS)


def drain(stream: DataFrame, mode: str = "append", keys: list[str] | None = None, each: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Run ``stream`` over all input there is and return the rows it gave (the last ones by ``keys`` in update mode)."""
    spark = stream.sparkSession
    root = f"{shared_dir(spark)}/evenpart-stream-{uuid.uuid4().hex}"

    def store(batch: DataFrame, number: int) -> None:
        (each(batch) if each else batch).write.mode("overwrite").parquet(f"{root}/rows/batch={number}")

    query = stream.writeStream.outputMode(mode).foreachBatch(store).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    got = spark.read.parquet(f"{root}/rows")
    if mode != "update":
        return got.drop("batch")
    others = [c for c in got.columns if c not in (keys or []) and c != "batch"]
    return got.groupBy(*keys).agg(F.max_by(F.struct(*others), "batch").alias("r")).select(*keys, "r.*")


def activity(spark: SparkSession, sf_dir: str, classes: int = 4, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(start, cls, n): events of each class of users in tumbling or sliding windows."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    counts = events(spark, sf_dir).groupBy(w.alias("w"), F.pmod("user_id", F.lit(classes)).alias("cls")).agg(F.count("*").alias("n"))
    return drain(counts.select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), "cls", "n"), "update", ["start", "cls"])


def densities(counts: DataFrame) -> DataFrame:
    """(start, s, t, pairs): co-active event pairs between the classes of one window."""
    a, b = counts.select("start", F.col("cls").alias("s"), F.col("n").alias("ns")), counts.select("start", F.col("cls").alias("t"), F.col("n").alias("nt"))
    return a.join(b, "start").where("s < t").select("start", "s", "t", (F.col("ns") * F.col("nt")).alias("pairs"))


def sessions(spark: SparkSession, sf_dir: str, gap: str = "10 minutes") -> DataFrame:
    """(user_id, n, first) of every session that is closed when the input ends."""
    got = events(spark, sf_dir).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drain(got.select("user_id", "n", F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("first")))


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drain(events(spark, sf_dir).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


def clicks_before_errors(spark: SparkSession, sf_dir: str, minutes: int = 10) -> DataFrame:
    """(click_id, error_id): an error of the same user at most ``minutes`` after a click."""
    c = events(spark, sf_dir).where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u"), F.col("ts").alias("tc"))
    e = events(spark, sf_dir).where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("user_id").alias("v"), F.col("ts").alias("te"))
    return drain(c.join(e, F.expr(f"u = v AND te >= tc AND te <= tc + INTERVAL {minutes} MINUTES")).select("click_id", "error_id"))


def drift(spark: SparkSession, sf_dir: str, classes: int = 4, limit: float = 0.5) -> DataFrame:
    """(cls, n, mean, drifted): running mean of each class of users and whether a batch moved it by more than ``limit``."""

    def step(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        before = total / n if n else None
        for f in frames:
            n, total = n + len(f), total + float(f["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"cls": [key[0]], "n": [n], "mean": [total / n], "drifted": [before is not None and abs(total / n - before) > limit]})

    placed = events(spark, sf_dir).select(F.pmod("user_id", F.lit(classes)).alias("cls"), "value")
    got = placed.groupBy("cls").applyInPandasWithState(step, "cls long, n long, mean double, drifted boolean", "n long, total double", "update", "NoTimeout")
    return drain(got, "update", ["cls"])


def assigned(stream: DataFrame, predict: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """New points (vid, x) of a stream, clustered by a static model batch by batch."""
    return drain(stream, each=predict)
