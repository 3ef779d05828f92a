"""Joins that Spark would run as nested loops, given an equality to shuffle on."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def band_join(rows: DataFrame, bands: DataFrame, value: str, lo: str, hi: str, width: float) -> DataFrame:
    """Rows with the bands where ``lo <= value < hi``; both sides meet on steps of ``width``, then the bounds are tested.

    A band stands once in every step it touches, a row in one step only, so no pair comes twice.
    """
    step = lambda c: F.floor(F.col(c) / width)
    spread = bands.withColumn("_step", F.explode(F.sequence(step(lo), step(hi))))
    return rows.withColumn("_step", step(value)).join(spread, "_step").where((F.col(value) >= F.col(lo)) & (F.col(value) < F.col(hi))).drop("_step")


def asof_last(rows: DataFrame, states: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """``rows`` with ``value`` of the last state of the same key at or before their time (null if there is none).

    One sort of both tables by (key, time) and a running last value; nothing is paired.
    """
    both = rows.withColumns({value: F.lit(None).cast(states.schema[value].dataType), "_row": F.lit(1)}).unionByName(states.select(key, ts, value).withColumn("_row", F.lit(0)), allowMissingColumns=True)
    seen = Window.partitionBy(key).orderBy(ts, "_row", value).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(seen)).where("_row = 1").drop("_row")


def within(rows: DataFrame, key: str, ts: str, row_id: str, seconds: int) -> DataFrame:
    """(a, b): rows of one key with a < b, b at most ``seconds`` after a and not before it.

    Rows meet on (key, time step); a row also looks into the step after its own.
    """
    step = F.floor(F.unix_seconds(F.col(ts).cast("timestamp")) / seconds)
    a = rows.select(key, F.col(row_id).alias("a"), F.col(ts).alias("ta"), F.explode(F.array(step, step + 1)).alias("_step"))
    b = rows.select(key, F.col(row_id).alias("b"), F.col(ts).alias("tb"), step.alias("_step"))
    end = F.col("ta") + F.expr(f"INTERVAL {seconds} SECONDS")
    return a.join(b, [key, "_step"]).where((F.col("a") < F.col("b")) & (F.col("tb") >= F.col("ta")) & (F.col("tb") <= end)).select("a", "b")


def spread_lookup(rows: DataFrame, table: DataFrame, keys: list[str], by: list[str], spread: int = 64) -> DataFrame:
    """``rows`` with the columns of ``table`` (one row a key); rows without a key in ``table`` go.  Keys aren't null.

    A key may hold a third of all rows: its rows are dealt over ``spread`` parts by the columns ``by``, and the row of
    ``table`` travels to those parts only that hold the key, which the map side finds before anything is shuffled.
    """
    salted = rows.withColumn("_salt", F.pmod(F.xxhash64(*by), F.lit(spread)))
    wide = salted.select(*keys, "_salt").distinct().join(table, keys)
    return salted.join(wide, [*keys, "_salt"]).drop("_salt")


def spread_groups(rows: DataFrame, keys: list[str], by: list[str], aggregates: dict[str, tuple[Column, Column]], spread: int = 64) -> DataFrame:
    """``rows`` with aggregates of their group; ``aggregates`` are name -> (over rows, over the partial results of that name).

    Groups of any size are summed in two steps, over ``spread`` parts first, and each part gets its group's result once.
    """
    salted = rows.withColumn("_salt", F.pmod(F.xxhash64(*by), F.lit(spread)))
    parts = salted.groupBy(*keys, "_salt").agg(*[first.alias(name) for name, (first, _) in aggregates.items()])
    whole = parts.groupBy(*keys).agg(*[then.alias(name) for name, (_, then) in aggregates.items()])
    wide = parts.select(*keys, "_salt").join(whole, keys)
    return salted.join(wide, [*keys, "_salt"]).drop("_salt")
