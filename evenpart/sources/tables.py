"""Readers for the given Parquet tables and for edge lists."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """Scan ``name`` under ``sf_dir``; only ``columns`` if any are named, so that the scan prunes the rest."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_edge_text(spark: SparkSession, path: str, sep: str = " ") -> DataFrame:
    """Edges (src < dst, w) from lines ``a<sep>b[<sep>w]``; loops are dropped, a missing weight is 1."""
    part = F.split(F.trim("value"), sep)
    raw = spark.read.text(path).select(
        part[0].cast("long").alias("a"), part[1].cast("long").alias("b"), F.coalesce(F.get(part, F.lit(2)).cast("double"), F.lit(1.0)).alias("w")
    )
    return raw.where("a <> b").select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), "w")


#: Formats that ``write_table`` and ``read_with`` know; the text ones need a schema to read.
FORMATS = ("parquet", "orc", "json", "csv")


def read_with(spark: SparkSession, path: str, form: str, schema: str) -> DataFrame:
    """Rows of ``path`` under a stated schema; nothing is inferred from the data."""
    if form not in FORMATS:
        raise ValueError(f"{form}: one of {FORMATS}")
    reader = spark.read.schema(schema)
    return (reader.option("header", True) if form == "csv" else reader).format(form).load(path)


def write_table(df: DataFrame, path: str, form: str = "parquet", partition_by: tuple[str, ...] = ()) -> None:
    """Replace ``path`` by the rows, in folders by ``partition_by``; a run that is repeated leaves the same rows."""
    if form not in FORMATS:
        raise ValueError(f"{form}: one of {FORMATS}")
    writer = df.write.mode("overwrite").format(form).partitionBy(*partition_by)
    (writer.option("header", True) if form == "csv" else writer).save(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, *keys: str) -> None:
    """A managed table whose joins and aggregations on ``keys`` need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(table)
