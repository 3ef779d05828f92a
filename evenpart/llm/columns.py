"""Columns that are safe on any input: names that clash with nothing, rows told apart by id and text."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def fresh(df: DataFrame, *names: str) -> list[str]:
    """``names``, each with as many leading underscores as it needs to be no column of ``df`` (nor one of the others)."""
    held, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in held:
            name = "_" + name
        held.add(name.lower())
        out.append(name)
    return out


def text_key(text: Column) -> Column:
    """SHA-256 of the whole original text, null like empty."""
    return F.sha2(F.coalesce(text, F.lit("")), 256)


def stay(docs: DataFrame, kept: DataFrame, repeated: DataFrame) -> DataFrame:
    """The rows of ``docs`` that ``kept`` names, one for each of its (doc_id, raw): all columns as given.

    ``kept`` are distinct (doc_id, raw), ``raw`` being ``text_key``; ``repeated`` are those of them that several rows
    of ``docs`` share.  Of such rows, copies in id and text, the smallest by all columns stays; only they are shuffled
    for it, and each task brings its own down to one first.
    """
    i, r = fresh(docs, "_kept_id", "_kept_raw")

    def named(keys: DataFrame) -> tuple[DataFrame, Column]:
        return keys.select(F.col("doc_id").alias(i), F.col("raw").alias(r)), docs["doc_id"].eqNullSafe(F.col(i)) & (text_key(docs["text"]) == F.col(r))

    if repeated.isEmpty():
        return docs.join(*named(kept), "left_semi")
    once = docs.join(*named(kept.join(repeated, kept["doc_id"].eqNullSafe(repeated["doc_id"]) & (kept["raw"] == repeated["raw"]), "left_anti")), "left_semi")
    (row,) = fresh(docs, "_row")
    many = docs.join(*named(repeated), "left_semi").groupBy("doc_id", text_key(F.col("text")).alias(r)).agg(F.min(F.struct(*docs.columns)).alias(row))
    return once.unionByName(many.select(*[F.col(row)[c].alias(c) for c in docs.columns]))
