"""A corpus from raw documents: toxic ones go, copies and near copies go, sources are mixed, sequences are packed.

Every stage takes (spark, docs, sf_dir) and returns a frame; ``run`` writes each as Parquet to the shared folder and
reads it again as the next stage's documents, whose own file then goes.

Defined results: a null text is an empty one, is clean, equals other empty ones and packs to its end id; texts of any
length pass whole; a row that stands twice, or an id that several rows share, is judged by its text, and one row of each
distinct text stays (the longest original, then the smallest id, then the smallest row); ties between near copies go to
the smallest id, null ids last; empty tables give no sequences; all stages but the last return the columns of documents,
more of them or others by name included.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from evenpart.llm import exact_dedup, mixing, near_copies, packing, toxicity
from evenpart.plans.scratch import cut, release
from evenpart.sources.tables import read_table

#: The mix spends this share of all tokens and takes no document twice.
MIX_BUDGET, MIX_REPEATS = 0.9, 1.0


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.keep_clean(docs, read_table(spark, sf_dir, "labels", "doc_id", "toxic"))


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.keep_first(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_copies.keep_representatives(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.realise(docs, budget=MIX_BUDGET, repeats=MIX_REPEATS)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, packing.vocabulary_path())


STAGES = [("toxicity", drop_toxic), ("exact_dedup", drop_copies), ("simhash", drop_near_copies), ("mixing", mix_sources), ("packing", pack_sequences)]

#: Learning, tokenising and packing have no SQL form; tests hold the stages against brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        before, docs = docs, cut(stage(spark, docs, sf_dir))
        release(before)
    return docs
