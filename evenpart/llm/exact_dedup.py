"""Operator 2: exact duplicates by deterministic block naming.

A normalised text is cut into blocks of ``block_chars`` code points.  The distinct blocks of the table are sorted by
(64-bit hash, content) and named by their place in that order: 1, 2, 3 and so on.  Then pairs of adjacent names are
sorted and named in the same way, level by level, until one integer is left per document; with the number of blocks it
is the document's identity.  Equal names mean equal contents, whatever the hash does: it only gives the order its first
key, and blocks that share a hash are compared in full.

The order is a radix sort: the top bits of the hash are the bucket, counts of the buckets give each its first number, and
rows are numbered inside buckets only.  Contents are shuffled once, after map-side distinct, to look for hashes with
several contents; that look-up is normally empty, and sorting then moves 12 bytes a distinct block.  Rows of one
original text are reduced to one before they are named, and names return by ``spread_lookup``, so that neither a copied
text nor a block of a third of all documents is a hot key.  No Python runs on executors.

Defined results: null text counts as empty, and empty texts equal each other (no block, name 0); rows that repeat a
doc_id are each counted in group_size and share the verdict of their id when their texts are equal, while ``keep_first``
keeps one of them; ties in length go to the smallest id, null ids last; a text of any length is a list of blocks in one
row; an empty table gives no rows; other columns, whatever their names, are not read, and ``keep_first`` returns them.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evenpart.llm.columns import stay, text_key
from evenpart.operators.joins import spread_groups, spread_lookup
from evenpart.plans.scratch import cut
from evenpart.sources.tables import read_table

#: Deleted before texts are compared: space and U+0009 to U+000D.
BLANKS = r"[\x20\x09-\x0D]+"
BLOCK_CHARS = 4096
#: Top bits of a hash that are its bucket in the sort: counts of 65,536 buckets are one small table.
BUCKET_BITS = 16


def _hash64(item: Column) -> Column:
    return F.xxhash64(item)


def sorted_names(items: DataFrame, keys: list[str]) -> DataFrame:
    """``keys`` and name, for distinct ``keys`` whose first is a hash: the place in their order, from 1."""
    held = items.select(*keys, F.shiftrightunsigned(keys[0], 64 - BUCKET_BITS).alias("bucket"))
    counts = held.groupBy("bucket").agg(F.count("*").alias("n"))
    first = counts.select("bucket", (F.sum("n").over(Window.orderBy("bucket")) - F.col("n")).alias("first"))  # a row a bucket
    place = F.row_number().over(Window.partitionBy("bucket").orderBy(*keys))
    return held.join(F.broadcast(first), "bucket").select(*keys, (F.col("first") + place).alias("name"))


def _tied(items: DataFrame, hashed: Callable[[Column], Column]) -> DataFrame | None:
    """(h, item, t) of the distinct ``item`` that share their hash with a smaller one; None if there are none."""
    distinct = items.groupBy("item").agg(F.lit(1).alias("one")).select("item", hashed(F.col("item")).alias("h"))
    contested = distinct.groupBy("h").count().where("count > 1").select("h")
    if contested.isEmpty():
        return None
    return distinct.join(contested, "h", "left_semi").select("h", "item", (F.row_number().over(Window.partitionBy("h").orderBy("item")) - 1).alias("t")).where("t > 0")


def _numbered(placed: DataFrame, keys: list[str]) -> DataFrame:
    """(raw, n, pos, name) from (raw, n, pos, ``keys``)."""
    names = cut(sorted_names(placed.select(*keys).distinct(), keys))
    return cut(spread_lookup(placed, names, keys, ["raw"]).select("raw", "n", "pos", "name"))


def identities(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", block_chars: int = BLOCK_CHARS, hashed: Callable[[Column], Column] = _hash64) -> DataFrame:
    """doc_id, n_chars, text_sha256, raw (of the original text), n_blocks and name of every row; equal (n_blocks, name) mean equal texts."""
    raw = F.coalesce(F.col(text), F.lit(""))
    blocks = F.regexp_extract_all("norm", F.lit(f"(?s).{{1,{block_chars}}}"), F.lit(0))
    norm = docs.select(F.col(doc_id).alias("doc_id"), F.length(raw).cast("long").alias("n_chars"), text_key(raw).alias("raw"), F.regexp_replace(raw, BLANKS, "").alias("norm")).withColumn("items", blocks)
    rows = cut(norm.select("doc_id", "n_chars", "raw", F.sha2("norm", 256).alias("text_sha256"), F.transform("items", hashed).alias("hs")).withColumn("n_blocks", F.size("hs")))
    texts = cut(rows.where("n_blocks > 0").groupBy("raw").agg(F.first("hs").alias("hs")))
    placed = texts.select("raw", F.size("hs").alias("n"), F.posexplode("hs").alias("pos", "h")).withColumn("t", F.lit(0))
    ties = _tied(norm.select(F.explode("items").alias("item")), hashed)
    if ties is not None:
        late = norm.select("raw", F.posexplode("items").alias("pos", "item")).withColumn("h", hashed(F.col("item"))).join(ties.withColumnRenamed("t", "u"), ["h", "item"]).select("raw", "pos", "u").distinct()
        placed = cut(placed.join(late, ["raw", "pos"], "left").select("raw", "n", "pos", "h", F.coalesce("u", "t").alias("t")))
    level = _numbered(placed, ["h", "t"])
    done = level.where("n = 1").select("raw", "name")
    while not (more := level.where("n > 1")).isEmpty():
        adjacent = more.groupBy("raw", F.floor((F.col("n") + 1) / 2).cast("int").alias("n"), F.floor(F.col("pos") / 2).cast("int").alias("pos"))
        pairs = adjacent.agg(F.sum(F.when(F.col("pos") % 2 == 0, F.col("name"))).alias("l"), F.coalesce(F.sum(F.when(F.col("pos") % 2 == 1, F.col("name"))), F.lit(0)).alias("r"))
        level = _numbered(cut(pairs.withColumn("h", hashed(F.struct("l", "r")))), ["h", "l", "r"])
        done = done.unionByName(level.where("n = 1").select("raw", "name"))
    full = spread_lookup(rows.where("n_blocks > 0"), done, ["raw"], ["doc_id"])
    out = ["doc_id", "n_chars", "text_sha256", "raw", "n_blocks"]
    return full.select(*out, "name").unionByName(rows.where("n_blocks = 0").select(*out, F.lit(0).cast("long").alias("name")))


def _grouped(docs: DataFrame, **options) -> DataFrame:
    """The identities with group_size and first: the original that stays, as (-n_chars, whether the id is null, doc_id, raw)."""
    first = F.struct((-F.col("n_chars")).alias("c"), F.col("doc_id").isNull().alias("x"), F.col("doc_id").alias("d"), F.col("raw").alias("r"))
    sums = {"group_size": (F.count("*"), F.sum("group_size")), "first": (F.min(first), F.min("first"))}
    return spread_groups(identities(docs, **options), ["n_blocks", "name"], ["doc_id"], sums)


def duplicate_groups(docs: DataFrame, **options) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 for every row of ``docs``."""
    return _grouped(docs, **options).select("doc_id", F.col("first.d").alias("keep_id"), "group_size", F.col("doc_id").eqNullSafe(F.col("first.d")).alias("kept"), "text_sha256")


def keep_first(docs: DataFrame) -> DataFrame:
    """One row of ``docs`` for each distinct text, with all its columns: the longest original, then the smallest id, then the smallest row."""
    rows = _grouped(docs).where(F.col("doc_id").eqNullSafe(F.col("first.d")) & (F.col("raw") == F.col("first.r")))
    kept = cut(rows.groupBy("doc_id", "raw").agg(F.count("*").alias("n")))
    return stay(docs, kept.select("doc_id", "raw"), kept.where("n > 1").select("doc_id", "raw"))


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return duplicate_groups(read_table(spark, sf_dir, "documents", "doc_id", "text"))


OP2_SQL = r"""
WITH n AS (SELECT doc_id, length(coalesce(text, '')) AS chars, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', '', 'g')) AS text_sha256 FROM documents),
g AS (SELECT *, first_value(doc_id) OVER (PARTITION BY text_sha256 ORDER BY chars DESC, doc_id) AS keep_id, count(*) OVER (PARTITION BY text_sha256) AS group_size FROM n)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM g
"""
