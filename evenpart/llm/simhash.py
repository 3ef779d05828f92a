"""Operator 3: SimHash near-duplicates, linked by pivot distance tables.

Fingerprints come from one pass in Arrow batches.  Copies collapse to distinct fingerprints first.  For links at
Hamming distance ``MAX_BITS`` = 4 or less, the 64 bits are cut into six blocks: at least two blocks of two linked
fingerprints are equal, so each distinct fingerprint stands in 15 buckets, one per pair of blocks, and no link is lost.
A bucket is searched with a pivot table: the Hamming distances of its members to ``PIVOTS`` reference fingerprints.  By the
triangle inequality a pair is out if its distances to any reference differ by more than 4; survivors are verified bit
by bit.  A bucket gives a spanning forest of its links, not all its pairs.

A bucket with more than ``BUCKET`` members is dealt into parts, and every two parts meet in a task of their own, so no
task ever holds more than two parts; all pairs of parts are searched, so nothing is capped.

Components return to the rows by ``spread_groups``: a fingerprint that a third of all rows share is no hot key.

Defined results: null text is empty; texts without words have fingerprint zero and are linked like any other; rows that
repeat a doc_id are linked by their fingerprints, and ``keep_representatives`` keeps one row of a component, the smallest
text where the smallest id has several; a null doc_id is larger than any id; a text of any length is read whole, one
word list at a time; any integer type serves as doc_id; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpart.llm.columns import stay, text_key
from evenpart.operators.components import connected_components
from evenpart.operators.joins import spread_groups, spread_lookup
from evenpart.plans.scratch import cut
from evenpart.sources.tables import read_table

SHINGLE, SEED, MAX_BITS = 4, 42, 4
#: (shift, bits) of the six blocks.
BLOCKS = ((0, 11), (11, 11), (22, 11), (33, 11), (44, 10), (54, 10))
PIVOTS, BUCKET = 16, 4096


def reference_fingerprints(n: int = PIVOTS) -> np.ndarray:
    """Fixed, well spread 64-bit values: hashes of 0, 1, 2 and so on."""
    import xxhash

    return np.array([xxhash.xxh64_intdigest(i.to_bytes(8, "little"), 1) for i in range(n)], dtype=np.uint64)


def fingerprint(text: str | None, shingle: int = SHINGLE, seed: int = SEED) -> bytes:
    """Eight bytes, most significant first."""
    from xxhash import xxh64_digest

    words = (text or "").encode().lower().split()
    if not words:
        return bytes(8)
    body = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = np.append(0, ends[:-1] + 1)
    last = max(0, len(words) - shingle)
    stops = ends[min(shingle, len(words)) - 1 :]
    hashed = b"".join([xxh64_digest(body[a:b], seed) for a, b in zip(starts[: last + 1].tolist(), stops.tolist(), strict=True)])
    bits = np.unpackbits(np.frombuffer(hashed, dtype=np.uint8).reshape(-1, 8), axis=1)
    counts = np.zeros(64, dtype=np.int64)
    for lo in range(0, len(bits), 255):  # sums of 255 bits fit in a byte, which keeps the adding in bytes
        counts += bits[lo : lo + 255].sum(axis=0, dtype=np.uint8)
    return np.packbits(counts * 2 > len(bits)).tobytes()


def fingerprints(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, raw, fp): the key of the original text, and the fingerprint as a signed long with the same bits."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = b"".join([fingerprint(t.as_py()) for t in batch.column(2)])
            fp = np.frombuffer(got, dtype=">u8").astype(np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(fp)], names=["doc_id", "raw", "fp"])

    return docs.select(docs[doc_id].cast("long").alias("doc_id"), text_key(docs[text]).alias("raw"), docs[text].alias("text")).mapInArrow(run, "doc_id long, raw string, fp long")


def _block(fp: Column, i: int) -> Column:
    shift, bits = BLOCKS[i]
    return F.shiftrightunsigned(fp, shift).bitwiseAND(F.lit((1 << bits) - 1))


def bucket_keys(fp: Column) -> Column:
    """The 15 bucket keys: number of the pair of blocks, then the two blocks."""
    return F.array(*[F.lit(n << 22).bitwiseOR(F.shiftleft(_block(fp, i), 11)).bitwiseOR(_block(fp, j)) for n, (i, j) in enumerate(combinations(range(len(BLOCKS)), 2))])


def search(fp: np.ndarray, group: np.ndarray, max_bits: int = MAX_BITS) -> tuple[np.ndarray, np.ndarray]:
    """Ends (places in ``fp``) of a spanning forest of the links inside each run of equal ``group``."""
    table = np.bitwise_count(fp[:, None] ^ reference_fingerprints()[None, :]).astype(np.int8)
    root = np.arange(len(fp))
    ends: list[tuple[int, int]] = []

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    at, lag = np.arange(len(fp)), 1
    while True:
        at = at[at < len(fp) - lag]
        at = at[group[at] == group[at + lag]]
        if not len(at):
            break
        near = at[np.abs(table[at] - table[at + lag]).max(axis=1) <= max_bits]
        near = near[np.bitwise_count(fp[near] ^ fp[near + lag]) <= max_bits]
        near = near[root[near] != root[near + lag]]
        for i in near.tolist():
            x, y = find(i), find(i + lag)
            if x != y:
                root[max(x, y)] = min(x, y)
                ends.append((i, i + lag))
        if len(near):
            while (root[root] != root).any():
                root[:] = root[root]
        lag += 1
    a = np.array(ends, dtype=int).reshape(-1, 2)
    return a[:, 0], a[:, 1]


def links(distinct: DataFrame, bucket: int = BUCKET) -> DataFrame:
    """Links (a, b) whose components are those of all links at ``MAX_BITS`` or less among the distinct ``fp``."""
    held = distinct.select("fp", F.explode(bucket_keys(F.col("fp"))).alias("key"))
    # a key of more than `bucket` members: few rows, one for thousands of members
    large = held.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > bucket).select("key", F.ceil(F.col("n") / bucket).cast("int").alias("parts"))
    dealt = held.join(large, "key", "left").withColumn("mine", F.when(F.col("parts").isNull(), 0).otherwise(F.pmod(F.xxhash64("fp"), "parts").cast("int")))
    others = F.when(F.col("parts").isNull(), F.array(F.lit(0))).otherwise(F.sequence(F.lit(0), F.col("parts") - 1))
    meet = dealt.withColumn("other", F.explode(others)).select("fp", "key", F.least("mine", "other").alias("p"), F.greatest("mine", "other").alias("q"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: list[np.ndarray] = []

        def out(rows: np.ndarray) -> pa.RecordBatch:
            change = np.append(0, np.cumsum((rows[1:, 1:] != rows[:-1, 1:]).any(axis=1)))
            fp = rows[:, 0]
            a, b = search(fp.view(np.uint64), change)
            return pa.RecordBatch.from_arrays([pa.array(fp[a]), pa.array(fp[b])], names=["a", "b"])

        for batch in batches:
            rows = np.column_stack([np.ascontiguousarray(batch.column(i).to_numpy(zero_copy_only=False)).astype(np.int64) for i in range(4)])
            kept.append(rows)
            if not len(rows) or (kept[0][0, 1:] == rows[-1, 1:]).all():
                continue  # one bucket so far
            rows = np.concatenate(kept)
            edge = len(rows) - int((rows[::-1, 1:] != rows[-1, 1:]).any(axis=1).argmax())
            kept = [rows[edge:]]
            yield out(np.asfortranarray(rows[:edge]))
        if kept and len(rows := np.concatenate(kept)):
            yield out(np.asfortranarray(rows))

    found = meet.repartition("key", "p", "q").sortWithinPartitions("key", "p", "q").mapInArrow(run, "a long, b long")
    return found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def _components(docs: DataFrame, **columns) -> DataFrame:
    """doc_id, raw, fp and first (whether the id is null, doc_id, raw of the row that stands for the component) of every row."""
    rows = cut(fingerprints(docs, **columns))
    order = F.struct(F.col("doc_id").isNull().alias("x"), F.col("doc_id").alias("d"), F.col("raw").alias("r"))
    distinct = cut(rows.groupBy("fp").agg(F.min(order).alias("first")))
    roots = connected_components(links(distinct.select("fp")))
    named = distinct.join(roots.withColumnRenamed("v", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    known = spread_groups(named.withColumnRenamed("first", "own"), ["root"], ["fp"], {"first": (F.min("own"), F.min("first"))})
    return spread_lookup(rows, known.select("fp", "first"), ["fp"], ["doc_id", "raw"])


def near_duplicates(docs: DataFrame, **columns) -> DataFrame:
    """doc_id, fingerprint, component_id for every row of ``docs``."""
    return _components(docs, **columns).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), F.col("first.d").alias("component_id"))


def keep_representatives(docs: DataFrame) -> DataFrame:
    """One row of each component with all its columns: the smallest doc_id, then the smallest text key, then the smallest row."""
    rows = _components(docs).where(F.col("doc_id").eqNullSafe(F.col("first.d")) & (F.col("raw") == F.col("first.r")))
    kept = cut(rows.groupBy("doc_id", "raw").agg(F.count("*").alias("n")))
    return stay(docs, kept.select("doc_id", "raw"), kept.where("n > 1").select("doc_id", "raw"))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(read_table(spark, sf_dir, "documents", "doc_id", "text"))
