"""Operator 8: Order MinHash fingerprints.

K-mers are runs of ``k`` words.  The j-th occurrence of a k-mer is an element of its own (occurrence numbering), so the
fingerprint sees a multiset.  The ``POOL`` elements of a text with the smallest hashes stand for it; for each of
``tuples`` independent hashes the two smallest elements of the pool are selected, put in the order in which they stand in
the text, and the hash of the ordered pair is one component.  Swapping passages therefore changes components although
the set of k-mers stays: the likeness falls with edit distance, not with set distance only.  A text of at most ``POOL``
elements is its own pool, so short texts have ordered components as long ones do.

All of it happens inside a row with array functions on sorted packed longs; no k-mer becomes a row, and nothing
leaves the JVM.  A text crosses one exchange, to stand beside its successor, and is fingerprinted behind it, once; no
table of texts is written.

Defined results: null text is empty; a text of fewer than ``k`` words is one k-mer; a text of one k-mer has unordered
components; an empty text has the empty fingerprint, like 1 to another empty one and 0 to the rest; elements that tie in
a hash are ordered by their own hash; places in texts of more than 16.7 million words are told apart to one part in 16.7
million; rows with equal doc_id follow one another in text order, null ids first; with one document the successor is the
document itself; an empty table gives no rows; other columns, whatever their names, are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evenpart.plans.scratch import cut
from evenpart.sources.tables import read_table

K_WORDS, TUPLES, POOL = 2, 32, 64
#: A packed element: 39 bits of hash, 24 bits of place.
PLACE_BITS, HASH_BITS = 24, 39
POOL_BITS = POOL.bit_length() - 1
#: Rows of an id range; ranges of the first level, whose ends are quantiles and constants of the plan.
ROWS_PER_BUCKET, FIRST_LEVEL = 1024, 4096


def _let(value: Column, body) -> Column:
    """``body`` with ``value`` evaluated once."""
    return F.transform(F.array(value), body)[0]


def _pack(h: Column, place: Column) -> Column:
    return F.shiftleft(F.shiftrightunsigned(h, 64 - HASH_BITS), PLACE_BITS).bitwiseOR(place.cast("long").bitwiseAND(F.lit((1 << PLACE_BITS) - 1)))


def fingerprint(text: Column, k: int = K_WORDS, tuples: int = TUPLES) -> Column:
    """``tuples`` components of 8 hex digits each, "" for a component without elements, joined by commas."""
    words = F.filter(F.split(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+"), lambda w: w != "")

    def starts(sorted_: Column, shift: int) -> Column:
        """Places in a sorted array where the value above ``shift`` bits changes."""
        return F.filter(
            F.sequence(F.lit(0), F.size(sorted_) - 1),
            lambda i: (i == 0) | (F.shiftrightunsigned(F.get(sorted_, i), shift) != F.shiftrightunsigned(F.get(sorted_, F.greatest(i - 1, F.lit(0))), shift)),
        )

    def kmers(h: Column) -> Column:
        last = F.greatest(F.size(h) - k, F.lit(0))
        coarse = F.greatest(F.ceil(F.log2(F.size(h).cast("double"))).cast("int") - PLACE_BITS, F.lit(0))
        return _let(coarse, lambda c: F.transform(F.sequence(F.lit(0), last), lambda i: _pack(F.xxhash64(*[F.get(h, i + j) for j in range(k)]), F.call_function("shiftrightunsigned", i, c))))

    def numbered(s: Column) -> Column:
        """Elements (k-mer, occurrence) from k-mers sorted by (hash, place)."""
        def runs(at: Column) -> Column:
            def run(b: Column, r: Column) -> Column:
                size = F.coalesce(F.get(at, r + 1), F.size(s)) - b
                first = F.shiftrightunsigned(F.get(s, b), PLACE_BITS)
                mask = F.lit((1 << PLACE_BITS) - 1)
                return F.transform(F.sequence(F.lit(0), size - 1), lambda o: _pack(F.xxhash64(first, o), F.get(s, b + o).bitwiseAND(mask)))

            return F.flatten(F.transform(at, run))

        return _let(starts(s, PLACE_BITS), runs)

    place = F.lit((1 << PLACE_BITS) - 1)

    def signature(v: Column) -> Column:
        """Components from the pool: the sorted elements' first."""

        def component(j: Column) -> Column:
            # an independent hash of an element above its number in the pool
            keys = F.transform(v, lambda e, i: F.shiftleft(F.shiftrightunsigned(F.xxhash64(F.shiftrightunsigned(e, PLACE_BITS), j), 8), POOL_BITS).bitwiseOR(i.cast("long")))
            at = lambda key: F.get(v, key.bitwiseAND(F.lit(POOL - 1)).cast("int"))

            def pair(ks: Column) -> Column:
                return _let(F.array_min(ks), lambda a: _let(F.array_min(F.filter(ks, lambda x: x != a)), lambda b: _let(F.struct(at(a).alias("a"), at(b).alias("b")), named)))

            return _let(keys, pair)

        def named(e: Column) -> Column:
            a, b = e["a"], e["b"]
            pa, pb, ha, hb = a.bitwiseAND(place), b.bitwiseAND(place), F.shiftrightunsigned(a, PLACE_BITS), F.shiftrightunsigned(b, PLACE_BITS)
            turned = (pa > pb) | ((pa == pb) & (ha > hb))
            both = F.when(b.isNull(), F.xxhash64(ha)).when(turned, F.xxhash64(hb, ha)).otherwise(F.xxhash64(ha, hb))
            return F.lpad(F.lower(F.hex(both.bitwiseAND(F.lit(0xFFFFFFFF)))), 8, "0")

        return F.array_join(F.transform(F.sequence(F.lit(0), F.lit(tuples - 1)), component), ",")

    empty = ",".join([""] * tuples)
    hashes = lambda w: F.transform(w, lambda x: F.xxhash64(x))
    full = _let(hashes(words), lambda h: F.when(F.size(h) == 0, F.lit(empty)).otherwise(_let(F.sort_array(kmers(h)), lambda s: _let(F.slice(F.sort_array(numbered(s)), 1, POOL), signature))))
    return full


def likeness(a: Column, b: Column) -> Column:
    """Share of equal components among those that either side has; 1 when neither has any."""
    pairs = F.arrays_zip(F.split(a, ",").alias("x"), F.split(b, ",").alias("y"))
    used = F.filter(pairs, lambda p: (p["x"] != "") | (p["y"] != ""))
    return _let(used, lambda u: F.when(F.size(u) == 0, F.lit(1.0)).otherwise(F.size(F.filter(u, lambda p: p["x"] == p["y"])) / F.size(u)))


def with_next(rows: DataFrame, rows_per_bucket: int = ROWS_PER_BUCKET, derived: dict[str, Column] | None = None) -> DataFrame:
    """``rows`` (doc_id, text, more) with ``following``: the struct of the next row by (doc_id, text), cyclic.

    Columns ``derived`` from a row are added to it and to ``following``; they are made behind the exchange, once a row.

    Ids are cut into ranges at approximate quantiles, and each of these into equal steps, until a step has about
    ``rows_per_bucket`` rows; a window orders each step, and only the first row of every step travels to the step before.
    """
    n, low, high = rows.agg(F.count("*"), F.min("doc_id"), F.max("doc_id")).first()
    more = derived or {}
    given, whole = F.struct(*rows.columns), F.struct(*rows.columns, *more)
    if n == 0:
        return rows.withColumns(more).withColumn("following", whole)
    ranges = max(1, min(n // rows_per_bucket, FIRST_LEVEL))
    bounds = rows.agg(F.percentile_approx("doc_id", [i / ranges for i in range(1, ranges)], 10 * ranges).alias("b")).first()["b"] if ranges > 1 else []
    edges = sorted(set(bounds or []))
    index = F.when(F.col("doc_id").isNull(), F.lit(-1)).otherwise(_rank(F.col("doc_id"), edges)).cast("int")
    steps = -(-n // (ranges * rows_per_bucket))
    if steps > 1 and low is not None:
        ends = [low, *edges, high]
        start, width = F.array(*[F.lit(float(e)) for e in ends[:-1]]), F.array(*[F.lit(float(max(b - a, 1))) for a, b in zip(ends, ends[1:], strict=False)])
        share = (F.col("doc_id") - F.get(start, F.greatest("range", F.lit(0)))) / F.get(width, F.greatest("range", F.lit(0)))
        step = F.coalesce(F.greatest(F.least(F.floor(share * steps), F.lit(steps - 1)), F.lit(0)), F.lit(0))
    else:
        step = F.lit(0)
    placed = rows.withColumn("range", index).withColumn("step", step.cast("int"))
    order = Window.partitionBy("range", "step").orderBy("doc_id", "text")
    inner = placed.repartition("range", "step").withColumns(more).withColumn("following", F.lead(whole).over(order))
    heads_of = placed.groupBy("range", "step").agg(F.min(given).alias("first"))
    firsts = cut(heads_of.select("range", "step", "first.*").withColumns(more).select("range", "step", whole.alias("first")))  # a row a step
    present = sorted(r["range"] for r in firsts.select("range").distinct().collect())  # FIRST_LEVEL + 1 numbers
    links = rows.sparkSession.createDataFrame([(present[(i + 1) % len(present)], r) for i, r in enumerate(present)], "range int, to int")
    heads = firsts.groupBy("range").agg(F.min_by("first", "step").alias("far")).join(F.broadcast(links), "range").select(F.col("to").alias("range"), "far")
    near = firsts.withColumn("near", F.lead("first").over(Window.partitionBy("range").orderBy("step")))
    after = near.join(heads, "range").select("range", "step", F.coalesce("near", "far").alias("head"))
    return inner.join(after, ["range", "step"]).withColumn("following", F.coalesce("following", "head")).drop("range", "step", "head")


def _rank(value: Column, edges: list) -> Column:
    """How many edges are below ``value``: a balanced tree of comparisons."""

    def tree(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(value > F.lit(edges[mid]), tree(mid + 1, hi)).otherwise(tree(lo, mid))

    return tree(0, len(edges))


def fingerprints(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """The columns of the digest for every row of ``docs``."""
    plain = docs.select(docs[doc_id].alias("doc_id"), F.coalesce(docs[text], F.lit("")).alias("text"))
    n, following = F.length("text"), F.col("following")
    q = F.floor(n / 4).cast("int")
    edited = F.concat(F.substring("text", F.lit(1), n - q), F.substring(following["text"], F.lit(1), q))
    pair = with_next(plain, derived={"own": fingerprint(F.col("text"))}, **options).select("doc_id", n.cast("long").alias("n_chars"), edited.alias("edited"), "own", following["own"].alias("next"))
    # bound inside an expression: a struct of it would be taken apart, and the fingerprint made once for each reader
    made = _let(fingerprint(F.col("edited")), lambda c: F.struct(c.alias("changed"), likeness(F.col("own"), c).alias("near")))
    return pair.select("doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), "own", "next", made.alias("f")).select(
        "doc_id", "n_chars", "edited_sha256", F.col("own").alias("fingerprint"), F.col("f.changed").alias("edited_fingerprint"),
        F.col("f.near").alias("near_edited"), likeness(F.col("own"), F.col("next")).alias("near_next"),
    )


def op8_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints(read_table(spark, sf_dir, "documents", "doc_id", "text"))
