"""Operator 4: mixing sources to target weights by temperature, realised as budgeted block permutations.

Source shares p are flattened to weights p^a / sum p^a.  The exponent a in [0, 1] is bisected inside one SQL
expression: either the largest a whose weights reach a target entropy (a share of the log of the number of sources),
or the largest flattening (smallest a) whose heaviest repetition, budget x weight / tokens, keeps a limit.  The
weights become token budgets.  Every source is dealt into blocks of about ``block_rows`` rows by a keyed hash.  An
epoch is a keyed permutation of its blocks and of the rows in each block; a budget takes whole epochs and then a
prefix of the next permutation, cut inside one block at the row where the budget is spent.

Prefix sums run over slices of a source's permutation first, over the block totals of a slice then, and over the rows of
the block of the cut at last, so that no task orders all blocks of a source.  Everything is DataFrame functions.

Defined results: a null source is a source of its own; null and empty texts hold no tokens and follow their source's
whole epochs (kept when the budget holds at least one epoch, or when their place comes before the cut); rows of one id and
source are told apart by nothing and are taken together; a text of any length is counted whole; an empty table gives no
rows; an empty source cannot occur; other columns, whatever their names, are not read, and ``realise`` returns them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evenpart.llm.columns import fresh
from evenpart.plans.scratch import cut
from evenpart.sources.tables import read_table

WORD = r"[^\x20\x09-\x0D]+"
BISECTIONS = 60
BLOCK_ROWS = 1000
#: A source's permutation is cut into 4096 slices by the top bits of its block keys.
SLICE_BITS = 12
#: Sources whose weights are sent to all tasks; more are joined by a shuffle.
MOST_SENT = 100_000


def n_tokens(text: Column) -> Column:
    """White-space separated words."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def _bisect(test, grows: bool) -> Column:
    """End of 60 halvings of [0, 1]: ``test(a)`` holds on one side; the end returned is on the side where it holds.

    ``grows``: the test holds for large a (search its smallest such a); else it holds for small a (the largest).
    """

    def step(s: Column, _: Column) -> Column:
        mid = (s["lo"] + s["hi"]) / 2
        up = ~test(mid) if grows else test(mid)
        return F.struct(F.when(up, mid).otherwise(s["lo"]).alias("lo"), F.when(up, s["hi"]).otherwise(mid).alias("hi"))

    ends = F.aggregate(F.sequence(F.lit(1), F.lit(BISECTIONS)), F.struct(F.lit(0.0).alias("lo"), F.lit(1.0).alias("hi")), step)
    if grows:
        return F.when(test(F.lit(0.0)), F.lit(0.0)).otherwise(ends["hi"])
    return F.when(test(F.lit(1.0)), F.lit(1.0)).otherwise(ends["lo"])


def _total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda a, x: a + x)


def source_weights(totals: DataFrame, budget: float, entropy: float | None = None, repeats: float | None = None) -> DataFrame:
    """(source, tokens, share, weight, budget, exponent) from (source, tokens); one of ``entropy`` and ``repeats`` is given.

    ``budget`` is a multiple of all tokens.  A limit on repeats below the budget can't be met and gives exponent 1.
    """
    if (entropy is None) == (repeats is None):
        raise ValueError("give entropy or repeats")
    held = totals.where("tokens > 0").select("source", F.col("tokens").cast("double").alias("t"))
    # one row that holds every source's total: as long as there are sources
    packed = held.agg(F.collect_list(F.struct("source", "t")).alias("rows"), F.sum("t").alias("all"))
    packed = packed.where("all > 0").withColumn("ts", F.array_sort(F.transform("rows", lambda r: r["t"])))

    def logs(a: Column) -> Column:  # p^a by logarithms, scaled by the largest share
        return F.transform("ts", lambda t: F.exp(a * F.log(t / F.array_max("ts"))))

    if entropy is not None:
        # entropy of w_i = e_i / S is log S - sum(e_i log e_i) / S
        def reach(a: Column) -> Column:
            s = _total(logs(a))
            h = F.log(s) - _total(F.transform(logs(a), lambda e: F.when(e > 0, e * F.log(e)).otherwise(0.0))) / s
            return h >= F.lit(float(entropy)) * F.log(F.size("ts").cast("double"))

        exponent = _bisect(reach, grows=False)
    else:

        def keeps(a: Column) -> Column:
            s = _total(logs(a))
            most = F.array_max(F.transform("ts", lambda t: F.exp(a * F.log(t / F.array_max("ts"))) / t))
            return most * F.lit(float(budget)) * F.col("all") / s <= F.lit(repeats * (1 + 1e-12))

        exponent = _bisect(keeps, grows=True)
    solved = packed.select(exponent.alias("exponent"), "all", "rows", F.array_max("ts").alias("top")).withColumn("raw", F.transform("rows", lambda r: F.exp(F.col("exponent") * F.log(r["t"] / F.col("top")))))
    each = solved.select("exponent", "all", _total(F.col("raw")).alias("sum"), F.explode(F.arrays_zip("rows", "raw")).alias("z"))
    weight = F.col("z.raw") / F.col("sum")
    return each.select(
        F.col("z.rows.source").alias("source"), F.col("z.rows.t").cast("long").alias("tokens"), (F.col("z.rows.t") / F.col("all")).alias("share"),
        weight.alias("weight"), (weight * F.lit(float(budget)) * F.col("all")).alias("budget"), "exponent",
    )


def mix(
    docs: DataFrame, budget: float = 1.0, entropy: float | None = None, repeats: float | None = None, seed: int = 42, block_rows: int = BLOCK_ROWS, source: str = "source", text: str = "text", doc_id: str = "doc_id"
) -> DataFrame:
    """doc_id, source, tokens, copies (0 and more), whole_epochs, weight, exponent, epoch_key for every row of ``docs``.

    ``epoch_key`` orders the rows of a source inside its last epoch: (block key, row key) of the permutation.
    """
    rows = cut(docs.select(F.col(doc_id).alias("doc_id"), F.col(source).alias("source"), n_tokens(F.col(text)).alias("tokens")))
    totals = rows.groupBy("source").agg(F.sum("tokens").alias("tokens"), F.count("*").alias("rows"))
    weights = source_weights(totals.select("source", "tokens"), budget, entropy, repeats).withColumnRenamed("source", "s")
    plan = cut(
        totals.select("source", "rows")
        .join(weights, F.col("source").eqNullSafe(F.col("s")), "left")
        .select(
            F.col("source").alias("s"), "weight", "exponent", F.coalesce("tokens", F.lit(0)).alias("source_tokens"),
            F.coalesce(F.floor(F.col("budget") / F.col("tokens") + 1e-9), F.lit(1)).cast("int").alias("whole"),
            F.greatest(F.ceil(F.col("rows") / block_rows), F.lit(1)).alias("n_blocks"),
            F.coalesce(F.col("budget"), F.lit(0.0)).alias("budget"),
        )
    )
    # a row of plan per source: sent to all tasks up to a checked number of sources
    few = plan.limit(MOST_SENT + 1).count() <= MOST_SENT
    dealt = rows.join(F.broadcast(plan) if few else plan, F.col("source").eqNullSafe(F.col("s"))).drop("s")
    row_key = F.xxhash64("doc_id", F.lit(seed))
    dealt = dealt.withColumn("row_key", row_key).withColumn("block", F.pmod(row_key, "n_blocks")).withColumn("block_key", F.xxhash64("block", "source", F.col("whole"), F.lit(seed)))
    block = ["source", "block_key", "block"]
    sums = dealt.groupBy(*block).agg(F.sum("tokens").alias("block_tokens"), F.first("budget").alias("budget"), F.first("whole").alias("whole"), F.first("source_tokens").alias("source_tokens"))
    # prefix sums in two steps, so that no task orders all blocks of a source: its slices first, then the blocks of a slice
    sums = cut(sums.withColumn("slice", F.shiftrightunsigned(F.col("block_key").bitwiseXOR(F.lit(-(2**63))), 64 - SLICE_BITS)))
    slices = sums.groupBy("source", "slice").agg(F.sum("block_tokens").alias("slice_tokens"))
    ahead = F.sum("slice_tokens").over(Window.partitionBy("source").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1))
    slices = slices.select(F.col("source").alias("s"), F.col("slice").alias("l"), F.coalesce(ahead, F.lit(0)).alias("ahead"))
    before = F.sum("block_tokens").over(Window.partitionBy("source", "slice").orderBy("block_key", "block").rowsBetween(Window.unboundedPreceding, -1))
    rest = F.col("budget") - F.col("whole") * F.col("source_tokens")
    blocks = sums.withColumn("inside", F.coalesce(before, F.lit(0))).join(slices, F.col("source").eqNullSafe(F.col("s")) & (F.col("slice") == F.col("l")))
    blocks = blocks.select(F.col("source").alias("s"), F.col("block_key").alias("k"), F.col("block").alias("b"), "block_tokens", (rest - F.col("ahead") - F.col("inside")).alias("left"))
    placed = dealt.join(blocks, F.col("source").eqNullSafe(F.col("s")) & (F.col("block") == F.col("b")) & (F.col("block_key") == F.col("k"))).drop("s", "b", "k")
    # whole blocks before the cut and after it need no order inside; the block of the cut is summed row by row
    split = (F.col("left") > 0) & (F.col("left") < F.col("block_tokens"))
    spent = F.sum("tokens").over(Window.partitionBy("source", "block").orderBy("row_key", "doc_id").rangeBetween(Window.unboundedPreceding, Window.currentRow))
    inside = placed.where(split).withColumn("extra", (F.col("left") - spent >= 0).cast("int"))
    outside = placed.where(~split).withColumn("extra", (F.col("left") >= F.greatest("block_tokens", F.lit(1))).cast("int"))
    return inside.unionByName(outside).select(
        "doc_id", "source", "tokens", (F.col("whole") + F.col("extra")).alias("copies"), F.col("whole").alias("whole_epochs"), "weight", "exponent", "block_key", "row_key"
    )


def realise(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with every row as often as the mix takes it; columns as given."""
    i, s, n = fresh(docs, "_id", "_source", "_n")
    plan = mix(docs, **options).where("copies > 0").groupBy(F.col("doc_id").alias(i), F.col("source").alias(s)).agg(F.max("copies").alias(n))
    taken = docs.join(plan, docs["doc_id"].eqNullSafe(F.col(i)) & docs["source"].eqNullSafe(F.col(s)))
    return taken.withColumn(n, F.explode(F.sequence(F.lit(1), n))).select(*docs.columns)


def op4_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Flattened to 0.97 of the largest entropy, with a budget of all tokens."""
    return mix(read_table(spark, sf_dir, "documents", "doc_id", "source", "text"), budget=1.0, entropy=0.97)
