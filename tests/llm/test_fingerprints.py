"""Order MinHash against a plain version, its likeness, and the successor rule over many ranges."""

import numpy as np
from pyspark.sql import functions as F

from evenpart.llm import document_fingerprints as D

MASK = (1 << 64) - 1


def _spark_hash(spark, rows, columns):
    """xxhash64 of integer columns, by Spark itself."""
    made = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "i int, " + ", ".join(columns))
    names = [c.split(" ")[0] for c in columns]
    return [r.h for r in made.select("i", F.xxhash64(*names).alias("h")).orderBy("i").collect()]


def _plain(spark, text):
    """Components of one text, element by element; hashes come from Spark."""
    words = [w for w in text.split() if w]
    if not words:
        return [""] * D.TUPLES
    wh = _spark_hash(spark, [(w,) for w in words], ["w string"])
    kmers = _spark_hash(spark, [(wh[i], wh[i + 1]) for i in range(len(wh) - 1)], ["a long", "b long"]) if len(wh) > 1 else None
    if kmers is None:  # a null second word is passed over by the hash
        kmers = _spark_hash(spark, [(wh[0],)], ["a long"])
    short = lambda h: (h & MASK) >> (64 - D.HASH_BITS)
    seen, elements = {}, []
    order = sorted(range(len(kmers)), key=lambda i: (short(kmers[i]), i))
    for i in order:
        o = seen[short(kmers[i])] = seen.get(short(kmers[i]), -1) + 1
        elements.append((short(kmers[i]), o, i))
    eh = [short(h) for h in _spark_hash(spark, [(h, o) for h, o, _ in elements], ["a long", "o int"])]
    pool = sorted(zip(eh, [i for _, _, i in elements], strict=True))[: D.POOL]
    flat = _spark_hash(spark, [(h, j) for j in range(D.TUPLES) for h, _ in pool], ["a long", "j int"])
    out = []
    for j in range(D.TUPLES):
        mine = flat[j * len(pool) : (j + 1) * len(pool)]
        best = sorted(range(len(pool)), key=lambda i: (((mine[i] & MASK) >> 8) & ((1 << 58) - 1), i))[:2]
        chosen = sorted((pool[i] for i in best), key=lambda e: (e[1], e[0]))
        out.append(tuple(e[0] for e in chosen))
    two = [t for t in out if len(t) == 2]
    hashed = dict(zip(two, _spark_hash(spark, two, ["a long", "b long"]), strict=True)) if two else {}
    one = [t for t in out if len(t) == 1]
    hashed |= dict(zip(one, _spark_hash(spark, one, ["a long"]), strict=True)) if one else {}
    return [f"{hashed[t] & 0xFFFFFFFF:08x}" for t in out]


def test_components_against_a_plain_version(spark):
    rng = np.random.default_rng(5)
    texts = ["", "one", "one two", "a b a b a b a b", " ".join(f"w{i}" for i in rng.integers(0, 40, 30)), " ".join(f"w{i}" for i in rng.integers(0, 900, 400))]
    table = spark.createDataFrame(list(enumerate(texts)), "i int, t string")
    got = {r.i: r.f.split(",") for r in table.select("i", D.fingerprint(F.col("t")).alias("f")).collect()}
    for i, t in enumerate(texts):
        assert got[i] == _plain(spark, t)


def test_swapped_halves_show_at_every_length(spark):
    rng = np.random.default_rng(8)
    rows = []
    for n in (16, 40, 80, 200, 600, 2000):
        for k in range(20):
            w = [f"x{i}" for i in rng.integers(0, 10**6, n)]
            rows.append((n, " ".join(w), " ".join(w[n // 2 :] + w[: n // 2]), " ".join(w[:-1] + ["end"])))
    made = spark.createDataFrame(rows, "n int, a string, b string, c string").select("n", D.likeness(D.fingerprint(F.col("a")), D.fingerprint(F.col("b"))).alias("swapped"), D.likeness(D.fingerprint(F.col("a")), D.fingerprint(F.col("c"))).alias("near"))
    for r in made.groupBy("n").agg(F.avg("swapped").alias("swapped"), F.avg("near").alias("near")).collect():
        # half of all pairs of elements stand in different halves; more is lost at the seam of short texts
        assert 0.25 < r.swapped < 0.65 and r.near > 0.7, r


def test_likeness(spark):
    pairs = spark.createDataFrame([("a,b,,", "a,c,,"), (",,", ",,"), ("a,b", "a,b"), ("a,", ",")], "x string, y string")
    assert [r.l for r in pairs.select(D.likeness(F.col("x"), F.col("y")).alias("l")).collect()] == [0.5, 1.0, 1.0, 0.0]


def test_successor_over_uneven_ids(spark):
    rng = np.random.default_rng(9)
    ids = [None, None, *range(40), *[int(i) for i in 10**12 + rng.integers(0, 10**6, 60)], *[7] * 20]
    rows = [(i, f"t{n}") for n, i in enumerate(ids)]
    table = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    key = lambda r: (r[0] is not None, r[0] or 0, r[1])
    order = sorted(rows, key=key)
    want = {r[1]: n[1] for r, n in zip(order, order[1:] + order[:1], strict=True)}
    first_level = D.FIRST_LEVEL
    try:
        for level in (4096, 3, 1):  # fewer ranges than steps: both levels are in use
            D.FIRST_LEVEL = level
            for per in (1000, 4):
                got = {r.text: r.following.text for r in D.with_next(table, rows_per_bucket=per).collect()}
                assert got == want
    finally:
        D.FIRST_LEVEL = first_level


def test_no_table_of_texts_is_written(spark, monkeypatch):
    """Texts cross one exchange; what is written for it is a row a step."""
    written = []
    monkeypatch.setattr(D, "cut", lambda df, own=D.cut: written.append(own(df)) or written[-1])
    docs = spark.createDataFrame([(i, f"text {i} of many words") for i in range(64)], "doc_id long, text string")
    got = {r.doc_id: r for r in D.fingerprints(docs, rows_per_bucket=16).collect()}
    assert sum(df.count() for df in written) <= 8
    own = {r.doc_id: r.fp for r in docs.select("doc_id", D.fingerprint(F.col("text")).alias("fp")).collect()}
    assert all(got[i].fingerprint == own[i] for i in range(64))
    both = spark.createDataFrame([(i, own[i], own[(i + 1) % 64]) for i in range(64)], "i int, a string, b string")
    assert all(got[r.i].near_next == r.n for r in both.select("i", D.likeness(F.col("a"), F.col("b")).alias("n")).collect())
