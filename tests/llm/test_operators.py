"""The training-data operators against brute force, on hostile small tables."""

import hashlib
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from evenpart.llm import document_fingerprints, exact_dedup, license_scan, mixing, packing, pii_surrogates, simhash, suffix_dedup, toxicity, url_filters
from evenpart.llm.queries import ORACLES, QUERIES
from tests.conftest import SF
from tests.test_oracles import rows

LONG = "the quick brown fox jumps over the lazy dog and goes on its way to the river. "
TEXTS = [
    (1, LONG * 3), (2, LONG * 3), (3, " " + LONG * 3), (4, "x" + LONG * 2 + "y" * 60), (5, ""), (6, None), (7, "   \n"), (8, "Under the\tMIT-License; cc by nc"), (9, "é" * 80), (10, "a" + "é" * 80),
    (11, "mail ann.b7@corp.example.org or +1 (743) 555-3824"), (12, "z" * 500), (12, "z" * 500), (13, "Released under the MIT Licence."), (14, "wörd ÄB " * 700),
]


@pytest.fixture(scope="module")
def docs(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("d") / "documents.parquet")
    spark.createDataFrame([(i, t, "en", None if i == 4 else f"s{i % 2}", len(t or ""), "more") for i, t in TEXTS], "doc_id long, text string, lang string, source string, n_chars long, kept string").write.parquet(path)
    return spark.read.parquet(path)


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("doc_id < 0")


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_sql(spark, duck, name):
    got, want = QUERIES[name](spark, SF), duck.execute(ORACLES[name])
    assert rows(got.columns, got.collect()) == rows([d[0] for d in want.description], want.fetchall())


def test_urls(spark):
    urls = spark.createDataFrame([(1, None), (2, "no scheme"), (3, "http://A.Example.ORG/en/12?x"), (4, "https://org"), (5, "ftp://b.com/de/"), (6, "x://y.net/ads/1")], "page_id long, url string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filters.judge(urls, url_filters.default_rules()).collect()}
    assert got == {1: ("", "", None, "allow"), 2: ("", "", None, "allow"), 3: ("a.example.org", "/en/12", "example.org/en/1", "block"), 4: ("org", "", None, "allow"), 5: ("b.com", "/de/", "com/de/", "block"), 6: ("y.net", "/ads/1", None, "block")}


def test_exact_groups_survive_a_weak_hash(docs):
    weak = lambda c: F.pmod(F.xxhash64(c), F.lit(3))
    want: dict = {}
    strip = str.maketrans("", "", " \t\n\v\f\r")
    for i, t in TEXTS:
        want.setdefault((t or "").translate(strip), []).append((-len(t or ""), i))
    for options in ({}, {"block_chars": 7, "hashed": weak}):
        got = {(r.doc_id, r.keep_id, r.group_size) for r in exact_dedup.duplicate_groups(docs, **options).collect()}
        assert got == {(i, min(g)[1], len(g)) for g in want.values() for _, i in g}


def test_simhash(docs):
    def one(t):
        w = (t or "").encode().lower().split()
        s = [b" ".join(w[i : i + 4]) for i in range(max(1, len(w) - 3))] if w else []
        h = [xxhash.xxh64_intdigest(x, 42) for x in s]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    fps = {i: one(t) for i, t in TEXTS}
    comp = {i: i for i in fps}
    for _ in fps:
        for i in fps:
            for j in fps:
                if (fps[i] ^ fps[j]).bit_count() <= 4:
                    comp[i] = comp[j] = min(comp[i], comp[j])
    assert {(r.doc_id, r.fingerprint, r.component_id) for r in simhash.near_duplicates(docs).collect()} == {(i, f"{f:016x}", comp[i]) for i, f in fps.items()}


@pytest.mark.parametrize("bucket", [4096, 3])
def test_links_of_hot_buckets(spark, bucket):
    rng = np.random.default_rng(0)
    base = rng.integers(0, 2**63, 3)
    fps = sorted({int(b) ^ int(sum(1 << int(x) for x in rng.choice(62, 2, replace=False))) for b in base for _ in range(25)})
    got = {(r.a, r.b) for r in simhash.links(spark.createDataFrame([(f,) for f in fps], "fp long"), bucket).collect()}
    root = {f: f for f in fps}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in got:
        assert (a ^ b).bit_count() <= 4
        root[find(a)] = find(b)
    for a in fps:
        for b in fps:
            if (a ^ b).bit_count() <= 4:
                assert find(a) == find(b)


def test_mix_meets_its_budget(docs, spark):
    many = spark.range(3000).select(F.col("id").alias("doc_id"), F.lit("a b c d").alias("text"), F.when(F.col("id") < 2000, "big").otherwise(F.concat(F.lit("s"), (F.col("id") % 4).cast("string"))).alias("source"))
    for options, most in (({"entropy": 0.97}, 3), ({"repeats": 1.5}, 2)):
        got = mixing.mix(many, budget=1.0, **options).groupBy("source").agg(F.sum(F.col("tokens") * F.col("copies")).alias("n"), F.max("weight").alias("w"), F.max("copies").alias("c")).collect()
        assert abs(sum(r.w for r in got) - 1) < 1e-9 and max(r.c for r in got) <= most + 1
        for r in got:
            assert abs(r.n - r.w * 12000) <= 4
    h = [r.w for r in mixing.mix(many, entropy=0.97).groupBy("source").agg(F.max("weight").alias("w")).collect()]
    assert -sum(w * np.log(w) for w in h) == pytest.approx(0.97 * np.log(5), abs=1e-6)
    assert mixing.mix(docs, entropy=0.9).count() == len(TEXTS)


def test_licences():
    n, base, first, last, b, labels, score, _ = license_scan.scan("Under the\tMIT-License; cc by nc")
    assert (n, base, first, last, b) == (7, 2, 0, 4, "cc-by-nc,mit") and score == 1
    fuzzy = license_scan.scan("Released under the MIT Licence.")
    assert fuzzy[1] == 0 and fuzzy[5] == "mit" and 0 < fuzzy[6] < 1
    assert license_scan.scan(None)[:4] == (0, 0, None, None)


def test_surrogates(docs, spark):
    r = pii_surrogates.replace_entities(docs, "k").where("doc_id = 11").first()
    assert r.entity_kinds == "email,phone" and "corp.example.org" not in r.text and "(743)" not in r.text and r.kept == "more"
    table = spark.createDataFrame([(i, f"ip 10.0.0.{i} and 10.0.0.{(i + 1) % 200}") for i in range(200)], "doc_id long, text string")
    few = lambda kind, canon, attempt, key: F.concat(F.lit("250.0.0."), F.pmod(F.xxhash64(canon, attempt), F.lit(256)).cast("string"))
    got = pii_surrogates.attempts(table, "k", maker=few).withColumn("m", few(F.col("kind"), F.col("canon"), F.col("attempt"), "k"))
    assert got.select("m").distinct().count() == 200
    texts = [x.text.split() for x in pii_surrogates.replace_entities(table, "k", maker=few).orderBy("doc_id").collect()]
    assert all(texts[i][3] == texts[(i + 1) % 200][1] for i in range(200)) and len({t[1] for t in texts}) == 200


@pytest.mark.parametrize("options", [{}, {"hot": 0}, {"group_bytes": 700}])
def test_repeats(docs, options):
    first: dict = {}
    table = sorted((i, (t or "").encode()) for i, t in TEXTS)
    for i, b in table:
        for k in range(len(b) - 49):
            first.setdefault(b[k : k + 50], i)
    want = []
    for i, b in table:
        m = bytearray(len(b))
        for k in range(len(b) - 49):
            if first[b[k : k + 50]] < i:
                m[k : k + 50] = b"\1" * 50
        want.append((i, len(b), sum(m), sum(1 for k in range(len(m)) if m[k] and not (k and m[k - 1])), hashlib.sha256(bytes(x for x, y in zip(b, m, strict=True) if not y)).hexdigest()))
    assert sorted(map(tuple, suffix_dedup.remove_repeats(docs, **options).collect())) == sorted(want)


def test_fingerprints(docs):
    got = document_fingerprints.fingerprints(docs, rows_per_bucket=4).collect()
    order = sorted(((i, t or "") for i, t in TEXTS))
    want = []
    for (i, t), (_, n) in zip(order, order[1:] + order[:1], strict=True):
        q = len(t) // 4
        want.append((i, len(t), hashlib.sha256((t[: len(t) - q] + n[:q]).encode()).hexdigest()))
    assert sorted((r.doc_id, r.n_chars, r.edited_sha256) for r in got) == sorted(want)
    by = {r.doc_id: r.fingerprint for r in got}
    assert by[1] == by[2] == by[3] and by[5] == by[6] == by[7] != by[1] and all(0 <= r.near_edited <= 1 for r in got)


def test_packing(docs):
    encode = packing.encoder(packing.vocabulary_path())
    ids = {i: encode([t])[0] + b"\1\0\0\0" for i, t in TEXTS}
    for i, t in TEXTS:
        whole = encode.tokenizer.encode(t or "", add_special_tokens=False).ids
        assert ids[i][:-4] == np.array(whole, dtype="<u4").tobytes()
    got = packing.pack(docs, packing.vocabulary_path()).collect()
    assert sum(r.length for r in got) == sum(len(ids[i]) // 4 for i, _ in TEXTS)
    for r in got:
        assert zlib.crc32(ids[r.doc_id][4 * r.start : 4 * (r.start + r.length)]) == r.ids_crc32
    sequences: dict = {}
    for r in got:
        sequences.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for s in sequences.values():
        at = 0
        for o, n in sorted(s):
            assert o == at
            at += n
        assert at <= 2048


def test_toxicity():
    rng = np.random.default_rng(3)
    words = [f"w{i}" for i in range(200)]
    make = lambda bad: ". ".join(" ".join(rng.choice(words, 8)) + (" vile scum" if bad and s == 1 else "") for s in range(3))
    data = [(make(i % 5 == 0), int(i % 5 == 0)) for i in range(400)]
    model = toxicity.fit(data[:300])
    assert all((model.score(t)[0] >= 0.5) == bool(y) for t, y in data[300:])
    text = "All good. You vile scum! Bye."
    _, a, b, _ = model.score(text)
    assert text[a:b].strip() == "You vile scum"
    assert toxicity.fit([]).score("x")[0] < 0.5 and model.score(None)[0] < 0.5


def test_empty_tables(empty):
    for made in (exact_dedup.duplicate_groups(empty), simhash.near_duplicates(empty), mixing.mix(empty, entropy=0.9), license_scan.scan_licenses(empty), pii_surrogates.replace_entities(empty, "k"), suffix_dedup.remove_repeats(empty), document_fingerprints.fingerprints(empty), packing.pack(empty, packing.vocabulary_path()), toxicity.score(empty, toxicity.Model())):
        assert made.count() == 0
