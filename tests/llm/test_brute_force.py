"""Operators 4, 5, 9 and 10 against plain versions, clashing columns, repeated rows, narrow ids."""

import math
import zlib

import numpy as np
import pytest
import regex
from pyspark.sql import functions as F

from evenpart.llm import exact_dedup, license_scan, mixing, near_copies, packing, pii_surrogates, simhash, toxicity, url_filters


def test_mix_against_a_plain_version(spark):
    rng = np.random.default_rng(2)
    rows = [(int(i), None if i % 17 == 0 else ["a", "b", "c"][int(rng.integers(0, 10) > 5) + int(rng.integers(0, 10) > 8)], " ".join(["w"] * int(rng.integers(0, 9)))) for i in range(600)] + [(600, "b", None), (600, "b", "w w")]
    table = spark.createDataFrame(rows, "doc_id long, source string, text string").repartition(3)
    got = mixing.mix(table, budget=1.3, entropy=0.9, block_rows=20).collect()
    tokens: dict = {}
    for _, s, t in rows:
        tokens[s] = tokens.get(s, 0) + len((t or "").split())
    total = sum(tokens.values())

    def weights(a):
        e = {s: t**a for s, t in tokens.items()}
        return {s: v / sum(e.values()) for s, v in e.items()}

    lo, hi = 0.0, 1.0
    for _ in range(60):
        mid = (lo + hi) / 2
        reach = -sum(w * math.log(w) for w in weights(mid).values()) >= 0.9 * math.log(len(tokens))
        lo, hi = (mid, hi) if reach else (lo, mid)
    want = weights(lo)
    for s in tokens:
        mine = [r for r in got if r.source == s]
        assert len(mine) == sum(x[1] == s for x in rows) and mine[0].weight == pytest.approx(want[s])
        budget, whole = 1.3 * total * want[s], int(1.3 * total * want[s] / tokens[s] + 1e-9)
        left, taken, spent = budget - whole * tokens[s], set(), 0
        # the next permutation: blocks by key, rows by key inside; equal places are taken together
        for place in sorted({(r.block_key, r.row_key) for r in mine}):
            here = [r for r in mine if (r.block_key, r.row_key) == place]
            spent += sum(r.tokens for r in here)
            if spent <= left:
                taken.add(place)
        ends = {p for p in taken}
        for r in mine:
            extra = r.copies - whole
            assert extra in (0, 1) and (r.tokens == 0 or (extra == 1) == ((r.block_key, r.row_key) in ends))


def _slow_scan(text):
    words = regex.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", regex.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    places, base = [], set()
    for phrase, label in license_scan.BASE.items():
        p = phrase.split(" ")
        for i in range(len(words) - len(p) + 1):
            if words[i : i + len(p)] == p:
                places.append(i)
                base.add(label)
    labels, body = set(base), " ".join(words).encode()
    for phrase, label in license_scan.NOTICES.items():
        e = license_scan.errors_allowed(phrase)
        for m in regex.finditer(rb"(?b)(?:" + regex.escape(phrase.encode(), literal_spaces=True) + rb"){e<=%d}" % e, body):
            labels.add(label + (license_scan.further(body[m.end() : m.end() + 64]) if label == "cc-by" else ""))
    return len(words), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(base)), ",".join(sorted(labels))


def test_licences_against_a_plain_version(spark):
    rng = np.random.default_rng(4)
    filler = ["the", "code", "of", "mit", "license", "cc", "by", "nc", "é", "Apache", "x1", "gnu"]
    texts = [None, "", "  ", "licensed under CC BY", "licensed under cc by nc sa 4.0", "Creative Commons Attribution Share Alike", "licensed under cc by-nd", "cc by nc cc by nc", "Released undr the MIT licence", "É under the MIT license"]
    for _ in range(40):
        w = [str(x) for x in rng.choice(filler, 30)]
        for phrase in rng.choice(list(license_scan.NOTICES), 2):
            p = list(str(phrase))
            for _ in range(int(rng.integers(0, 3))):
                p[int(rng.integers(0, len(p)))] = str(rng.choice(list("abc ")))
            w.insert(int(rng.integers(0, len(w))), "".join(p))
        texts.append(str(rng.choice([" ", "\n", "; "])).join(w))
    table = spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string")  # an int id
    got = {r.doc_id: r for r in license_scan.scan_licenses(table).collect()}
    for i, t in enumerate(texts):
        r, want = got[i], _slow_scan(t)
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == want[:5]
        # every label that a search of the whole text finds, and the base ones
        names = lambda x: {y for y in x.split(",") if y}
        assert names(want[5]) | names(r.base_labels) <= names(r.labels), t
    assert got[3].labels == "cc-by" and got[4].labels == "cc-by-nc,cc-by-nc-sa" and got[5].labels == "cc-by-sa" and got[6].labels == "cc-by-nd"


def test_licences_in_a_long_text():
    text = "under the MIT license " * 20_000
    n, base, first, last, *_ = license_scan.scan(text)
    assert (n, base, first, last) == (80_000, 20_000, 0, 79_996)


def test_only_powers_of_two_are_short():
    rng = np.random.default_rng(3)
    for sizes in ([1], [2047], [2048], [2049], [int(x) for x in rng.integers(1, 5000, 200)]):
        packer = packing.Packer(0)
        for i, n in enumerate(sizes):
            packer.add(i, np.arange(n, dtype="<u4").tobytes())
        packer.flush(True)
        length: dict = {}
        for row in packer.drain():
            length[row[5]] = length.get(row[5], 0) + row[2]
        padding = sum(2048 - n for n in length.values() if n & (n - 1))
        assert all(0 < n <= 2048 for n in length.values()) and sum(length.values()) == sum(sizes) and padding <= 0.02 * sum(sizes)


def test_toxicity_sample_and_split(spark):
    rng = np.random.default_rng(6)
    words = [f"w{i}" for i in range(200)]
    texts = [". ".join(" ".join(rng.choice(words, 8)) + (" vile scum" if i % 5 == 0 and s == 1 else "") for s in range(3)) for i in range(400)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string").withColumns({"toxic": F.lit("mine"), "y": F.lit(1), "id": F.lit(2)})
    labels = spark.createDataFrame([(i, int(i % 5 == 0)) for i in range(400)] + [(400, 1), (7, None)], "doc_id long, toxic int")
    held = lambda i: zlib.crc32(str(i).encode()) % 5 == 0
    learned = toxicity.learning_rows(docs, labels)
    assert sorted(learned) == sorted((texts[i], int(i % 5 == 0)) for i in range(400) if not held(i))
    assert len(toxicity.learning_rows(docs, labels, max_rows=50)) <= 50
    got = {r.doc_id: r.score for r in toxicity.score(docs, toxicity.fit(learned)).collect()}
    assert all((got[i] >= 0.5) == (i % 5 == 0) for i in range(400) if held(i)) and any(held(i) for i in range(0, 400, 5))
    kept = toxicity.keep_clean(docs, labels)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {i for i in range(400) if i % 5}


def test_clashing_columns_and_repeated_rows(spark):
    names = ["_kept_id", "_kept_raw", "_row", "_n", "_id", "_source", "_top", "_late", "_done", "host", "path", "rule", "verdict", "pattern", "n_candidates", "entity_kinds", "n_entities", "toxic", "raw", "h", "t", "fp"]
    long = " ".join(f"w{i}" for i in range(40))
    rows = [(1, long, "a"), (1, long, "a"), (1, " " + long, "a"), (2, long + " end", "a"), (3, "alone mr x", None), (3, "another one of that id", None), (None, None, None), (None, "", None)]
    docs = spark.createDataFrame(rows, "doc_id int, text string, source string").withColumns({n: F.lit(n) for n in names})
    first = exact_dedup.keep_first(docs)
    assert first.columns == docs.columns and sorted(str((r.doc_id, (r.text or "").strip())) for r in first.collect()) == sorted(str(x) for x in [(1, long), (2, long + " end"), (3, "alone mr x"), (3, "another one of that id"), (None, "")])
    near = near_copies.keep_representatives(docs)
    assert near.columns == docs.columns and sorted(str(r.doc_id) for r in near.collect()) == ["1", "3", "3", "None"]
    assert sorted(str(r.doc_id) for r in simhash.keep_representatives(docs).collect()) == ["1", "3", "3", "None"]
    assert mixing.realise(docs, budget=1.0, repeats=1.0).columns == docs.columns
    got = pii_surrogates.replace_entities(docs, "k")
    assert got.columns == docs.columns and {r.entity_kinds for r in got.collect()} == {""}
    urls = url_filters.judge(docs.withColumn("url", F.lit("http://a.org/x")), url_filters.default_rules())
    assert {r.host for r in urls.collect()} == {"a.org"} and {r._top for r in urls.collect()} == {"_top"}


def test_rules_beyond_one_plan(spark):
    rules = url_filters.default_rules()
    urls = spark.createDataFrame([(i, u) for i, u in enumerate(["http://a.example.org/en/12", "http://x.com/fr/ads/1", "http://x.net/ads/1", "ftp://b.com/de/", None])], "page_id long, url string")
    one, many = (sorted(map(str, url_filters.judge(urls, rules, plan_rules=n).collect())) for n in (20_000, 3))
    drop = lambda rows: [regex.sub(r"n_candidates=\d+", "", r) for r in rows]
    assert drop(one) == drop(many)
