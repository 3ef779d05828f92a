"""Each stage of the pipeline against a brute-force version on a small hostile table."""

import numpy as np
import pytest

import corpus_pipeline
from evenpart.llm import packing, simhash, toxicity

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long, kept string"
SPACE = str.maketrans("", "", " \t\n\v\f\r")


def _rows():
    rng = np.random.default_rng(7)
    words = [f"w{i}" for i in range(300)]
    make = lambda n: " ".join(rng.choice(words, n))
    texts = [make(60) + (". you vile scum" if i % 5 == 0 else "") for i in range(120)]
    texts += [texts[1], " " + texts[1], texts[2].replace("w", "w", 1) + " ", None, "", make(4000), texts[3][:-3] + "w1"]
    rows = [(i, t, None if i == 7 else "en", None if i % 11 == 0 else f"s{i % 3 and 1}", None if i == 9 else len(t or ""), "more") for i, t in enumerate(texts)]
    return [*rows, (None, make(50), None, None, None, None)]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("p"))
    rows = _rows()
    spark.createDataFrame(rows, COLUMNS).repartition(3).write.parquet(f"{path}/documents.parquet")
    labels = [(r[0], 0, None if r[0] == 8 else int("vile" in (r[1] or ""))) for r in rows if r[0] is not None] + [(None, 1, 1)]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    return path


def test_stages(spark, folder):
    docs = spark.createDataFrame(_rows(), COLUMNS)
    stages, before = dict(corpus_pipeline.STAGES), [tuple(r) for r in docs.collect()]
    assert list(stages) == ["toxicity", "exact_dedup", "simhash", "mixing", "packing"]

    clean = stages["toxicity"](spark, docs, folder)
    left = [tuple(r) for r in clean.collect()]
    gone = {r for r in before if r not in left}
    assert clean.columns == docs.columns and {r[0] for r in gone} == {i for i in range(120) if i % 5 == 0}

    first = stages["exact_dedup"](spark, clean, folder)
    best: dict = {}
    for r in left:
        key = (r[1] or "").translate(SPACE)
        best[key] = min(best.get(key, (1, 0, None)), (-len(r[1] or ""), -1 if r[0] is None else r[0], r), key=lambda v: v[:2])
    kept = [tuple(r) for r in first.collect()]
    assert sorted(map(str, kept)) == sorted(str(v[2]) for v in best.values()) and first.columns == docs.columns

    near = stages["simhash"](spark, first, folder)
    bits = {r.doc_id: int(r.fingerprint, 16) for r in simhash.near_duplicates(first).collect()}
    at = {i: i for i in bits}
    order = sorted(bits, key=lambda i: -1 if i is None else i)
    for _ in order:  # smallest reachable id, by plain spreading
        for i in order:
            for j in order:
                if bin(bits[i] ^ bits[j]).count("1") <= 4:
                    at[i] = at[j] = min(at[i], at[j], key=lambda v: -1 if v is None else v)
    single = [tuple(r) for r in near.collect()]
    assert sorted(map(str, single)) == sorted(str(r) for r in kept if at[r[0]] == r[0]) and near.columns == docs.columns

    mixed = stages["mixing"](spark, near, folder)
    drawn = [tuple(r) for r in mixed.collect()]
    assert mixed.columns == docs.columns and len(set(drawn)) == len(drawn) and set(drawn) <= set(single) and len(drawn) >= 0.6 * len(single)

    encode = packing.encoder(packing.vocabulary_path())
    size = {r[0]: len(encode.tokenizer.encode(r[1] or "", add_special_tokens=False).ids) + 1 for r in drawn}
    pieces: dict = {}
    for r in stages["packing"](spark, mixed, folder).collect():
        pieces.setdefault(r.doc_id, []).append((r.start, r.length))
    assert pieces.keys() == size.keys()
    for i, n in size.items():
        ends = [0, *[a + b for a, b in sorted(pieces[i])]]
        assert [a for a, _ in sorted(pieces[i])] == ends[:-1] and ends[-1] == n


def test_run_and_empty(spark, folder, tmp_path):
    ids = {r.doc_id for r in corpus_pipeline.run(spark, folder).collect()}
    assert 0 not in ids and len(ids) > 40
    for name in ("documents", "labels"):
        spark.read.parquet(f"{folder}/{name}.parquet").where("doc_id < 0").write.parquet(f"{tmp_path}/{name}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
    assert toxicity.fit([]).score("")[0] < 0.5
