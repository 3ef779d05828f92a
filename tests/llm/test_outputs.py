"""Operators give their product, not digests only."""

import numpy as np

from evenpart.llm import packing, suffix_dedup

LINE = "the same fifty bytes and more stand in both of these two texts. "


def test_repeats_give_text_and_spans(spark):
    docs = spark.createDataFrame([(1, "a " + LINE), (2, "wörd " + LINE + "tail"), (3, None)], "doc_id long, text string")
    got = {r.doc_id: (bytes(r.kept), [tuple(s) for s in r.spans]) for r in suffix_dedup.cleaned(docs).collect()}
    raw = ("wörd " + LINE + "tail").encode()
    (lo, hi), = got[2][1]
    assert got[1] == (("a " + LINE).encode(), []) and got[3] == (b"", [])
    assert raw[lo:hi].decode() == " " + LINE and got[2][0] == raw[:lo] + raw[hi:]


def test_packing_gives_ids(spark):
    docs = spark.createDataFrame([(1, LINE * 300), (2, ""), (3, "a b")], "doc_id long, text string").coalesce(1)
    path = packing.vocabulary_path()
    pieces: dict = {}
    for r in packing.pack(docs, path).collect():
        assert len(r.ids) == r.length
        pieces.setdefault(r.doc_id, []).append((r.start, r.ids))
    encode = packing.encoder(path)
    for i, t in ((1, LINE * 300), (2, ""), (3, "a b")):
        whole = np.frombuffer(encode([t])[0], dtype="<u4").tolist() + [packing.END_ID]
        assert [x for _, ids in sorted(pieces[i]) for x in ids] == whole
