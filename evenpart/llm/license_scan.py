"""Operator 5: licence notices, exact and with a few errors.

A text is reduced to its words (A-Z lower-cased), single-spaced.  A notice of n letters is allowed ``n // 10`` errors,
3 at most; it is split into one more piece than that, so that by the pigeonhole principle at least one piece stands
unchanged in every match.  Exact search for the pieces gives candidate windows, and only there the ``regex`` library's
bounded-error matching verifies the edits and reports the span.  Base phrases are counted at every place.

Creative Commons notices are read on over the words that follow, so that one with "nc", "nd" or "sa" behind it is labelled
as such and not as plain attribution.

One pass over the texts in Arrow batches, no shuffle; a text costs time in proportion to its length and its hits.
Defined results: null text is empty; a text without words has n_words 0 and no labels; a text of any length is scanned
whole; of matches of one notice that overlap the leftmost counts; repeated rows are scanned alike; any integer type serves
as doc_id and a null one passes through; an empty table gives no rows; other columns, whatever their names, are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from evenpart.sources.tables import read_table

#: Fixed values of the contract: label by phrase.
BASE = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}
#: The method's own notices.
NOTICES = {
    "under the mit license": "mit",
    "apache license version 2": "apache-2",
    "gnu general public license": "gpl",
    "gnu lesser general public license": "lgpl",
    "mozilla public license": "mpl",
    "licensed under cc by": "cc-by",
    "creative commons attribution": "cc-by",
    "permission is hereby granted free of charge": "mit",
    "redistribution and use in source and binary forms": "bsd",
    "all rights reserved": "all-rights-reserved",
}
#: Words that go on a notice of attribution, and what they add to its label (fixed values).
TERMS = {"nc": "nc", "noncommercial": "nc", "nd": "nd", "noderivatives": "nd", "noderivs": "nd", "sa": "sa", "sharealike": "sa", "non commercial": "nc", "no derivatives": "nd", "share alike": "sa"}
LETTERS_PER_ERROR, MOST_ERRORS = 10, 3

#: Bytes of words stay (A-Z lower-cased), the others become blanks; all bytes of non-ASCII characters are word bytes.
_TABLE = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))
SCHEMA = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, spans array<struct<label:string,first_word:long,last_word:long,errors:int>>"


def errors_allowed(phrase: str) -> int:
    return min(MOST_ERRORS, len(phrase.replace(" ", "")) // LETTERS_PER_ERROR)


class Notice:
    def __init__(self, phrase: str, label: str) -> None:
        self.label, self.size, self.errors = label, len(phrase), errors_allowed(phrase)
        raw, parts = phrase.encode(), self.errors + 1
        cuts = [i * len(raw) // parts for i in range(parts + 1)]
        self.seeds = [(raw[a:b], a) for a, b in zip(cuts, cuts[1:], strict=False)]
        self.pattern = regex.compile(rb"(?b)(?:" + regex.escape(raw, literal_spaces=True) + rb"){e<=%d}" % self.errors)

    def find(self, text: bytes) -> Iterator[tuple[int, int, int]]:
        """(start, end, errors) of matches, left to right."""
        windows = []
        for seed, lead in self.seeds:
            at = text.find(seed)
            while at >= 0:
                windows.append((max(0, at - lead - self.errors), min(len(text), at - lead + self.size + self.errors)))
                at = text.find(seed, at + 1)
        done = 0
        for lo, hi in sorted(windows):
            lo = max(lo, done)
            if hi - lo >= self.size - self.errors and (m := self.pattern.search(text, lo, hi)):
                yield m.start(), m.end(), sum(m.fuzzy_counts)
                done = m.end()


_NOTICES = [Notice(p, x) for p, x in NOTICES.items()]


def scan(text: str | None) -> tuple:
    """The digest of one text, and the spans."""
    body = b" ".join((text or "").encode().translate(_TABLE).split())
    if not body:
        return 0, 0, None, None, "", "", 0.0, []
    padded = b" " + body + b" "
    # the place of each blank: the word of a byte is the number of blanks before it, less one
    blanks = np.flatnonzero(np.frombuffer(padded, np.uint8) == 32)
    word_at = lambda i: int(np.searchsorted(blanks, i, side="right")) - 1
    places, base = [], set()
    for phrase, label in BASE.items():
        raw = f" {phrase} ".encode()
        at = padded.find(raw)
        while at >= 0:
            places.append(word_at(at))
            base.add(label)
            at = padded.find(raw, at + 1)
    spans, labels, best = [], set(base), 1.0 if base else 0.0
    for n in _NOTICES:
        for a, b, e in n.find(body):
            label = n.label + further(body[b : b + 64]) if n.label == "cc-by" else n.label
            spans.append({"label": label, "first_word": word_at(a + 1), "last_word": word_at(b), "errors": e})
            labels.add(label)
            best = max(best, 1 - e / n.size)
    return len(blanks) - 1, len(places), min(places, default=None), max(places, default=None), ",".join(sorted(base)), ",".join(sorted(labels)), best, spans


def further(rest: bytes) -> str:
    """The terms that the words right behind a notice of attribution add, such as ``-nc-sa``."""
    words, out = rest.decode(errors="ignore").split(), []
    while words:
        size = 2 if " ".join(words[:2]) in TERMS else 1
        term = TERMS.get(" ".join(words[:size]))
        if term is None:
            break
        out.append(term)
        words = words[size:]
    return "".join(f"-{t}" for t in sorted(set(out), key=("nc", "nd", "sa").index))


def scan_licenses(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.float64(), pa.list_(pa.struct([("label", pa.string()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("errors", pa.int32())]))]
        names = ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "spans"]
        for batch in batches:
            found = [scan(t.as_py()) for t in batch.column(1)]
            cols = zip(*found, strict=True) if found else [[]] * len(kinds)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, type=k) for c, k in zip(cols, kinds, strict=True))], names=names)

    return docs.select(docs[doc_id].cast("long").alias("doc_id"), docs[text].alias("text")).mapInArrow(run, SCHEMA)


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(read_table(spark, sf_dir, "documents", "doc_id", "text")).drop("spans")
