"""Maximal repeat groups of contexts against a plain search over all lengths."""

import numpy as np
import pytest

from evenpart.llm.suffix_dedup import LEFT, SPAN, later_shifts, lcp_intervals, maximal_repeats, repeats


def contexts(seed, n=60):
    rng = np.random.default_rng(seed)
    rows = rng.integers(0, 2, (n, LEFT + SPAN)).astype(np.uint8)  # zero bytes too, which also pad
    for i in range(1, n):
        j, a, b = rng.integers(0, i), LEFT - rng.integers(0, LEFT + 1), LEFT + rng.integers(10, SPAN + 1)
        rows[i, a:b] = rows[j, a:b]
    left, right = np.where(rng.random(n) < 0.3, rng.integers(0, LEFT, n), LEFT), np.where(rng.random(n) < 0.3, rng.integers(16, SPAN, n), SPAN)
    at = np.arange(LEFT + SPAN)[None, :]
    rows[(at < LEFT - left[:, None]) | (at >= LEFT + right[:, None])] = 0
    return rows, left, right


def classes(rows, left, right, before, after):
    out = {}
    for i in range(len(rows)):
        if left[i] >= before and right[i] >= after:
            out.setdefault(rows[i, LEFT - before : LEFT + after].tobytes(), set()).add(i)
    return {frozenset(c) for c in out.values() if len(c) > 1}


@pytest.mark.parametrize("seed", range(6))
def test_groups_and_marks(seed):
    rows, left, right = contexts(seed)
    want = set()
    for before in range(LEFT + 1):
        for after in range(SPAN - before, SPAN + 1):
            for c in classes(rows, left, right, before, after):
                longer = [(before + 1, after)] * (before < LEFT) + [(before, after + 1)] * (after < SPAN)
                if not any(c in classes(rows, left, right, *x) for x in longer):
                    want.add((c, before, after))
    got = []
    for entry, count, before, after in maximal_repeats(rows, left, right):
        at = 0
        for n, x, y in zip(count.tolist(), before.tolist(), after.tolist(), strict=True):
            got.append((frozenset(entry[at : at + n].tolist()), x, y))
            at += n
    assert len(got) == len(set(got)) and set(got) == want and want
    key = np.random.default_rng(seed).integers(0, 20, len(rows))
    low, high = later_shifts(rows, key, left, right)
    shifts = [[t for t in range(LEFT + 1) if any(i in c and key[i] > min(key[list(c)]) for c in classes(rows, left, right, t, SPAN - t))] for i in range(len(rows))]
    assert [(s[0], s[-1]) if s else (-1, -1) for s in shifts] == list(zip(low.tolist(), high.tolist(), strict=True))


def test_intervals_nest():
    found = sorted(zip(*(x.tolist() for x in lcp_intervals(np.array([0, 2, 3, 3, 1, 0, 4]), 1)), strict=True))
    assert found == [(1, 0, 5), (2, 0, 4), (3, 1, 4), (4, 5, 7)]


@pytest.mark.parametrize("hot", [20_000, 3])
def test_repeats_hold_all_occurrences(spark, hot):
    """Every occurrence of a group has its bytes, and no other place has; together they cover all strings that two documents share."""
    rng = np.random.default_rng(5)
    words = ["".join(rng.choice(list("abcdefgh "), 70)) for _ in range(4)]
    texts = {i: " ".join(rng.choice(words, rng.integers(1, 4))) + "".join(rng.choice(list("xyz"), rng.integers(0, 30))) for i in range(30)} | {40: "", 41: "wörd " + words[0]}
    docs = spark.createDataFrame([*texts.items(), (42, None)], "doc_id long, text string")
    raw = {i: t.encode() for i, t in texts.items()}
    groups, covered = {}, set()
    for r in repeats(docs, hot=hot).collect():
        groups.setdefault(r["repeat"], set()).add((r.doc_id, r.start, r.stop))
        covered |= {(r.doc_id, x) for x in range(r.start, r.stop - SPAN + 1)}
    for places in groups.values():
        (bytes_,) = {raw[d][a:b] for d, a, b in places}
        assert len(bytes_) >= SPAN and len(places) > 1
        assert places == {(d, a, a + len(bytes_)) for d, t in raw.items() for a in range(len(t)) if t.startswith(bytes_, a)}
    held: dict = {}
    for d, t in raw.items():
        for a in range(len(t) - SPAN + 1):
            held.setdefault(t[a : a + SPAN], set()).add((d, a))
    assert covered >= {p for places in held.values() if len({d for d, _ in places}) > 1 for p in places} and covered
