"""Every tier is packed into windows of its own size."""

from collections import Counter

import numpy as np

from evenpart.llm.packing import TIERS, Packer


def test_tiers_have_their_own_windows():
    rng = np.random.default_rng(6)
    sizes = [int(n) for n in np.concatenate([rng.integers(1, 257, 1500), rng.integers(257, 513, 800), rng.integers(513, 1025, 300), rng.integers(1025, 2049, 100), [5000]])]
    packer = Packer(0, lot=1000)
    for i, n in enumerate(sizes):
        packer.add(i, np.arange(n, dtype="<u4").tobytes())
    packer.flush(True)
    length, tier, group, pieces = Counter(), {}, {}, {}
    for doc, start, n, _, _, seq, offset, t, g, *_ in packer.drain():
        assert offset == length[seq]
        length[seq] += n
        tier[seq], group[seq] = t, g
        pieces.setdefault(doc, []).append((start, n))
    for i, n in enumerate(sizes):
        ends = [0, *[a + b for a, b in sorted(pieces[i])]]
        assert [a for a, _ in sorted(pieces[i])] == ends[:-1] and ends[-1] == n
    for t in TIERS:
        mine = [length[s] for s in tier if tier[s] == t]
        assert len(mine) >= 50
        # all but the powers of two of the last window are full up to 1/128
        assert sum(n <= t - max(1, t // 128) for n in mine) <= 11
    # a tier's own pieces stay in windows no longer than they need, but for what fills gaps
    assert sum(length[s] for s in tier if tier[s] < 2048) > sum(sizes) / 2
    by = {}
    for s, g in group.items():
        by.setdefault(g, []).append(length[s])
    assert len(by) > 10
