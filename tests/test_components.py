"""Components of random and of long graphs, contracted by joins and settled in a task, against a plain search."""

import numpy as np
import pytest

from evenpart.operators.components import connected_components, further_components, settle


def plain(edges):
    root = {v: v for e in edges for v in e}
    def find(v):
        while root[v] != v:
            v = root[v]
        return v
    for a, b in edges:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    return {v: find(v) for v in root}


def classes(pairs):
    out = {}
    for v, r in pairs:
        out.setdefault(r, set()).add(v)
    return {frozenset(c) for c in out.values()}


def some(seed, n, m):
    rng = np.random.default_rng(seed)
    return [tuple(e) for e in rng.integers(-n, n, (m, 2)).tolist()] + [(1000 + i, 1001 + i) for i in range(60)]


def test_settle_is_the_smallest_vertex():
    edges = some(1, 40, 50)
    v, to = settle(*np.array(edges).T)
    assert dict(zip(v.tolist(), to.tolist(), strict=True)) == plain(edges)


@pytest.mark.parametrize("in_task", [0, 20, 1 << 20])
def test_any_bound_gives_the_same_components(spark, in_task):
    edges = some(2, 60, 70)
    own = {(v, v) for e in edges for v in e if all(a == b for a, b in edges if v in (a, b))}
    got = connected_components(spark.createDataFrame(edges, "a long, b long"), in_task=in_task).collect()
    assert len({r.v for r in got}) == len(got)
    assert classes((r.v, r.root) for r in got) | {frozenset((v,)) for v, _ in own} == classes(plain(edges).items())


@pytest.mark.parametrize("in_task", [0, 1 << 20])
def test_further_edges_join_components(spark, in_task):
    edges = [e for e in some(3, 60, 80) if e[0] != e[1]]
    frame = lambda e: spark.createDataFrame(e, "a long, b long")
    first = connected_components(frame(edges[::2]), in_task=in_task)
    got = further_components(first, frame(edges[1::2]), in_task=in_task).collect()
    assert classes((r.v, r.root) for r in got) == classes(plain(edges).items())


def test_no_edges(spark):
    none = connected_components(spark.createDataFrame([], "a long, b long"))
    assert none.columns == ["v", "root"] and none.count() == 0
    assert further_components(none, spark.createDataFrame([(1, 2)], "a long, b long")).count() == 2
