"""Every query of the engine with a DuckDB statement gives the same rows as the statement."""

import pytest

from evenpart.queries import collected
from tests.conftest import SF

QUERIES, ORACLES = collected()


def rows(names, data):
    return sorted(tuple((f"{v:.6g}" if isinstance(v, float) else str(v)) for _, v in sorted(zip(names, r, strict=True))) for r in data)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_same_rows(spark, duck, name):
    got = QUERIES[name](spark, SF)
    want = duck.execute(ORACLES[name])
    names = [d[0] for d in want.description]
    assert sorted(names) == sorted(got.columns)
    number = lambda v: float(v) if isinstance(v, (int, float)) and not isinstance(v, bool) else v
    assert rows(got.columns, [map(number, r) for r in got.collect()]) == rows(names, [map(number, r) for r in want.fetchall()])
