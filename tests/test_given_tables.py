"""Queries that once made their data up follow the given tables."""

import pytest
from pyspark.sql import functions as F

from evenpart.queries import collected
from tests.conftest import SF

QUERIES, _ = collected()


@pytest.mark.parametrize("name, table, column", [("graph_planted", "lineitem", "l_partkey"), ("theory_table", "lineitem", "l_quantity"), ("loop_sizes", "orders", "o_custkey"), ("cte_recursive", "orders", "o_custkey"), ("io_planted_source", "lineitem", "l_partkey")])
def test_rows_follow_the_table(spark, tmp_path, name, table, column):
    spark.read.parquet(f"{SF}/{table}.parquet").where(F.col(column) <= 20).write.parquet(f"{tmp_path}/{table}.parquet")
    some, all_ = ({tuple(r) for r in QUERIES[name](spark, path).collect()} for path in (str(tmp_path), SF))
    assert some != all_


@pytest.mark.parametrize("name, rows", [("check_exhaustive_small", 1), ("refine_full_toy", 64), ("loop_full_toy", 1)])
def test_folded_graphs(spark, name, rows):
    from evenpart.queries.methods import _folded

    orders = [(r.o_custkey, r.o_orderkey) for r in spark.read.parquet(f"{SF}/orders.parquet").select("o_custkey", "o_orderkey").collect()]
    n = 16 if name == "check_exhaustive_small" else 64
    met: dict = {}
    for a, b in ((c % n, o % n) for c, o in orders):
        if a != b:
            met[min(a, b), max(a, b)] = met.get((min(a, b), max(a, b)), 0) + 1
    mean = sum(met.values()) / len(met)
    assert {(r.src, r.dst) for r in _folded(spark, SF, n)[1].collect()} == {p for p, c in met.items() if c >= mean}
    assert QUERIES[name](spark, SF).count() == rows
