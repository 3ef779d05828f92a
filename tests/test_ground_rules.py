"""The shared folder, and the contract without its optional parts."""

import subprocess
import sys
from types import SimpleNamespace

import pytest
from pyspark.sql import functions as F

from evenpart.operators.joins import spread_groups, spread_lookup
from evenpart.plans import scratch


def test_no_local_folder_on_a_cluster():
    held = SimpleNamespace(isDefined=lambda: False)
    context = SimpleNamespace(master="spark://host:7077", _jsc=SimpleNamespace(sc=lambda: SimpleNamespace(getCheckpointDir=lambda: held)))
    spark = SimpleNamespace(conf=SimpleNamespace(get=lambda name, default: default), sparkContext=context)
    with pytest.raises(ValueError, match="spark.checkpoint.dir"):
        scratch.shared_dir(spark)


def test_contract_without_optional_libraries():
    code = "import sys; sys.modules['regex'] = None; sys.modules['tokenizers'] = None; sys.modules['evenpart.llm.license_scan'] = None\nimport __spark_entry__ as e\nassert len(e.queries()) > 100 and not [q for q in e.queries() if q.startswith('op')] and 'pipeline' not in e.oracle_sql()"
    # the optional parts may also be there and whole: then only the names differ
    subprocess.run([sys.executable, "-c", code], check=True)


def test_spread_keeps_hot_keys_whole(spark):
    rows = spark.range(500).select("id", F.when(F.col("id") < 300, 7).otherwise(F.col("id") % 5).alias("k"))
    table = spark.createDataFrame([(k, f"n{k}") for k in (0, 1, 2, 7)], "k long, name string")
    got = {(r.id, r.k, r.name) for r in spread_lookup(rows, table, ["k"], ["id"], 8).collect()}
    assert got == {(i, k, f"n{k}") for i in range(500) for k in [7 if i < 300 else i % 5] if k in (0, 1, 2, 7)}
    sums = {"n": (F.count("*"), F.sum("n")), "least": (F.min("id"), F.min("least"))}
    got = {(r.id, r.n, r.least) for r in spread_groups(rows, ["k"], ["id"], sums, 8).collect()}
    groups: dict = {}
    for i in range(500):
        groups.setdefault(7 if i < 300 else i % 5, []).append(i)
    assert got == {(i, len(g), min(g)) for g in groups.values() for i in g}
