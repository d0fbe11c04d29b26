from __future__ import annotations

import pytest

import __spark_entry__
from regpath.plans import entries

NAMES = list(entries.QUERIES)


@pytest.mark.parametrize("name", NAMES)
def test_query_against_sql(spark, sf, duck, same_rows, name):
    df = entries.QUERIES[name](spark, sf)
    if name in entries.ORACLES:
        same_rows(df, duck, entries.ORACLES[name])
    else:
        assert df.count() > 0


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() == 21
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
    assert set(entries.QUERIES) <= set(__spark_entry__.queries())


#: Queries on structure whose forms are read from line items.
STRUCTURE = ["cyclic_rejected", "decomposition_table", "elimination_trace", "join_tree_table", "width_table"]


@pytest.mark.parametrize("name", STRUCTURE)
def test_structure_reads_a_table(spark, sf, name):
    df = entries.QUERIES[name](spark, sf)
    assert [f for f in df.inputFiles() if "lineitem" in f]
    orders = spark.read.parquet(f"{sf}/lineitem.parquet").select("l_orderkey").distinct().count()
    assert 0 < df.select("lines", "orders").distinct().agg({"orders": "sum"}).first()[0] <= orders
