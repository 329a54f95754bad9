"""Every registered query with SQL, over the smallest tables."""

import pytest
from pyspark.sql import functions as F

from clustercost import catalog
from tests.compare import connect, rows_of, sql_rows


@pytest.fixture(scope="module")
def tables(sf):
    return connect(sf)


@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_same_rows(spark, sf, tables, name):
    assert rows_of(catalog.QUERIES[name](spark, sf)) == sql_rows(tables, catalog.ORACLES[name])


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) - set(catalog.ORACLES)))
def test_runs(spark, sf, name):
    assert catalog.QUERIES[name](spark, sf).columns


def test_whole_tables_are_read(spark, sf):
    """Set operators, the full join, intervals and exploded arrays hold every row of their tables."""
    count = lambda name: spark.read.parquet(f"{sf}/{name}.parquet").count()
    run = lambda name: catalog.QUERIES[f"op_{name}"](spark, sf)
    assert run("join_full_outer").agg(F.sum("n")).first()[0] == count("customer")
    assert run("set_union_all").count() == count("customer") + count("supplier")
    assert run("arr_explode").select("id").distinct().count() == count("embeddings")
    assert run("join_interval").select("x").distinct().count() == count("embeddings") - 40
