"""Every query of the catalogue against its independent SQL."""

import pytest
from rowcheck import same_rows

import __spark_entry__ as entry
from dedupflow.plans import catalog


def test_every_query_has_sql():
    assert set(catalog.QUERIES) == set(catalog.ORACLE_SQL)


@pytest.mark.parametrize("name", sorted(catalog.QUERIES))
def test_query_equals_sql(name, spark, sf, duck):
    assert same_rows(catalog.QUERIES[name](spark, sf), duck, catalog.ORACLE_SQL[name]) > 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0
    assert set(catalog.QUERIES) <= set(entry.queries())


@pytest.mark.parametrize("name", ["q42c_exp6_scaling", "q67_no_private_columns", "q68_fleet"])
def test_query_reads_a_given_table(name, spark, sf):
    assert any(f.endswith(".parquet") and "testdata" in f for f in catalog.QUERIES[name](spark, sf).inputFiles())
