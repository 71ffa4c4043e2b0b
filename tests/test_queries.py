"""Every query with SQL, side by side at the smallest size."""

import pytest
from compare import same
from geocensus.plans import relational, workloads
from geocensus.streaming import operators

QUERIES = {**workloads.queries(), **relational.queries(), **operators.queries()}
SQL = {**workloads.oracle_sql(), **relational.oracle_sql(), **operators.oracle_sql()}


@pytest.mark.parametrize("name", sorted(SQL))
def test_same_rows(spark, duck, sf, name):
    assert same(QUERIES[name](spark, sf).toPandas(), duck.execute(SQL[name]).df()).startswith("ok")


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(SQL)))
def test_runs(spark, sf, name):
    assert QUERIES[name](spark, sf).count() >= 0


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 4
