import pytest
from conftest import SF

from ebbset.plans import extended, relational, workloads

QUERIES, ORACLE = workloads.QUERIES | relational.QUERIES | extended.QUERIES, workloads.ORACLE | relational.ORACLE | extended.ORACLE
SLOW = {"similarity_histogram_customer_brands"}


@pytest.mark.parametrize("name", sorted(set(ORACLE) - SLOW))
def test_query_equals_its_sql(spark, duck, name):
    df = QUERIES[name](spark, SF)
    want = duck.sql(ORACLE[name])
    cols = sorted(df.columns)
    assert cols == sorted(want.columns)
    at = [want.columns.index(c) for c in cols]
    got = sorted((tuple(r[c] for c in cols) for r in df.collect()), key=repr)
    assert got == sorted((tuple(r[i] for i in at) for r in want.fetchall()), key=repr)
