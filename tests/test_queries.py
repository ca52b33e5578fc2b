"""Every registered query against its SQL; those without SQL give rows with a stable schema."""

import pytest
from conftest import DATA, same_rows

from orthant import workloads

SMALL = f"{DATA}/sf0.001"


@pytest.mark.parametrize("name", sorted(workloads.oracle_sql()))
def test_equals_sql(spark, name):
    assert same_rows(workloads.queries()[name](spark, SMALL), workloads.oracle_sql()[name], SMALL)


@pytest.mark.parametrize("name", sorted(set(workloads.queries()) - set(workloads.oracle_sql())))
def test_runs(spark, name):
    df = workloads.queries()[name](spark, SMALL)
    assert df.count() > 0 and len(set(df.columns)) == len(df.columns)
