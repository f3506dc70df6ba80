"""Every registered query with SQL gives the rows of its SQL."""

import pytest

from pairbundle.operators import relational
from pairbundle.plans import variants, workloads  # noqa: F401  (variants register with workloads)

QUERIES, ORACLES = workloads.QUERIES | relational.QUERIES, workloads.ORACLES | relational.ORACLES


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_sql(spark, small, duck, name):
    got = QUERIES[name](spark, small)
    names = sorted(got.columns)
    result = duck.execute(ORACLES[name])
    columns = [d[0] for d in result.description]
    assert sorted(columns) == names
    want = sorted(repr(tuple(r[columns.index(n)] for n in names)) for r in result.fetchall())
    assert sorted(repr(tuple(r)) for r in got.select(*names).collect()) == want


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES)))
def test_runs(spark, small, name):
    assert QUERIES[name](spark, small).count() > 0


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
