"""Every core query with an SQL twin, on the smallest tables."""

import pytest
from compare import SF_SMOKE, differences, duck

from shardgraph.catalog import CORE

# experiments build many graphs; bench.py and the driver run them
NAMES = sorted(n for n, e in CORE.items() if e.sql)


@pytest.fixture(scope="module")
def con():
    return duck(SF_SMOKE)


@pytest.mark.parametrize("name", NAMES)
def test_matches_twin(spark, con, name):
    assert differences(CORE[name].run(spark, SF_SMOKE), CORE[name].sql, con) is None


def test_entry_and_catalog(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    df = e.entry(spark)
    rows = {r.metric: r.value for r in df.collect()}
    assert rows["recall"] >= 0.95
    assert 0 < rows["replicated_share"] < 1
