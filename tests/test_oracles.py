"""Every registered query that has an oracle equals it on the smoke tables; the others run."""

import pytest
from oracle import compare, connect

from corpuskit import registry

QUERIES, ORACLES = registry.queries(), registry.oracle_sql()


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, sf_dir, name):
    df = QUERIES[name](spark, sf_dir)
    if name in ORACLES:
        assert compare(df, connect(sf_dir), ORACLES[name]) is None
    else:
        assert df.columns and df.limit(5).collect() is not None
