"""Every registered query of the library against its oracle."""

import pytest
from parity import assert_same

from clipforge import queries

QUERIES, ORACLES = queries.load()


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, sf, duck, name):
    df = QUERIES[name](spark, sf)
    if name in ORACLES:
        assert_same(df, duck, ORACLES[name])
    else:
        df.collect()


def test_every_oracle_has_a_query():
    assert set(ORACLES) <= set(QUERIES)
