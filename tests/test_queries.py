"""Every registered query against its SQL on the smallest tables; those without SQL give rows."""

import pytest

from compare import connect, difference
from raydescent.plans.catalog import QUERIES
from raydescent.plans.oracles import ORACLES

@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, data, name):
    df = QUERIES[name](spark, data)
    if name in ORACLES:
        assert difference(df, connect(data), ORACLES[name]) == ""
    else:
        assert df.count() > 0
