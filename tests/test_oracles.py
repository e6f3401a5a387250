"""Every query with SQL gives DuckDB's rows."""

import pytest

from regioncount.plans import registry

ORACLES = registry.oracle_sql()


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query(spark, sf_dir, same_rows, name):
    same_rows(registry.queries()[name](spark, sf_dir), ORACLES[name])


@pytest.mark.parametrize("name", sorted(set(registry.queries()) - set(ORACLES)))
def test_runs(spark, sf_dir, name):
    if name.startswith(("w1_", "w2_", "w3_", "w4_", "w5_", "w6_", "w7_", "w8_", "w11", "w12", "w13", "w15")):
        pytest.skip("long; run by bench.py")
    assert registry.queries()[name](spark, sf_dir).count() > 0
