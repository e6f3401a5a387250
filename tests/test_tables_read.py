"""Queries that once made their data up read a given table."""

import pytest

from regioncount.plans import registry


@pytest.mark.parametrize("name", "bounds_table constraints_n20 lattice_n20 ledger_compose release_card sensitivity_table w16_worked_example workload_positions".split())
def test_needs_its_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        registry.queries()[name](spark, str(tmp_path)).count()
