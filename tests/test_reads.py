"""Queries that once made their data up read a given table."""

import pytest

from tilewright import queries as q


@pytest.mark.parametrize("name", ["cost_model_sweep", "grid_assign_toy"])
def test_reads_a_table(spark, sf, name):
    assert any(f.endswith("orders.parquet") for f in q.QUERIES[name](spark, sf).inputFiles())
