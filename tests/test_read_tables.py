"""Queries that made their numbers up read a given table in Spark's tasks."""

import pytest
from lexfold.plans import catalog


@pytest.mark.parametrize("name", ["break_even_table", "join_theta_break_even"])
def test_reads_documents(spark, sf, name):
    assert any("documents" in f for f in catalog.QUERIES[name](spark, sf).inputFiles())
