"""Every query with a twin gives the twin's rows on the smallest tables."""

import pytest

import __spark_entry__ as entry
from run_query import compare


@pytest.mark.parametrize("name", [n for n in entry.oracle_sql() if not n.startswith(("op", "pipeline"))])
def test_twin(spark, name):
    _, said = compare(spark, name, "/root/testdata/sf0.001")
    assert ": same" in said, said


def test_every_twin_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry_runs(spark):
    assert entry.entry(spark).count() == 1
