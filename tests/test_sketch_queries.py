"""Every query against its SQL, or for its rows, on the smallest tables."""

import pytest

from floorcount.plans import registry

TABLES = "/root/testdata/sf0.001"
SQL = registry.oracle_sql()


@pytest.mark.parametrize("name", sorted(SQL))
def test_equals_sql(name, compare):
    compare(registry.queries()[name], SQL[name], TABLES)


@pytest.mark.parametrize("name", sorted(set(registry.queries()) - set(SQL)))
def test_has_rows(name, spark):
    assert registry.queries()[name](spark, TABLES).limit(1).count() == 1


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 3
    assert set(registry.queries()) <= set(__spark_entry__.queries())


#: Queries that once made their data up.
MOVED = ["averaging_comparison", "bias_curves", "cf_curve", "cf_fold", "cf_range_lookup", "history_ablation", "laws", "memory_grid", "memory_table", "memory_variance", "merge_study", "simulate_skewed"]


@pytest.mark.parametrize("name", MOVED)
def test_reads_a_table(name, spark):
    assert registry.queries()[name](spark, TABLES).inputFiles()
