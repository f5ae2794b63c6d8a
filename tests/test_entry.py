import __spark_entry__ as entry


def test_queries_and_oracles_have_the_same_names():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry_runs(spark):
    assert entry.entry(spark).count() > 0
