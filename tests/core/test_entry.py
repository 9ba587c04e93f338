import __spark_entry__ as entry
from gradsift.workloads import catalog


def test_every_oracle_has_a_query_and_names_are_registered():
    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q) and len(catalog.QUERIES) > 90


def test_entry_runs(spark):
    assert entry.entry(spark).count() == 16
