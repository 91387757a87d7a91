"""The driver's contract."""

import __spark_entry__ as entry


def test_entry_and_registry(spark):
    assert entry.entry(spark).count() > 0
    queries, oracles = entry.queries(), entry.oracle_sql()
    assert set(oracles) <= set(queries) and len(queries) > 160 and all(callable(q) for q in queries.values())
    assert all(isinstance(s, str) and "SELECT" in s for s in oracles.values())
