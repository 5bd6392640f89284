import __spark_entry__ as entry


def test_registry_has_sql_only_for_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.queries()) > 80
