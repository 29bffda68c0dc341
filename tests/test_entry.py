import __spark_entry__ as entry


def test_keys():
    q, s = entry.queries(), entry.oracle_sql()
    assert set(s) <= set(q)
