import __spark_entry__ as contract


def test_contract(spark):
    names, sql = contract.queries(), contract.oracle_sql()
    assert set(sql) <= set(names) and len(names) > 80
    assert contract.entry(spark).count() == 3
