import duckdb
import pytest

from relstrata.llm import registry

from ..test_oracles import same, views


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_sql(name, spark, sf):
    con = duckdb.connect()
    views(con, sf)
    assert same(registry.queries()[name](spark, sf).toPandas(), con.sql(registry.oracle_sql()[name]).df())


def test_every_operator_is_registered():
    import __spark_entry__

    names = __spark_entry__.queries()
    assert "pipeline" in names and set(registry.queries()) <= set(names)
    assert all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11))
