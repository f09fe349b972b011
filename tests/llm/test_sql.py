"""The operators' queries against the SQL of the second engine, value for value."""

import pytest

from tests.conftest import MIDDLE
from tuneloom.llm.queries import ORACLE_SQL, QUERIES


@pytest.mark.parametrize("name", ORACLE_SQL)
def test_query_equals_sql(spark, duck, name):
    df = QUERIES[name](spark, MIDDLE)
    columns = sorted(df.columns)
    got = sorted((tuple(r) for r in df.select(*columns).collect()), key=str)
    want = sorted(duck.execute("SELECT " + ", ".join(f'"{c}"' for c in columns) + f" FROM ({ORACLE_SQL[name]})").fetchall(), key=str)
    assert got == want
