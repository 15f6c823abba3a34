import duckdb
import pytest

from suffix_engine.llm import queries

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", queries.oracle_sql())
def test_sql_gives_the_same_rows(spark, name):
    con = duckdb.connect()
    for table in ("documents", "benchmark", "pages"):
        con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{SF}/{table}.parquet'")
    found = con.execute(queries.oracle_sql()[name])
    columns = [c[0] for c in found.description]
    want = [dict(zip(columns, r, strict=True)) for r in found.fetchall()]
    got = [r.asDict() for r in queries.queries()[name](spark, SF).collect()]
    rows = lambda x: sorted(tuple(sorted((c, str(v)) for c, v in r.items())) for r in x)
    assert rows(got) == rows(want)
