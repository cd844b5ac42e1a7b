"""Every registered query with SQL gives the same rows in DuckDB."""

import duckdb
import pytest

from meshspan.plans import queries

SF = "/root/testdata/sf0.001"

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def rows_of(frame):
    columns = sorted(frame.columns)
    out = []
    for row in frame[columns].astype(object).where(frame[columns].notna(), None).values.tolist():
        out.append(tuple("" if x is None else f"{float(x):.6g}" if isinstance(x, (int, float)) and not isinstance(x, bool) else str(x) for x in row))
    return columns, sorted(out)


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_query_matches_sql(spark, duck, name):
    ours = queries.queries()[name](spark, SF).toPandas()
    theirs = duck.execute(queries.oracle_sql()[name]).df()
    assert rows_of(ours) == rows_of(theirs)
