"""Queries of the training-data operators that have SQL equal DuckDB's answer on the small tables."""

import duckdb
import pytest

from veilstat.llm import queries as Q

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", sorted(Q.oracle_sql()))
def test_equals_sql(spark, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    rel = con.sql(Q.oracle_sql()[name])
    cols = sorted(rel.columns)
    got = [tuple(r) for r in Q.queries()[name](spark, SF).select(*cols).collect()]
    at = [rel.columns.index(c) for c in cols]
    assert sorted(map(str, got)) == sorted(str(tuple(r[i] for i in at)) for r in rel.fetchall())
