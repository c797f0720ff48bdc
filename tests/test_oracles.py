"""Every query with SQL equals DuckDB's answer on the small tables."""

import duckdb
import pytest

from veilstat import queries as core

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def _key(row):
    return tuple((x is not None, str(x)) for x in row)


def _names():
    from pyspark.sql import SparkSession

    SparkSession.builder.master("local[4]").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "4").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    return sorted(core.oracle_sql())


@pytest.mark.parametrize("name", _names())
def test_equals_sql(spark, duck, name):
    df = core.queries()[name](spark, SF)
    cols = sorted(df.columns)
    got = sorted((tuple(r) for r in df.select(*cols).collect()), key=_key)
    rel = duck.sql(core.oracle_sql()[name])
    at = [[c.lower() for c in rel.columns].index(c.lower()) for c in cols]
    want = sorted((tuple(r[i] for i in at) for r in rel.fetchall()), key=_key)
    assert len(got) == len(want)
    for g, w in zip(got, want, strict=True):
        for a, b in zip(g, w, strict=True):
            assert a == b or (isinstance(a, float) and b is not None and abs(a - float(b)) < 2e-6), (g, w)
