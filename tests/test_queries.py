"""Every query that has SQL against DuckDB at the smallest size."""

import os

import duckdb
import pytest

from virtcol import queries

SF = "/root/testdata/sf0.01"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


def canonical(rows, cols):
    order = sorted(range(len(cols)), key=lambda k: cols[k])
    return sorted((tuple(round(r[k], 4) + 0.0 if isinstance(r[k], float) else r[k] for k in order) for r in rows), key=str)


@pytest.mark.skipif(not os.path.isdir(SF), reason="no tables here")
@pytest.mark.parametrize("name", sorted(queries.SQL))
def test_matches_sql(spark, duck, name):
    df, sql = queries.QUERIES[name](spark, SF), duck.sql(queries.SQL[name])
    assert sorted(df.columns) == sorted(sql.columns)
    assert canonical([tuple(r) for r in df.collect()], df.columns) == canonical(sql.fetchall(), sql.columns)
