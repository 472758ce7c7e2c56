"""Every query that has SQL gives the SQL's rows, on the smallest tables."""

import duckdb
import pytest

from peertrust import registry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SF = "/root/testdata/sf0.01"
#: The slow ones are covered by the driver's own comparison.
SLOW = {"power_distributed", "walks_recursive_sql", "op_containment"}


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def rows_of(names, rows):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted(repr(tuple(r[i] for i in order)) for r in rows)


@pytest.mark.parametrize("name", sorted(set(registry.ORACLE_SQL) - SLOW))
def test_rows_equal(spark, duck, name):
    df = registry.QUERIES[name](spark, SF)
    got = df.collect()
    found = duck.execute(registry.ORACLE_SQL[name])
    names = [c[0] for c in found.description]
    assert sorted(df.columns) == sorted(names)
    assert rows_of(df.columns, got) == rows_of(names, found.fetchall())


def test_entry(spark):
    rows = registry.entry(spark).collect()
    assert len(rows) == 10 and rows[0].node == 0 and rows[0].place == 1
