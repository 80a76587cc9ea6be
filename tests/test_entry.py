"""What the driver calls, and each oracle against its query on the smallest tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry

OWN = [k for k in entry.oracle_sql() if not k.startswith("op")]

def plain(rows):
    show = lambda x: None if x is None or x != x else f"{x:.6g}" if isinstance(x, float) else str(x)
    return sorted((tuple(map(show, r)) for r in rows), key=str)


def connect(folder):
    c = duckdb.connect()
    c.execute("SET TimeZone='UTC'")
    for t in os.listdir(folder):
        c.execute(f"CREATE VIEW {t.split('.')[0]} AS SELECT * FROM read_parquet('{folder}/{t}')")
    return c


def test_entry(spark):
    assert entry.entry(spark).count() == 6000
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", OWN)
def test_oracle(spark, sf_small, name):
    folder = sf_small
    df = entry.queries()[name](spark, folder)
    names = sorted(df.columns)
    got = plain(df.select(*(f"`{c}`" for c in names)).collect())
    cur = connect(folder).execute(f"SELECT {', '.join(chr(34) + c + chr(34) for c in names)} FROM ({entry.oracle_sql()[name]})")
    assert got == plain(cur.fetchall())
