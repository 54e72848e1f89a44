"""Every query that has SQL against DuckDB on the smallest tables, and the others for their rows."""

import math

import duckdb
import pytest

import __spark_entry__ as entry

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
# The training-data queries have tests of their own.
OWN = [n for n in entry.QUERIES]


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.execute("SET TimeZone='UTC'")
    for t in NAMES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def plain(v):
    if isinstance(v, float) or type(v).__name__ == "Decimal":
        v = float(v)
        return "nan" if math.isnan(v) else repr(round(v, 6) + 0.0)
    if isinstance(v, (list, tuple)):
        return [plain(x) for x in v]
    return str(v)


@pytest.mark.parametrize("name", [n for n in OWN if n in entry.ORACLES])
def test_same_rows(spark, sf, duck, name):
    df = entry.QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    got = sorted([plain(r[c]) for c in cols] for r in df.collect())
    res = duck.execute(entry.ORACLES[name])
    names = [d[0] for d in res.description]
    assert sorted(names) == cols
    want = sorted([plain(r[names.index(c)]) for c in cols] for r in res.fetchall())
    assert got == want


@pytest.mark.parametrize("name", [n for n in OWN if n not in entry.ORACLES])
def test_has_rows(spark, sf, name):
    assert entry.QUERIES[name](spark, sf).count() > 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0
