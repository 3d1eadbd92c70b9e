"""Every catalogued query with SQL equals it at the smallest scale; the entry point works without the llm subpackage's queries."""

import math

import duckdb
import pytest

from patternlm.queries import catalogue

QUERIES, SQL = catalogue()
SLOW = {"q_walks_total", "q_unrank", "q_best_frontier"}  # many small jobs; each has its own test beside the driver's version


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else round(v, 6)
    if hasattr(v, "as_tuple"):
        return float(v)
    return tuple(map(plain, v)) if isinstance(v, (list, tuple)) else v


def rows(names, order, data):
    at = [names.index(c) for c in order]
    return sorted((tuple(plain(r[i]) for i in at) for r in data), key=lambda r: [(x is None, str(x)) for x in r])


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", [n for n in SQL if n not in SLOW])
def test_query_equals_sql(spark, sf, duck, name):
    df = QUERIES[name](spark, sf)
    order = sorted(df.columns)
    got = rows(df.columns, order, [tuple(r) for r in df.collect()])
    rel = duck.execute(SQL[name])
    names = [x[0] for x in rel.description]
    assert sorted(names) == order
    assert got == rows(names, order, rel.fetchall())


def test_entry(spark):
    import __spark_entry__ as e

    df = e.entry(spark)
    assert df.columns == ["attempts", "valid", "valid_unique", "completion"] and df.count() == 1
    assert set(e.oracle_sql()) <= set(e.queries())
