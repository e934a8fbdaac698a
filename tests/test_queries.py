"""Every registered query against its SQL on the small tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry
from clearbound import plans

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from read_parquet('{SF}/{t}.parquet')")
    return c


def plain(v):
    if isinstance(v, bool) or v is None or isinstance(v, str):
        return repr(v)
    if hasattr(v, "isoformat"):
        return v.isoformat()
    if isinstance(v, (list, tuple)):
        return repr([plain(x) for x in v])
    return repr(round(float(v), 6) + 0.0)


@pytest.mark.parametrize("name", sorted(plans.ORACLES))
def test_against_sql(spark, con, name):
    df = plans.QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    mine = sorted(tuple(map(plain, r)) for r in df.select(*cols).collect())
    cur = con.execute(plans.ORACLES[name])
    names = [d[0] for d in cur.description]
    at = sorted(range(len(names)), key=lambda i: names[i])
    assert [names[i] for i in at] == cols
    assert mine == sorted(tuple(plain(r[i]) for i in at) for r in cur.fetchall())


@pytest.mark.parametrize("name", sorted(plans.WITHOUT_SQL))
def test_runs(spark, name):
    assert plans.WITHOUT_SQL[name] and plans.QUERIES[name](spark, SF).count() > 0


def test_entry(spark):
    assert entry.entry(spark).count() == 30
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_library_does_not_import_llm():
    root = os.path.dirname(plans.__file__) + "/.."
    for d, _, files in os.walk(root):
        if "llm" not in d.split(os.sep):
            assert not any("llm" in open(os.path.join(d, f)).read() for f in files if f.endswith(".py") and f != "__init__.py")
