"""Every query of the engine against its SQL, and the wiring."""

from __future__ import annotations

import duckdb
import pytest

import __spark_entry__
from levelmine import catalog
from levelmine.functions import sql as functions

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def db(sf_dir):
    con = duckdb.connect()
    con.execute("SET TimeZone='UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


def rows(cols, data):
    at = [cols.index(c) for c in sorted(cols)]
    cell = lambda v: round(v, 6) if isinstance(v, float) else v
    return sorted((tuple(cell(r[i]) for i in at) for r in data), key=lambda r: tuple((x is None, str(x)) for x in r))


@pytest.mark.parametrize("name", sorted(catalog.queries()))
def test_query(spark, db, sf_dir, name):
    df = catalog.queries()[name](spark, sf_dir)
    got = rows(df.columns, df.collect())
    sql = catalog.oracle_sql().get(name)
    if sql is None:
        return
    r = db.execute(sql)
    cols = [d[0] for d in r.description]
    assert sorted(cols) == sorted(df.columns)
    assert got == rows(cols, r.fetchall())


def test_entry(spark):
    df = __spark_entry__.entry(spark)
    assert df.columns == ["k", "motif", "frequency"] and df.filter("k = 3").count() == 2


def test_wiring():
    names = __spark_entry__.queries()
    assert set(catalog.queries()) <= set(names) and set(__spark_entry__.oracle_sql()) <= set(names)


def test_table_function(spark):
    functions.register(spark)
    spark.createDataFrame([(0, 1, 2), (0, 2, 3), (0, 1, 3), (1, 1, 2), (1, 2, 3)], "part int, src long, dst long").createOrReplaceTempView("small_edges")
    got = spark.sql("SELECT * FROM mine_motifs(TABLE(SELECT * FROM small_edges) PARTITION BY (part), 3)").collect()
    assert sorted(map(tuple, got)) == [("chain", 1), ("triangle", 1)]
