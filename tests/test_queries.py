"""Every query with a SQL twin against DuckDB on the smallest tables."""

import math
import re

import duckdb
import pytest

import __spark_entry__

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUERIES, SQL = __spark_entry__.queries(), __spark_entry__.oracle_sql()
OWN = [n for n in QUERIES if not re.match(r"op\d+_|pipeline", n)]


def rows(frame):
    names = sorted(frame.columns)

    def cell(v):
        if v is None or v is getattr(v, "NaT", object()) or (isinstance(v, float) and math.isnan(v)) or str(v) in ("NaT", "<NA>"):
            return ""
        if isinstance(v, float):
            return f"{v:.6g}"
        return str(int(v)) if type(v).__name__.startswith(("int", "uint")) else str(v)

    return names, sorted([cell(v) for v in row] for row in frame[names].astype(object).values.tolist())


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", [n for n in OWN if n in SQL])
def test_against_sql(spark, sf, duck, name):
    assert rows(QUERIES[name](spark, sf).toPandas()) == rows(duck.execute(SQL[name]).df())


@pytest.mark.parametrize("name", [n for n in OWN if n not in SQL])
def test_runs(spark, sf, name):
    assert QUERIES[name](spark, sf).count() > 0


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() == 6
