"""Every registered query of the graph side with SQL, on the smallest tables; and the driver's contract."""

import collections

import duckdb
import pytest

import __spark_entry__
from rdf_assist import oracles
from rdf_assist.queries import ALL

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
KINDS = {"bigint": "BIGINT", "string": "VARCHAR", "double": "DOUBLE", "boolean": "BOOLEAN", "int": "INTEGER"}
SQL = oracles.oracle_sql()


@pytest.fixture(scope="module")
def duck(tiny):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{tiny}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(SQL))
def test_sql(spark, tiny, duck, name):
    df = ALL[name](spark, tiny)
    columns = sorted(df.columns)
    want = duck.sql("SELECT " + ", ".join(f'"{c}"' for c in columns) + f" FROM ({SQL[name]}) q")
    assert [KINDS[dict(df.dtypes)[c]] for c in columns] == [str(t) for t in want.types]
    assert collections.Counter(tuple(r[c] for c in columns) for r in df.collect()) == collections.Counter(want.fetchall())


def test_contract(spark):
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
    df = __spark_entry__.entry(spark)
    assert df.columns == ["rank", "term", "origin"] and 0 < df.count() <= 10


def test_nothing_else_imports_the_text_operators():
    import pathlib

    root = pathlib.Path(__spark_entry__.__file__).parent / "rdf_assist"
    for p in root.rglob("*.py"):
        if "llm" not in p.parts:
            assert "llm" not in p.read_text(), p
