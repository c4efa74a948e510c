"""Every registered query of the reference against its SQL on the smallest tables."""

import duckdb
import pytest

from orderdep import queries as reference

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"q_exp_lists", "q_exp_columns", "q_exp_levels", "q_exp_pruning", "q_exp_fd_only"}  # minutes each; test_whole_experiments runs them in quick form


@pytest.fixture(scope="module")
def con(sf_dir):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return c


def test_every_sql_has_a_query():
    assert set(reference.SQL) <= set(reference.QUERIES) and len(reference.QUERIES) > 100


@pytest.mark.parametrize("name", sorted(set(reference.QUERIES) - SLOW))
def test_query(spark, con, sf_dir, name):
    df = reference.QUERIES[name](spark, sf_dir)
    columns = sorted(df.columns)
    rows = sorted(repr(tuple(r)) for r in df.select(*[f"`{c}`" for c in columns]).collect())
    if name in reference.SQL:
        sql = reference.SQL[name]
        assert sorted(con.sql(sql).columns) == columns
        assert rows == sorted(repr(r) for r in con.sql(f"SELECT {', '.join(chr(34) + c + chr(34) for c in columns)} FROM ({sql})").fetchall())
