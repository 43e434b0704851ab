"""Every registered query of the engine against its SQL, at the smallest size."""

import os

import duckdb
import pytest

from hyperpath.plans.registry import ORACLE_SQL, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return con


def normal(rows, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(tuple(str(round(r[i], 6) + 0.0 if isinstance(r[i], float) else r[i]) for i in order) for r in rows)


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_against_sql(spark, duck, small, name):
    df = QUERIES[name](spark, small)
    got = normal([tuple(r) for r in df.collect()], df.columns)
    cursor = duck.execute(ORACLE_SQL[name])
    columns = [c[0] for c in cursor.description]
    assert sorted(columns) == sorted(df.columns)
    assert got == normal(cursor.fetchall(), columns)


@pytest.mark.parametrize("name", ["q40c_sampled_suffixes", "q50b_example_fixed", "q47_communities", "q47b_found_clusters", "q49b_fit_path_lbfgs", "q49c_trained_weights"])
def test_others_give_rows(spark, small, name):
    assert QUERIES[name](spark, small).count() > 0


def test_entry_and_missing_folders(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert os.path.exists("/root/testdata") and set(ORACLE_SQL) <= set(QUERIES)
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
