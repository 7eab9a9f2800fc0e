"""Every query with SQL on the smallest tables, against DuckDB."""

import duckdb
import pytest

from densereps.queries import ORACLES, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Written for the sizes of sf0.01: fixed sample sizes, or fixed counts.
LARGER = {"sample_test_disjoint", "remainder_after_sample"}
FAST = sorted(k for k in ORACLES if k not in LARGER)


@pytest.fixture(scope="module")
def sql(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    return con


def normal(rows, columns):
    order = sorted(range(len(columns)), key=columns.__getitem__)
    value = lambda v: round(v, 6) if isinstance(v, float) else v
    return sorted([tuple(value(r[i]) for i in order) for r in rows], key=lambda r: tuple((x is None, str(x)) for x in r))


@pytest.mark.parametrize("name", FAST)
def test_query_against_sql(spark, sf_dir, sql, name):
    df = QUERIES[name](spark, sf_dir)
    want = sql.execute(ORACLES[name])
    columns = [c[0] for c in want.description]
    assert sorted(columns) == sorted(df.columns)
    assert normal(df.collect(), df.columns) == normal(want.fetchall(), columns)


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 150
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
