"""Registered queries against DuckDB on the smallest tables."""

import duckdb
import pytest

from bandstore import registry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations"
SKIP = {"sweep_eps", "sweep_width", "space_by_structure", "success_rate", "success_rate_wide", "sweep_value_bits"}  # measured, without a SQL side


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES.split():
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def rows(df):
    cols = sorted(df.columns)
    plain = df[cols].astype(object).where(df[cols].notna(), None)
    as_text = lambda x: str(int(x)) if isinstance(x, float) and x.is_integer() else str(x)
    return cols, sorted(tuple(as_text(x) for x in r) for r in plain.itertuples(index=False, name=None))


@pytest.mark.parametrize("name", sorted(set(registry.oracle_sql()) - SKIP))
def test_matches_sql(spark, duck, name):
    got = registry.queries()[name](spark, SF).toPandas()
    assert rows(got) == rows(duck.sql(registry.oracle_sql()[name]).df())


def test_every_sql_has_a_query():
    assert set(registry.oracle_sql()) <= set(registry.queries())
