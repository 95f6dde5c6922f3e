"""Registered queries against DuckDB on the smallest tables."""

import decimal

import pytest

DIR = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: One query of each kind; the driver compares all of them.
CHOSEN = ["forest_orders", "forest_sessions_rank", "forest_pages_flat", "forest_urls", "forest_stats_conversations", "parents_orders", "inner_join_cumulative_orders", "homo_count_fork3_conversations", "mine_conversations_k4", "mine_conversations_k3_class", "closed_conversations", "support_cube_orders", "anomaly_forest"]


@pytest.fixture(scope="module")
def duck():
    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{DIR}/{t}.parquet')")
    return con


def rows(columns, values):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    plain = lambda x: int(x) if isinstance(x, decimal.Decimal) else x
    return sorted((tuple(plain(r[i]) for i in order) for r in values), key=repr)


@pytest.mark.parametrize("name", CHOSEN)
def test_query_equals_sql(spark, duck, name):
    import __spark_entry__ as entry

    df = entry.queries()[name](spark, DIR)
    want = duck.sql(entry.oracle_sql()[name])
    assert sorted(df.columns) == sorted(want.columns)
    assert rows(df.columns, df.collect()) == rows(want.columns, want.fetchall())


def test_every_oracle_has_a_query():
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", ["star_records", "chain_records", "chain_records_literal", "synthetic_master_d10", "synthetic_master_d5", "synthetic_master_m", "synthetic_trees_d5"])
def test_query_reads_a_given_table(spark, duck, name):
    """Records and synthetic trees come from a table's rows and equal their SQL."""
    import __spark_entry__ as entry

    df = entry.queries()[name](spark, DIR)
    if "records" not in name:  # those are kept in memory, which names no files
        assert any(f"{DIR}/{t}.parquet" in f for f in df.inputFiles() for t in ("part", "orders"))
    want = duck.sql(entry.oracle_sql()[name])
    assert rows(df.columns, df.collect()) == rows(want.columns, want.fetchall())
