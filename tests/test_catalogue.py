"""Queries against their SQL forms on the smallest tables: a sample of each family."""

import os

import duckdb
import pytest

import __spark_entry__ as contract
from spreadmax.plans.queries import ORACLES, QUERIES

NAMES = [
    "graph_cust_part", "graph_page_link", "graph_doc_line", "edge_hash_murmur", "draw_cdf_remix", "weights_normal", "fused_sample", "lane_superstep", "components_star",
    "initial_gains", "fused_memo_greedy", "spread_wc", "spread_lt", "spread_lt_live_edge", "spread_ic_rounds", "rr_cover", "optimal_seeds", "report_cube",
    "stream_session", "udtf_components", "sql_functions",
]


@pytest.fixture(scope="module")
def sql(small):
    con = duckdb.connect()
    for f in os.listdir(small):
        con.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM read_parquet('{small}/{f}')")
    return con


def rows(df):
    df = df[sorted(df.columns)]
    clean = df.astype(object).where(df.notna(), None)
    return sorted(tuple(repr(float(x)) if isinstance(x, float) else str(x) for x in r) for r in clean.itertuples(index=False))


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, small, sql, name):
    assert rows(QUERIES[name](spark, small).toPandas()) == rows(sql.execute(ORACLES[name]).df())


def test_contract(spark):
    assert set(contract.oracle_sql()) <= set(contract.queries())
    assert contract.entry(spark).count() == 5
