"""Queries against their SQL on the smallest tables."""

import os

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry

KEYS = [
    "w_cust_type", "w_page_link", "m_estimate_k256", "m_hits_cells", "m_hits_sweep", "m_merge", "m_median_runs", "m_family_affine61", "m_interval", "s_exact_10", "s_store", "s_maintain",
    "b_min_rank", "x_work", "x_failure_split", "x_published_bounds", "join_asof", "join_range", "join_cells", "agg_bottom_k", "fn_sp_hits", "scan_blocks", "st_estimate", "app_chain_order",
]


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for f in os.listdir(sf):
        c.sql(f"create view {f.removesuffix('.parquet')} as select * from '{sf}/{f}'")
    return c


def rows(df):
    df = df[sorted(df.columns)]
    clean = lambda v: None if pd.isna(v) else round(float(v), 6) if isinstance(v, float) or hasattr(v, "dtype") and v.dtype.kind == "f" else str(v)
    return sorted((tuple(clean(v) for v in r) for r in df.itertuples(index=False)), key=str)


@pytest.mark.parametrize("key", KEYS)
def test_oracle(spark, sf, duck, key):
    ours, theirs = entry.queries()[key](spark, sf).toPandas(), duck.sql(entry.oracle_sql()[key]).df()
    assert sorted(ours.columns) == sorted(theirs.columns)
    assert rows(ours) == rows(theirs)


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
