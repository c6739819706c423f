"""The entry module: flagship query, registration, and SQL twins on the smallest tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry
from setsim import queries as core

SAMPLE = ["pfxl_order_parts_t50_hbf", "grp_order_parts_t80", "ell2_order_parts_t50_hbf", "block_order_parts_t80", "cosine_order_parts", "rs_bench_overlap10", "bitmap_probe_order_parts_b64", "bitmap_xor_page_words_b256", "prune_ratio_order_parts_t50_xor", "cutoff_table", "expected_bound_curve", "clusters", "sql_join_order_parts", "stream_user_sets", "vocab_order_parts"]


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for name in os.listdir(sf):
        c.sql(f"CREATE VIEW {name.removesuffix('.parquet')} AS SELECT * FROM '{sf}/{name}'")
    return c


def _norm(df):
    df = df[sorted(df.columns)].astype(str)
    return df.sort_values(list(df.columns)).reset_index(drop=True)


def test_flagship(spark):
    df = entry.entry(spark)
    assert df.columns == ["id_l", "id_r", "n_l", "n_r", "overlap", "sim"] and df.count() > 0


def test_names():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert set(core.QUERIES) <= set(entry.queries())


@pytest.mark.parametrize("name", SAMPLE)
def test_sql_twin(spark, sf, con, name):
    a, b = _norm(core.QUERIES[name](spark, sf).toPandas()), _norm(con.sql(core.ORACLES[name]).df())
    assert list(a.columns) == list(b.columns)
    assert a.equals(b)


@pytest.mark.parametrize("name", ["cutoff_table", "expected_bound_curve", "monte_carlo_or", "monte_carlo_xor", "monte_carlo_probe", "synth_uniform_profile", "synth_zipf_profile"])
def test_reads_a_given_table(spark, sf, con, name):
    """Theory and drawn collections run on the given tables and equal their twins."""
    df = core.QUERIES[name](spark, sf)
    assert df.inputFiles()
    assert _norm(df.toPandas()).equals(_norm(con.sql(core.ORACLES[name]).df()))
