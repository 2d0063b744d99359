"""Queries against their DuckDB SQL on the smallest tables."""

import duckdb
import pandas as pd
import pytest

from lexnorm.plans.catalog import ORACLES, QUERIES

DIR = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = ["tokens_by_lang", "rollup_cube", "asof_events", "session_windows", "gram_sets", "signatures", "edges_prefix", "components_star", "norm_map", "infer_attach_strict", "rewrite_conversations", "error_bounds", "perturb_40", "edit_deletion_index", "mips_exact", "sql_similarity", "exact_jaccard_pairs"]


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    c.execute("SET memory_limit = '3GB'")
    c.execute("SET threads = 4")
    c.execute("SET temp_directory = ''")
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DIR}/{t}.parquet'")
    return c


def _cell(v):
    if v is None or v is pd.NA or v is pd.NaT or v != v:
        return "none"
    if isinstance(v, float):
        return str(int(v)) if v == int(v) else f"{v:.6f}"
    return str(v)


def _rows(df):
    df = df[sorted(df.columns)]
    return sorted(tuple(map(_cell, r)) for r in df.itertuples(index=False, name=None))


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, con, name):
    got, want = QUERIES[name](spark, DIR).toPandas(), con.execute(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert _rows(got) == _rows(want)


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_error_bounds_read_a_table(spark):
    assert any("documents.parquet" in f for f in QUERIES["error_bounds"](spark, DIR).inputFiles())
