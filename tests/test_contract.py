"""Queries against their SQL in DuckDB, on the smallest tables."""

import math

import duckdb
import pytest

from dgprop.workloads import load

QUERIES, SQL = load()
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"pr_error_within_bound", "pr_push_embeddings_block", "gr_knn_edges", "st_foreachbatch_state"}
NAMES = [n for n in sorted(SQL) if n[:3] in ("ev_", "gr_", "sq_", "tk_", "mt_", "bl_", "md_", "tl_", "op_") and n not in SLOW] + ["pr_push_fixed_rounds", "pr_push_two_band", "pr_general_ab", "up_mixed_batch"]


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else repr(v + 0.0)
    return repr(v)


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, sf, duck, name):
    df = QUERIES[name](spark, sf)
    columns = sorted(df.columns)
    got = sorted(tuple(plain(r[c]) for c in columns) for r in df.collect())
    cursor = duck.execute(SQL[name])
    names = [d[0] for d in cursor.description]
    assert sorted(names) == columns
    at = [names.index(c) for c in columns]
    assert got == sorted(tuple(plain(r[i]) for i in at) for r in cursor.fetchall())


def test_entry_module(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    assert e.entry(spark).limit(1).count() == 1
