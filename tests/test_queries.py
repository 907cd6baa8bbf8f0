"""Every registered query with SQL agrees with it on the smallest tables that are cheap to run."""

import importlib.util

import duckdb
import pytest

import __spark_entry__ as entry
from ctxrelease import registry

SF = "/root/testdata/sf0.01"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHOSEN = ["encode_e14", "cells_doc13", "context_population_li12", "context_cube_e14", "grubbs_verify_e14", "hist_verify_li12", "lof_verify_li12", "direct_release_e14", "bfs_release_e14", "dfs_release_li12", "walk_release_li12", "uniform_release_li12", "budget_table", "ops_join_asof", "ops_join_mask_theta", "ops_join_self_flip", "ops_ctx_sql", "ops_grouped_udf", "valid_lof_doc13", "lof_bfs_release_doc13", "reference_list_doc13", "hidden_outliers_li12", "sensitivity_population_e14", "greedy_dfs_li12", "ops_agg_cube", "ops_udtf", "stream_tumbling"]


def rows(frame):
    out = []
    for r in frame:
        out.append(repr(tuple(round(float(x), 6) if isinstance(x, float) else (int(x) if isinstance(x, bool) else x) for x in r)))
    return sorted(out)


@pytest.mark.parametrize("name", CHOSEN)
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    df = registry.queries()[name](spark, SF)
    columns = sorted(df.columns)
    want = con.sql(registry.oracle_sql()[name])
    assert sorted(want.columns) == columns
    quoted = ", ".join(f'"{c}"' for c in columns)
    assert rows(df.select(*columns).collect()) == rows(want.select(quoted).fetchall())


def test_entry_module():
    names = entry.queries()
    assert set(registry.queries()) <= set(names) and set(entry.oracle_sql()) <= set(names)
    if importlib.util.find_spec("ctxrelease.llm") and importlib.util.find_spec("ctxrelease.llm.registry"):
        assert all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11))
