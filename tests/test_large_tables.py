"""What fails only on larger tables, made to show on small ones."""

import datetime

import duckdb
import numpy as np
import pytest

from ctxrelease import queries_experiments, queries_measures, registry
from ctxrelease.operators import detectors as det
from ctxrelease.operators import matching, measures
from ctxrelease.schema import AttributeSpec, ContextSchema

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["li12", "e14"])
def test_valid_sets_of_neighbours_need_no_values(spark, monkeypatch, name):
    """The top record's neighbouring datasets, with and without room for more than the cells' moments."""
    columns = ("pair", "exact", "jaccard", "max_ratio")
    want = sorted(map(tuple, queries_measures._neighbours(spark, SF, name, 0).select(*columns).collect()))
    monkeypatch.setattr(det, "BROADCAST_LIMIT_BYTES", 48 * 100)
    got = sorted(map(tuple, queries_measures._neighbours(spark, SF, name, 0).select(*columns).collect()))
    assert got == want and len(want) == 20


def test_logarithm_of_a_ratio_beyond_doubles(spark):
    """One context of a million rows is lost with its only far value; the others have a few rows each."""
    schema = ContextSchema("two", (AttributeSpec("a", "a", ("0", "1")),), "v", "id")

    class Lost(det.Detector):
        name = "lost"

        def flags(self, part, ctxs, x):
            n = part.stats(ctxs)["n"]
            return (ctxs == 1) | (n >= 1_000_000), n.astype(float)

    one, zero = np.array([1, 2]), np.zeros(2)
    part = det.Slice(one, np.array([5, 999_995]), zero, zero, np.zeros(2, np.int64), np.full(2, 9))
    edges = {2: (np.array([0, 0]), np.array([9, 9]))}
    row = matching.match_pairs(spark, schema, [("r", 1, 9)], part, Lost(), {1: [[(2, 0)]]}, edges).first()
    assert not row["exact"] and row["max_ratio"] == float("inf") and abs(row["log_ratio"] - 0.1 * 999_995) < 1e-6


def test_largest_ratio_where_probabilities_vanish(spark):
    """Contexts of 5 rows beside one of 100,000, whose probabilities are zero as doubles."""
    tables = [measures.probability_table(spark.createDataFrame([(1, 100_000), (2, 5), (3, n)], "ctx long, u long"), 0.1) for n in (5, 6)]
    row = measures.max_ratio(*tables).first()
    assert abs(row["max_ratio"] - np.exp(0.1)) < 1e-9 and row["common"] == 3


def crowded(spark, path, lonely):
    """lineitem and part whose largest metric has many copies in its cell; `lonely` rows are each alone with their metric."""
    crowd = [(k, 1.0, 1_000.0 * (1 + k % 5)) for k in range(200)] + [(200 + k, 1.0, 90_000.0) for k in range(20)] + [(300 + k, 1.0, v) for k, v in enumerate(lonely)]
    rows = [(k, 1, 1, 1, q, p, "A", "F", datetime.datetime(1996, 1, 1)) for k, q, p in crowd]
    spark.createDataFrame(rows, "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_quantity double, l_extendedprice double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz").write.parquet(f"{path}/lineitem.parquet")
    spark.createDataFrame([(1, "PROMO X")], "p_partkey long, p_type string").write.parquet(f"{path}/part.parquet")


def test_trials_of_a_record_without_valid_contexts(spark, tmp_path):
    grid = [("bfs", 0.2, 5), ("dfs", 0.2, 5)]
    crowded(spark, tmp_path / "none", [])
    rows = queries_experiments._summary(queries_experiments.trials(spark, str(tmp_path / "none"), "li16", grid, repetitions=3), ["method"]).collect()
    assert sorted(r["method"] for r in rows) == ["bfs", "dfs"] and all(r["utility"] is None and r["t_avg"] is None for r in rows)
    crowded(spark, tmp_path / "one", [60_000.0])
    rows = queries_experiments.trials(spark, str(tmp_path / "one"), "li16", grid, repetitions=3).collect()
    assert len(rows) == 6 and all(r["record_id"].startswith("300|") and r["ratio"] > 0 for r in rows)


@pytest.mark.parametrize("name", ["budget_table", "inc9_contexts", "ops_ctx_sql", "ops_pandas_udf", "wellformed_count_e14", "wellformed_count_inc9", "wellformed_count_li12"])
def test_query_reads_a_given_table(spark, name):
    con = duckdb.connect()
    for t in ("lineitem", "events", "orders", "customer"):
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    df = registry.queries()[name](spark, SF)
    assert any(f.endswith(".parquet") for f in df.inputFiles())
    want = con.sql(registry.oracle_sql()[name])
    assert sorted(want.columns) == sorted(df.columns)
    assert sorted(map(tuple, df.select(*want.columns).collect())) == sorted(want.fetchall())


@pytest.mark.parametrize("name", ["li12", "e14"])
def test_matching_on_stored_values(spark, monkeypatch, name):
    """All detectors on neighbouring datasets, with and without room for the counts of all values."""
    run = lambda: sorted(repr(tuple(r)) for r in queries_experiments.match(spark, SF, name, 3, 3, (1, 5)).collect())
    want = run()
    monkeypatch.setattr(det, "BROADCAST_LIMIT_BYTES", 48 * 100)
    assert run() == want and len(want) >= 12
