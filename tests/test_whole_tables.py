"""Operator queries over whole tables that have no SQL, or whose every row counts."""

import duckdb

from ctxrelease import queries_ops as ops

SF = "/root/testdata/sf0.001"


def test_band_join_equals_brute_force(spark, tmp_path):
    """Skewed buckets, ends of the band, negative balances, keys beyond 2,000."""
    orders = [(k, [500.0, 1500.0, 995.0, 100_000.0, -2_000.0][k % 5] + (k % 7) * 0.5) for k in range(1990, 2400)]
    customers = [(k, [5.0, 10.0, 15.0, 9.95, 0.0, -25.0, 1000.0][k % 7] + (k % 3) * 0.25) for k in range(300)]
    spark.createDataFrame(orders, "o_orderkey long, o_totalprice double").write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame(customers, "c_custkey long, c_acctbal double").write.parquet(f"{tmp_path}/customer.parquet")
    want = {k: sum(p / 100 - 5 <= b <= p / 100 + 5 for _, b in customers) for k, p in orders}
    got = {r["o_orderkey"]: r["n"] for r in ops.QUERIES["ops_join_range_band"](spark, str(tmp_path)).collect()}
    assert got == {k: n for k, n in want.items() if n} and len(got) > 300


def test_whole_tables_equal_sql(spark):
    con = duckdb.connect()
    for t in ("embeddings", "events"):
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    for name, columns, least in (("ops_explode_posexplode", "vec_id, pos, v", "select sum(len(embedding)) from embeddings"), ("ops_udf", "event_id, bits", "select count(*) from events")):
        got = sorted(map(tuple, ops.QUERIES[name](spark, SF).selectExpr(*columns.split(", ")).collect()))
        assert got == sorted(con.sql(f"select {columns} from ({ops.SQL[name]})").fetchall())
        assert len(got) == con.sql(least).fetchall()[0][0]
