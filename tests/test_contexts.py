"""Contexts, cells and folding on the worked example and a given table."""

import pytest

from ctxrelease.plans import cells as pl
from ctxrelease.schema import AttributeSpec, Context, ContextSchema, wide_words
from ctxrelease.sources import workloads as wl

SF = "/root/testdata/sf0.001"


def test_worked_example(spark):
    df, schema = wl.workload(spark, SF, "inc9")
    c = Context.from_bits(schema, "101001010")
    assert c.values() == {"job": ["CEO", "Lawyer"], "city": ["Toronto"], "district": ["Historic"]}
    assert df.where(c.to_column()).count() == 0
    assert c.connected(Context.from_bits(schema, "100001010")) and not c.connected(Context.from_bits(schema, "101010001"))
    found = df.where(Context.from_bits(schema, "101010001").to_column())
    assert sorted(r[0] for r in found.select("id").collect()) == [3, 5, 8]
    assert found.where("job = 'CEO'").count() == 1


def test_counts_and_bits():
    assert [wl.SCHEMAS[n].t for n in ("inc9", "e14", "e25", "li12", "li16", "doc13", "o13")] == [9, 14, 25, 12, 16, 13, 13]
    assert wl.SCHEMAS["inc9"].wellformed_count() == 343 and wl.SCHEMAS["e14"].wellformed_count() == 11_811 and wl.SCHEMAS["li12"].wellformed_count() == 2_667
    schema = wl.SCHEMAS["inc9"]
    assert Context.from_bits(schema, "101001010").bits == "101001010"
    assert not Context.from_bits(schema, "000001010").is_wellformed
    with pytest.raises(ValueError):
        Context.from_bits(schema, "10")


def test_fold_equals_cells_equals_filter(spark):
    df, schema = wl.workload(spark, SF, "inc9")
    cells = pl.build_cells(df, schema)
    folded = {r["ctx"]: (r["n"], r["s"], r["lo"], r["hi"]) for r in pl.fold_contexts(cells, schema).collect()}
    every = spark.range(512).selectExpr("id AS ctx")
    assert folded == {r["ctx"]: (r["n"], r["s"], r["lo"], r["hi"]) for r in pl.context_stats(cells, every).collect()}
    for mask in list(folded)[::60]:
        assert folded[mask][0] == df.where(Context(schema, mask).to_column()).count()
    cell, _ = pl.lookup_record(df, schema, 3)
    anchored = {r["ctx"]: r["n"] for r in pl.fold_contexts(cells, schema, cell).collect()}
    assert anchored == {c: v[0] for c, v in folded.items() if c & cell == cell}
    assert pl.candidate_contexts(spark, schema, cell).count() == 64


def test_nulls_and_undeclared_values_are_in_no_population(spark):
    schema = ContextSchema("x", (AttributeSpec("a", "a", ("p", "q")),), "v", "id")
    df = spark.createDataFrame([(1, "p", 1.0), (2, None, 2.0), (3, "z", 3.0), (4, "q", None), (5, "q", float("nan"))], "id long, a string, v double")
    assert [r[0] for r in pl.encode(df, schema).collect()] == [1]


def test_domains_are_declared(spark):
    df, _ = wl.workload(spark, SF, "inc9")
    with pytest.raises(ValueError):
        ContextSchema.infer(df, ["job"], "salary", "id")
    assert ContextSchema.infer(df, ["job"], "salary", "id", allow_inferred_domain=True).t == 3


def test_wide_contexts(spark):
    schema = ContextSchema("wide", (AttributeSpec("a", "a", tuple(map(str, range(70)))), AttributeSpec("b", "b", ("x", "y"))), "v", "id")
    df = spark.createDataFrame([(1, "0", "x", 1.0), (2, "69", "y", 2.0)], "id long, a string, b string, v double")
    ctx = schema.bit(0, 0) | schema.bit(1, 0) | schema.bit(1, 1)
    from pyspark.sql import functions as F

    from ctxrelease.schema import wide_contains

    words = F.array(*[F.lit(w).cast("long") for w in wide_words(schema, ctx)])
    assert [r[0] for r in pl.encode_wide(df, schema).where(wide_contains(F.col("cell"), words)).collect()] == [1]


@pytest.mark.parametrize("name", ["li12", "li16"])
def test_whole_lineitem(spark, name):
    """Every row of lineitem is in a cell, and cells and the chosen record equal SQL."""
    import duckdb

    con = duckdb.connect()
    for t in ("lineitem", "part"):
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    df, schema = wl.workload(spark, SF, name)
    got = sorted((r["cell"], r["n"], int(r["s"]), int(r["ss"]), r["lo"], r["hi"]) for r in pl.build_cells(df, schema).collect())
    assert got == sorted(con.sql(wl.cells_sql(name)).fetchall())
    assert sum(r[1] for r in got) == con.sql("select count(*) from lineitem").fetchall()[0][0]
    assert wl.top_records(df, schema) == [con.sql(f"select record_id from ({wl.encoded_sql(name)}) order by x desc, record_id limit 1").fetchall()[0][0]]
