"""Functions for SQL users; hot paths use built-ins only."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ctxrelease.schema import Context, ContextSchema

from .student import critical_values


@F.pandas_udf(T.DoubleType())
def grubbs_critical(n: pd.Series) -> pd.Series:
    return pd.Series(critical_values(n.to_numpy("int64")))


@F.udtf(returnType=T.StructType([T.StructField("neighbor", T.LongType())]))
class ContextNeighbors:
    """The contexts one flip away from a mask of t bits."""

    def eval(self, ctx: int, t: int):
        for k in range(t):
            yield (ctx ^ (1 << k),)


@F.pandas_udf(T.DoubleType())
def studentised_range(v: pd.Series) -> float:
    """Grouped aggregate: the range over the sample deviation; null for fewer than two values or no spread."""
    sd = v.std(ddof=1)
    return None if len(v) < 2 or not sd > 0 else float((v.max() - v.min()) / sd)


def ctx_sql(schema: ContextSchema):
    """A function from a mask to the public predicate of its context."""

    @F.pandas_udf(T.StringType())
    def predicate(ctx: pd.Series) -> pd.Series:
        known = {c: Context(schema, int(c)).to_sql() for c in ctx.dropna().unique()}  # masks repeat over a table's rows
        return ctx.map(known).astype("string")

    return predicate


def gumbel(noise, *key: Column) -> Column:
    """Noise of the exponential mechanism as a column; seeded noise repeats for equal keys, secure noise never does."""
    return noise.column(*key)


def release_contexts(df: DataFrame, schema: ContextSchema, record_ids: list, detector: str = "lof", ledger=None, **options) -> DataFrame:
    """(record_id, ctx, bits, predicate, epsilon): what may be published of several records; those without a context have no row.

    The number of records is the caller's list; each release reads the table through its cells.
    """
    from ctxrelease.functions.mechanism import NoValidContext
    from ctxrelease.operators.release import release_context

    rows = []
    for rid in record_ids:
        try:
            public, _ = release_context(df, schema, rid, detector, ledger=ledger, **options)
        except NoValidContext:
            continue
        rows.append((str(public.record_id), public.ctx, public.bits, public.predicate, public.epsilon))
    return df.sparkSession.createDataFrame(rows, "record_id string, ctx long, bits string, predicate string, epsilon double")


def register(spark: SparkSession, schema: ContextSchema | None = None) -> None:
    """Makes ctx_bits(ctx, t), grubbs_critical(n) and the table function context_neighbors(ctx, t) known to SQL.

    With a schema also ctx_sql(ctx), the public predicate of its contexts.
    """
    if schema is not None:
        spark.udf.register("ctx_sql", ctx_sql(schema))
    spark.udf.register("ctx_bits", lambda ctx, t: None if ctx is None else format(ctx, f"0{t}b"), "string")
    spark.udf.register("grubbs_critical", grubbs_critical)
    spark.udtf.register("context_neighbors", ContextNeighbors)
