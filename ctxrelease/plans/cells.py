"""From rows to cells, and from cells to contexts.

Contexts only see attribute values, so one scan condenses the table into cells (one for each combination of values
that occurs) with exact moments; all later work is independent of the number of rows. Statistics of all contexts
come from folding one attribute at a time, not from testing contexts against cells.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxrelease.schema import SCALE, WORD_BITS, Context, ContextSchema, wide_words

from .runtime import bounded_broadcast

MOMENTS = ("n", "s", "ss", "lo", "hi")


def encode(df: DataFrame, schema: ContextSchema) -> DataFrame:
    """(record_id, cell, x): the mask of a row's values and its metric in ten-thousandths.

    Rows with a null or undeclared value, or a null or non-finite metric, are in no population and go.
    """
    bits = []
    for i, a in enumerate(schema.attrs):
        value = F.expr(a.expr).cast("string")
        bits.append(reduce(lambda c, j, v=value, i=i, a=a: c.when(v == a.domain[j], F.lit(schema.bit(i, j))), range(1, len(a.domain)), F.when(value == a.domain[0], F.lit(schema.bit(i, 0)))))
    cell = reduce(lambda x, y: x.bitwiseOR(y), [b.cast("long") for b in bits])
    x = (F.expr(schema.metric).cast("decimal(18,4)") * SCALE).cast("long")
    return df.select(F.expr(schema.record_id).alias("record_id"), cell.alias("cell"), x.alias("x")).where("cell is not null and x is not null")


def encode_wide(df: DataFrame, schema: ContextSchema) -> DataFrame:
    """As encode(), for schemas of more than 63 bits: the cell is an array of words."""
    words = [F.lit(0).cast("long")] * len(wide_words(schema, 0))
    known = F.lit(True)
    for i, a in enumerate(schema.attrs):
        value = F.expr(a.expr).cast("string")
        known = known & F.coalesce(value.isin(*a.domain), F.lit(False))
        for j, v in enumerate(a.domain):
            for k, w in enumerate(wide_words(schema, schema.bit(i, j))):
                if w:
                    words[k] = words[k].bitwiseOR(F.when(value == v, F.lit(w)).otherwise(F.lit(0)).cast("long"))
    x = (F.expr(schema.metric).cast("decimal(18,4)") * SCALE).cast("long")
    return df.where(known).select(F.expr(schema.record_id).alias("record_id"), F.array(*words).alias("cell"), x.alias("x")).where("x is not null")


def population(df: DataFrame, context: Context) -> DataFrame:
    """The rows that a context selects, by its public predicate: on plain columns it reaches the scan."""
    return df.where(context.to_column())


def moments(group) -> DataFrame:
    d = F.col("x").cast("decimal(18,0)")
    return group.agg(
        F.count(F.lit(1)).alias("n"),
        F.sum(d.cast("decimal(28,0)")).cast("decimal(38,0)").alias("s"),
        F.sum((d * d).cast("decimal(36,0)")).cast("decimal(38,0)").alias("ss"),
        F.min("x").alias("lo"),
        F.max("x").alias("hi"),
    )


def build_cells(df: DataFrame, schema: ContextSchema) -> DataFrame:
    """(cell, n, s, ss, lo, hi): one scan of m+1 columns, partial sums before the only shuffle."""
    return moments(encode(df, schema).groupBy("cell"))


def build_cell_values(df: DataFrame, schema: ContextSchema) -> DataFrame:
    """(cell, x, cnt): counts of distinct values in cells."""
    return encode(df, schema).groupBy("cell", "x").agg(F.count(F.lit(1)).alias("cnt"))


def _merge(group) -> DataFrame:
    return group.agg(
        F.sum("n").cast("long").alias("n"),
        F.sum("s").cast("decimal(38,0)").alias("s"),
        F.sum("ss").cast("decimal(38,0)").alias("ss"),
        F.min("lo").alias("lo"),
        F.max("hi").alias("hi"),
    )


def _subsets(mask: int) -> list[int]:
    out, s = [], mask
    while s:
        out.append(s)
        s = (s - 1) & mask
    return out


def fold_contexts(cells: DataFrame, schema: ContextSchema, anchor: int | None = None) -> DataFrame:
    """(ctx, n, s, ss, lo, hi) of every context with rows; with an anchor (a record's cell) of those that hold it.

    Attribute by attribute, a cell's value is replaced by each allowed subset that holds it, and equal keys are
    merged at once. The tables of subsets are bounded by the domains (|A| 2^(|A|-1) rows).
    """
    spark = cells.sparkSession
    part = cells.select(F.lit(0).cast("long").alias("ctx"), "cell", *MOMENTS)
    for i, mask in enumerate(schema.attr_masks):
        rows = []
        for subset in _subsets(mask):
            if anchor is None or subset & anchor & mask:
                rows += [(schema.bit(i, j), subset) for j in range(len(schema.attrs[i].domain)) if subset & schema.bit(i, j)]
        table = bounded_broadcast(spark.createDataFrame(rows, "value long, subset long"), len(rows), 16)
        joined = part.join(table, F.col("cell").bitwiseAND(F.lit(mask)) == F.col("value"))
        part = _merge(joined.groupBy(F.col("ctx").bitwiseOR(F.col("subset")).alias("ctx"), F.col("cell").bitwiseAND(F.lit(~mask)).alias("cell")))
    return part.drop("cell")


def supersets(values: DataFrame, schema: ContextSchema) -> DataFrame:
    """Adds `ctx`: a row for each well-formed context that holds the row's cell, attribute by attribute."""
    spark = values.sparkSession
    out = values.withColumn("ctx", F.lit(0).cast("long"))
    for i, mask in enumerate(schema.attr_masks):
        rows = [(schema.bit(i, j), subset) for subset in _subsets(mask) for j in range(len(schema.attrs[i].domain)) if subset & schema.bit(i, j)]
        table = bounded_broadcast(spark.createDataFrame(rows, "value long, subset long"), len(rows), 16)
        out = out.join(table, F.col("cell").bitwiseAND(F.lit(mask)) == F.col("value")).withColumn("ctx", F.col("ctx").bitwiseOR(F.col("subset"))).drop("value", "subset")
    return out


def context_stats(cells: DataFrame, contexts: DataFrame) -> DataFrame:
    """Statistics of given contexts (ctx): every context against every cell. The reference path, and the one for few contexts."""
    return _merge(contexts.join(cells, F.col("cell").bitwiseAND(F.col("ctx")) == F.col("cell")).groupBy("ctx"))


def candidate_contexts(spark: SparkSession, schema: ContextSchema, anchor: int) -> DataFrame:
    """(ctx): the 2^(t-m) contexts that hold a record, from a range whose bits go to the free places."""
    free = schema.free_bits(anchor)
    if len(free) > 40:
        raise ValueError(f"2^{len(free)} candidates: use a sampling method")
    ctx = F.lit(anchor)
    for k, b in enumerate(free):
        ctx = ctx.bitwiseOR(F.shiftright(F.col("id"), k).bitwiseAND(F.lit(1)) * F.lit(b))
    return spark.range(1 << len(free)).select(ctx.alias("ctx"))


def neighbors(contexts: DataFrame, t: int, column: str = "ctx") -> DataFrame:
    """Adds `neighbor`: the t contexts one flip away, by explode; pairs are never searched for."""
    flips = F.array(*[F.lit(1 << k) for k in range(t)])
    return contexts.withColumn("neighbor", F.explode(F.transform(flips, lambda b: F.col(column).bitwiseXOR(b))))


def wellformed(schema: ContextSchema, column: str = "ctx"):
    out = F.lit(True)
    for a in schema.attr_masks:
        out = out & (F.col(column).bitwiseAND(F.lit(a)) != 0)
    return out


def lookup_record(df: DataFrame, schema: ContextSchema, record_id) -> tuple[int, int]:
    """(cell, x) of a record; its filter reaches the scan where the id is a column."""
    found = encode(df, schema).where(F.col("record_id") == F.lit(record_id)).select("cell", "x").first()
    if found is None:
        raise KeyError(f"no record {record_id} with declared values")
    return found[0], found[1]


def fits_word(schema: ContextSchema) -> bool:
    return schema.t <= WORD_BITS
