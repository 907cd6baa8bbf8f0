"""Tables that outlive a session: cells, reference files, trial logs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxrelease.schema import ContextSchema

CELLS_SCHEMA = "cell long, n long, s decimal(38,0), ss decimal(38,0), lo long, hi long"


def save_cells(cells: DataFrame, path: str) -> None:
    cells.write.mode("overwrite").parquet(path)


def load_cells(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(CELLS_SCHEMA).parquet(path)


def merge_cells(old: DataFrame, new: DataFrame) -> DataFrame:
    """Cells of two disjoint parts of a table: moments add, nothing is scanned again."""
    both = old.unionByName(new)
    return both.groupBy("cell").agg(F.sum("n").alias("n"), F.sum("s").cast("decimal(38,0)").alias("s"), F.sum("ss").cast("decimal(38,0)").alias("ss"), F.min("lo").alias("lo"), F.max("hi").alias("hi"))


def save_reference_file(contexts: DataFrame, schema: ContextSchema, path: str) -> None:
    """Contexts in folders by the subset of the first attribute, so that a record's contexts are few folders."""
    first = F.col("ctx").bitwiseAND(F.lit(schema.attr_masks[0]))
    contexts.withColumn("first_attribute", first).write.mode("overwrite").partitionBy("first_attribute").parquet(path)


def read_reference_file(spark: SparkSession, schema: ContextSchema, path: str, anchor: int | None = None) -> DataFrame:
    """Contexts of the file; with an anchor those that hold it, from matching folders only."""
    df = spark.read.parquet(path)
    if anchor is None:
        return df
    own = anchor & schema.attr_masks[0]
    return df.where((F.col("first_attribute").bitwiseAND(F.lit(own)) == F.lit(own)) & (F.col("ctx").bitwiseAND(F.lit(anchor)) == F.lit(anchor)))
