"""Streams of events: windowed cells, running state, and releases per closed batch under one budget."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxrelease.plans.cells import encode
from ctxrelease.plans.runtime import shared_dir, table
from ctxrelease.schema import ContextSchema

LATE = "1 hour"


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream; times become instants for watermarks."""
    schema = table(spark, sf_dir, "events").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(stream: DataFrame, width: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", LATE).groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), "event_type", "n")


def sliding(stream: DataFrame, width: str = "1 day", step: str = "6 hours") -> DataFrame:
    return stream.withWatermark("ts", LATE).groupBy(F.window("ts", width, step)).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), "n")


def session(stream: DataFrame, gap: str = "6 hours") -> DataFrame:
    return stream.withWatermark("ts", LATE).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("session_start"), "n")


def deduplicated(stream: DataFrame) -> DataFrame:
    return stream.withWatermark("ts", LATE).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type")


def with_domain(stream: DataFrame, domain: tuple[str, ...]) -> DataFrame:
    """Stream-static join with a declared domain, whose size is known."""
    rows = stream.sparkSession.createDataFrame([(v, k) for k, v in enumerate(domain)], "event_type string, ordinal int")
    return stream.join(F.broadcast(rows), "event_type", "left").select("event_id", "ordinal")


def running_cells(stream: DataFrame, schema: ContextSchema) -> DataFrame:
    """Cells over all micro-batches so far: bounded state, one row for each cell."""
    return encode(stream, schema).groupBy("cell").agg(F.count(F.lit(1)).alias("n"), F.sum("x").alias("s"))


def user_totals(stream: DataFrame) -> DataFrame:
    """A running count per user by explicit state."""

    def count(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n]})

    return stream.select("user_id").groupBy("user_id").applyInPandasWithState(count, "user_id long, n long", "n long", "update", "NoTimeout")


def run_to_table(spark: SparkSession, stream: DataFrame, mode: str) -> DataFrame:
    """Runs the stream over what is there and returns its result, written by tasks; it and the checkpoints lie in the shared folder.

    In update mode the result has a row for every change of a key.
    """
    name = f"result_{uuid.uuid4().hex}"
    where = f"{shared_dir(spark)}/{name}"
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{where}/out").option("checkpointLocation", f"{where}/state").outputMode(mode).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{where}/out")

    def write(batch: DataFrame, number: int) -> None:
        # a batch's folder is replaced when it is repeated, so a replay after a failure leaves one copy
        batch.write.mode("overwrite").parquet(f"{where}/out/batch={number}")

    q = stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{where}/state").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    written = spark.read.schema(stream.schema.add("batch", "long")).parquet(f"{where}/out")
    if mode == "complete":  # each batch has the whole result: the last one counts
        written = written.where(F.col("batch") == F.lit(written.agg(F.max("batch")).first()[0]))
    return written.drop("batch")


def release_each_batch(spark: SparkSession, sf_dir: str, eps: float = 0.1, total: float = 0.2) -> DataFrame:
    """A release for each micro-batch, charged to one ledger, which refuses what exceeds the total."""
    from ctxrelease.functions.mechanism import BudgetExceeded, BudgetLedger, NoValidContext, SeededNoise
    from ctxrelease.operators.release import release_context
    from ctxrelease.sources.workloads import SCHEMAS, top_records

    schema = SCHEMAS["e14"]
    where = f"{shared_dir(spark)}/releases-{uuid.uuid4().hex}"
    ledger = BudgetLedger(spark, f"{where}/ledger", total)
    rows: list[tuple] = []

    def each(batch: DataFrame, number: int) -> None:
        found = top_records(batch, schema)
        if not found:
            return
        try:
            public, _ = release_context(batch, schema, found[0], "grubbs", eps=eps, n=10, noise=SeededNoise(number), ledger=ledger)
            rows.append((number, int(found[0]), public.bits, public.predicate, public.epsilon))
        except (BudgetExceeded, NoValidContext):
            return

    q = events_stream(spark, sf_dir).writeStream.foreachBatch(each).option("checkpointLocation", f"{where}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.createDataFrame(rows, "batch long, record_id long, ctx_bits string, predicate string, epsilon double")
