"""Measures of cost, accuracy and privacy over trials and valid sets."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ctxrelease.functions.mechanism import selection_probabilities, weight
from ctxrelease.plans.cells import neighbors
from ctxrelease.schema import ContextSchema

#: Two-sided 90 % point of the normal distribution.
Z90 = 1.6448536269514722


def runtime_columns() -> list[Column]:
    return [F.min("seconds").alias("t_min"), F.max("seconds").alias("t_max"), F.avg("seconds").alias("t_avg")]


def utility_columns() -> list[Column]:
    """Mean ratio to the best valid context, with a 90 % interval."""
    half = F.lit(Z90) * F.coalesce(F.stddev_samp("ratio"), F.lit(0.0)) / F.sqrt(F.nullif(F.count("ratio"), F.lit(0)))
    return [F.avg("ratio").alias("utility"), (F.avg("ratio") - half).alias("ci_lo"), (F.avg("ratio") + half).alias("ci_hi")]


def counter_columns() -> list[Column]:
    """Machine-free cost: contexts verified, draws, random trials."""
    return [F.avg("verified").alias("verified"), F.avg("draws").alias("draws"), F.avg("trials").alias("trials")]


def utility_summary(trials: DataFrame, by: list[str]) -> DataFrame:
    return trials.groupBy(*by).agg(F.count("ratio").alias("trials"), *utility_columns())


def bootstrap_interval(trials: DataFrame, by: list[str], rounds: int = 200, seed: int = 1) -> DataFrame:
    """Percentile bootstrap of the mean ratio; a group holds one experiment's repetitions."""

    def run(key, frame: pd.DataFrame) -> pd.DataFrame:
        r = np.sort(frame["ratio"].dropna().to_numpy())
        if not len(r):
            return pd.DataFrame([[*key, None, None, None]])
        rng = np.random.default_rng(seed)
        means = r[rng.integers(0, len(r), (rounds, len(r)))].mean(1)
        return pd.DataFrame([[*key, r.mean(), *np.quantile(means, [0.05, 0.95])]])

    kinds = dict(trials.dtypes)
    schema = ", ".join([*(f"{c} {kinds[c]}" for c in by), "utility double, ci_lo double, ci_hi double"])
    return trials.groupBy(*by).applyInPandas(run, schema)


def counters(trials: DataFrame, by: list[str]) -> DataFrame:
    return trials.groupBy(*by).agg(*counter_columns(), F.max("verified").alias("verified_max"))


def expected_trials(valid: int, free_bits: int, n: int) -> float:
    """Mean number of random contexts until n valid ones."""
    return n * 2.0**free_bits / valid if valid else float("inf")


def locality(valid: DataFrame, schema: ContextSchema, anchor: int) -> DataFrame:
    """P(valid | neighbour of a valid context) against P(valid | candidate), by explode and equi join."""
    around = neighbors(valid.select("ctx"), schema.t).where(F.col("neighbor").bitwiseAND(F.lit(anchor)) == F.lit(anchor))
    hit = around.join(valid.select(F.col("ctx").alias("neighbor"), F.lit(1).alias("one")), "neighbor", "left")
    free = schema.t - anchor.bit_count()
    near = hit.agg(F.count("one").alias("hits"), F.count(F.lit(1)).alias("pairs"))
    return near.crossJoin(valid.agg(F.count(F.lit(1)).alias("valid"))).select(  # one row each
        "valid", (F.col("hits") / F.col("pairs")).alias("p_neighbor"), (F.col("valid") / F.lit(float(1 << free))).alias("p_random")
    )


def graph_components(valid: DataFrame, schema: ContextSchema) -> DataFrame:
    """(ctx, component) of the graph of valid contexts: min labels until nothing changes."""
    from ctxrelease.plans.runtime import cut

    edges = cut(neighbors(valid.select("ctx"), schema.t).join(valid.select(F.col("ctx").alias("neighbor")), "neighbor").select("ctx", "neighbor"))
    state = cut(valid.select("ctx", F.col("ctx").alias("component")))
    while True:
        low = edges.join(state.select(F.col("ctx").alias("neighbor"), "component"), "neighbor").groupBy("ctx").agg(F.min("component").alias("low"))
        new = cut(state.join(low, "ctx", "left").select("ctx", F.least("component", F.coalesce("low", "component")).alias("component"), F.col("component").alias("old")))
        if new.where("component <> old").isEmpty():
            return new.select("ctx", "component")
        state = new.select("ctx", "component")


def max_ratio(p1: DataFrame, p2: DataFrame) -> DataFrame:
    """Largest ratio of selection probabilities over contexts valid in both, from their logarithms: small ones are zero as doubles."""
    both = p1.select("ctx", F.col("log_p").alias("p1")).join(p2.select("ctx", F.col("log_p").alias("p2")), "ctx")
    return both.agg(F.exp(F.max(F.abs(F.col("p1") - F.col("p2")))).alias("max_ratio"), F.count(F.lit(1)).alias("common"))


def compare_sets(v1: DataFrame, v2: DataFrame) -> DataFrame:
    """Whether two valid sets agree, and their Jaccard similarity."""
    both = v1.select("ctx", F.lit(1).alias("a")).join(v2.select("ctx", F.lit(1).alias("b")), "ctx", "full")
    return both.agg(F.coalesce(F.bool_and(F.col("a").isNotNull() & F.col("b").isNotNull()), F.lit(True)).alias("exact"), (F.count_if(F.col("a").isNotNull() & F.col("b").isNotNull()) / F.count(F.lit(1))).alias("jaccard"))


def are_f_neighbors(d1: DataFrame, d2: DataFrame, v1: DataFrame, v2: DataFrame) -> bool:
    """One record apart, and the same non-empty valid set."""
    apart = d1.exceptAll(d2).count() + d2.exceptAll(d1).count()
    return apart == 1 and not v1.isEmpty() and bool(compare_sets(v1, v2).first()["exact"])


def probability_table(valid: DataFrame, eps1: float, sensitivity: float = 1.0) -> DataFrame:
    """(ctx, u, p, log_p) of valid contexts."""
    score = F.col("u").cast("double") * weight(eps1, sensitivity)
    top = F.max(score).over(Window.partitionBy())
    total = F.log(F.sum(F.exp(F.col("__score"))).over(Window.partitionBy()))
    return selection_probabilities(valid.select("ctx", "u"), eps1, sensitivity).withColumn("__score", score - top).withColumn("log_p", F.col("__score") - total).drop("__score")
