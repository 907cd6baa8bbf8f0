"""Noise, the exponential mechanism, and its budget.

A draw is an arg max of weight * utility plus Gumbel noise: equal in law to drawing with probabilities proportional
to the exponent, without a normalising sum, and one associative aggregate that never overflows.
"""

from __future__ import annotations

import hashlib
import math
import secrets
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


class NoValidContext(ValueError):
    """The record is an outlier in no context; nothing may be released and nothing is charged."""


class BudgetExceeded(ValueError):
    pass


@dataclass(frozen=True)
class SeededNoise:
    """Noise as a function of (seed, key): for tests, and the same in any SQL engine with md5."""

    seed: int = 0

    def column(self, *key: Column) -> Column:
        text = F.concat_ws("|", F.lit(str(self.seed)), *[k.cast("string") for k in key])
        head = F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("double")
        return -F.log(-F.log((head + 0.5) / F.lit(float(1 << 52))))

    def uniform(self, *key) -> float:
        text = "|".join(map(str, (self.seed, *key)))
        return (int(hashlib.md5(text.encode()).hexdigest()[:13], 16) + 0.5) / (1 << 52)

    def gumbel(self, *key) -> float:
        return -math.log(-math.log(self.uniform(*key)))


class SecureNoise:
    """Noise from the operating system, for releases: every use is a fresh number, and nothing to repeat it is kept.

    In columns the numbers come from the JVM's secure generator in the tasks, so neither the plan nor its logs hold a
    key. A column must be evaluated once (`exp_mechanism` and `lockstep` do): a recomputed task draws anew.
    """

    def column(self, *key: Column) -> Column:
        drawn = F.reflect(F.lit("java.util.UUID"), F.lit("randomUUID"))
        # 13 of the random hex digits of a version-4 identifier; its fixed digits lie elsewhere
        digits = F.concat(F.substring(drawn, 1, 8), F.substring(drawn, 10, 4), F.substring(drawn, 36, 1))
        return -F.log(-F.log((F.conv(digits, 16, 10).cast("double") + 0.5) / F.lit(float(1 << 52))))

    def uniform(self, *key) -> float:
        return (secrets.randbits(52) + 0.5) / (1 << 52)

    def gumbel(self, *key) -> float:
        return -math.log(-math.log(self.uniform()))


class NoNoise:
    """The limit of an unlimited budget: plain arg max, not private."""

    def column(self, *key: Column) -> Column:
        return F.lit(0.0)

    def uniform(self, *key) -> float:
        return 0.5

    def gumbel(self, *key) -> float:
        return 0.0


def weight(eps1: float, sensitivity: float = 1.0, convention: str = "eps1") -> float:
    """The factor of the utility: eps1 over the sensitivity, or half of it."""
    if convention not in ("eps1", "half"):
        raise ValueError(convention)
    return eps1 / sensitivity / (2 if convention == "half" else 1)


def selection_probabilities(cands: DataFrame, eps1: float, sensitivity: float = 1.0, by: list[str] | None = None, convention: str = "eps1") -> DataFrame:
    """Adds p to (.., ctx, u): a shifted soft maximum, so that large utilities don't overflow."""
    w = Window.partitionBy(*(by or []))
    score = F.col("u").cast("double") * weight(eps1, sensitivity, convention)
    e = cands.withColumn("__e", F.exp(score - F.max(score).over(w)))
    return e.withColumn("p", F.col("__e") / F.sum("__e").over(w)).drop("__e")


def arg_max(cands: DataFrame, noise: Column, factor: float, by: list[str]) -> DataFrame:
    """(.., best): the largest noisy score; the noise is a column of its own first, as aggregates take no random terms."""
    scored = cands.withColumn("__score", F.col("u").cast("double") * factor + noise)
    return scored.groupBy(*by).agg(F.max_by(F.struct("ctx", "u"), F.struct("__score", "ctx")).alias("best"))


def exp_mechanism(cands: DataFrame, eps1: float, noise, sensitivity: float = 1.0, by: list[str] | None = None, tag=(), convention: str = "eps1") -> DataFrame:
    """One draw (ctx, u) for each group of (.., ctx, u); ties go to the larger mask."""
    key = [*[F.lit(x) for x in tag], *[F.col(c) for c in by or []], F.col("ctx")]
    drawn = arg_max(cands, noise.column(*key), weight(eps1, sensitivity, convention), by or [])
    return drawn.where("best is not null").select(*(by or []), "best.ctx", "best.u")


def draw_local(masks, utilities, factor: float, noise, *tag) -> int:
    """Index of the draw among candidates in memory; the same noise as exp_mechanism."""
    return max(range(len(masks)), key=lambda i: (utilities[i] * factor + noise.gumbel(*tag, masks[i]), masks[i]))


METHODS = ("direct", "uniform", "walk", "dfs", "bfs")


def draws_charged(method: str, n: int, final: str = "visited", inclusive: bool = False) -> int:
    """How often eps1 is paid."""
    steps = n + 1 if inclusive else n
    if method in ("direct", "uniform", "walk"):
        return 2
    if method == "dfs" and final == "last":
        return 2 * steps
    if method in ("dfs", "bfs"):
        return 2 * steps + 2
    raise ValueError(method)


def allocate(method: str, eps: float, n: int, final: str = "visited", inclusive: bool = False) -> float:
    """The budget of one draw."""
    if eps <= 0:
        raise ValueError("the budget must be positive")
    return eps / draws_charged(method, n, final, inclusive)


def group_epsilon(eps: float, k: int) -> float:
    return eps * k


def utility_tail_bound(best: float, candidates: int, eps1: float, tau: float, sensitivity: float = 1.0) -> float:
    """A draw falls below this with probability at most exp(-tau)."""
    return best - sensitivity * (math.log(candidates) + tau) / eps1


LEDGER_SCHEMA = "at timestamp, record_id string, mechanism string, epsilon double"


class BudgetLedger:
    """Budget spent over releases: an append-only table, and an overdraft check."""

    def __init__(self, spark: SparkSession, path: str, total: float):
        self.spark, self.path, self.total = spark, path, total

    def entries(self) -> DataFrame:
        try:
            return self.spark.read.schema(LEDGER_SCHEMA).parquet(self.path)
        except Exception as e:  # nothing was charged yet
            if "PATH_NOT_FOUND" not in str(e):
                raise
            return self.spark.createDataFrame([], LEDGER_SCHEMA)

    def spent(self) -> float:
        return self.entries().agg(F.coalesce(F.sum("epsilon"), F.lit(0.0))).first()[0]

    def remaining(self) -> float:
        return self.total - self.spent()

    def charge(self, record_id, mechanism: str, epsilon: float) -> None:
        """Enters the charge first and checks afterwards, so that charges at the same time can't overdraw together.

        An entry that takes the sum over the total is reversed and refused; two that meet may both be refused.
        """
        if epsilon > self.remaining() + 1e-12:
            raise BudgetExceeded(f"{epsilon} is more than what is left of {self.total}")
        self._enter(record_id, mechanism, epsilon)
        if self.spent() > self.total + 1e-12:
            self._enter(record_id, f"{mechanism} reversed", -epsilon)
            raise BudgetExceeded(f"{epsilon} is more than what is left of {self.total}")

    def _enter(self, record_id, mechanism: str, epsilon: float) -> None:
        row = self.spark.range(1).select(F.current_timestamp().alias("at"), F.lit(str(record_id)).alias("record_id"), F.lit(mechanism).alias("mechanism"), F.lit(float(epsilon)).alias("epsilon"))
        row.write.mode("append").parquet(self.path)


def empirical_sensitivity(before: DataFrame, after: DataFrame) -> DataFrame:
    """(sensitivity): the largest change of a utility (ctx, u) between two neighbouring datasets; a missing context has 0."""
    both = before.select("ctx", F.col("u").alias("u1")).join(after.select("ctx", F.col("u").alias("u2")), "ctx", "full")
    change = F.abs(F.coalesce(F.col("u1"), F.lit(0)) - F.coalesce(F.col("u2"), F.lit(0)))
    return both.agg(F.coalesce(F.max(change), F.lit(0)).alias("sensitivity"))
