"""Releases: enumeration, direct selection, sampled selection, and many trials in one job."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ctxrelease.functions.mechanism import BudgetLedger, NoValidContext, SecureNoise, SeededNoise, allocate, arg_max, exp_mechanism
from ctxrelease.plans.cells import build_cells, candidate_contexts, context_stats, encode, fold_contexts, lookup_record, neighbors
from ctxrelease.plans.runtime import cut
from ctxrelease.schema import Context, ContextSchema

from .detectors import DETECTORS, LOF, Detector, Grubbs, Histogram, Slice, grubbs_columns, local_factor, take_slice, verify
from .search import UTILITIES, Outcome, Search, starting_context


@dataclass(frozen=True)
class Release:
    """What may be published."""

    record_id: object
    ctx: int
    bits: str
    predicate: str
    epsilon: float


@dataclass(frozen=True)
class OwnerLog:
    """What stays with the owner."""

    method: str
    detector: str
    outcome: Outcome


def valid_contexts(df: DataFrame, schema: ContextSchema, record_id, detector: Detector, start: int | None = None) -> DataFrame:
    """(ctx, population, u, score) of every valid context of a record: its exact enumeration.

    Moment-based detectors run on folded cells inside the JVM; others on batches of masks. With `start` the utility
    is the overlap with that context, the population of the masks' intersection.
    """
    cell, x = lookup_record(df, schema, record_id)
    cells = cut(build_cells(df, schema))
    if type(detector) is Grubbs and detector.mode == "deviation":
        folded = fold_contexts(cells, schema, cell)
        found = grubbs_columns(folded, x, detector.alpha, detector.sides).where("is_outlier").select("ctx", F.col("n").alias("population"), "score")
    else:
        part = take_slice(df, schema, detector, x, cells)
        found = verify(candidate_contexts(df.sparkSession, schema, cell), part, detector, x).where("is_outlier").select("ctx", "population", "score")
    if start is None:
        return found.withColumn("u", F.col("population"))
    both = found.withColumn("both", F.col("ctx").bitwiseAND(F.lit(start)))
    sizes = context_stats(cells, both.select(F.col("both").alias("ctx")).distinct()).select(F.col("ctx").alias("both"), F.col("n").alias("u"))
    return both.join(sizes, "both").drop("both")


def maximum_context(valid: DataFrame) -> DataFrame:
    """The non-private best (ctx, u); ties go to the larger mask."""
    return valid.agg(F.max_by(F.struct("ctx", "u"), F.struct("u", "ctx")).alias("b")).where("b is not null").select("b.ctx", "b.u")


def make_search(df: DataFrame, schema: ContextSchema, record_id, detector: Detector, start: int | str | None = "minimal", overlap: bool = False, noise=None, utility: str | None = None) -> Search:
    cell, x = lookup_record(df, schema, record_id)
    search = Search(schema, take_slice(df, schema, detector, x), detector, cell, x)
    search.start = starting_context(search, start, noise) if isinstance(start, str) else start
    search.overlap = overlap
    if utility is not None:
        search.utility, search.sensitivity = UTILITIES[utility]
    search.memo.clear()
    return search


def release_context(df: DataFrame, schema: ContextSchema, record_id, detector: Detector | str = "lof", utility: str = "population", method: str = "bfs", eps: float = 0.2, n: int = 50, start: int | str | None = "minimal", noise=None, ledger: BudgetLedger | None = None, **options) -> tuple[Release, OwnerLog]:
    """Publishes one context of a record; raises NoValidContext, charging nothing, if there is none."""
    detector = DETECTORS[detector]() if isinstance(detector, str) else detector
    noise = noise or SecureNoise()
    if ledger and eps > ledger.remaining() + 1e-12:
        ledger.charge(record_id, method, eps)  # raises
    needs_start = method in ("walk", "dfs", "bfs") or method.startswith("greedy") or utility == "overlap"
    search = make_search(df, schema, record_id, detector, start if needs_start else None, utility == "overlap", noise, None if utility in ("population", "overlap") else utility)
    outcome = search.run(method, eps, n, noise, **options)
    if ledger:
        ledger.charge(record_id, method, eps)
    c = Context(schema, outcome.ctx)
    return Release(record_id, c.mask, c.bits, c.to_sql(), eps), OwnerLog(method, detector.name, outcome)


def direct_release(df: DataFrame, schema: ContextSchema, record_id, detector: Detector, eps: float, noise, start: int | None = None) -> DataFrame:
    """(ctx, u): direct selection wholly as a DataFrame plan."""
    return exp_mechanism(valid_contexts(df, schema, record_id, detector, start), allocate("direct", eps, 0), noise, tag=(0, 0))


TRIAL_SCHEMA = "record_id string, trial int, method string, detector string, utility_name string, eps double, n int, seconds double, ctx long, utility double, ratio double, verified long, draws int, trials long"


def best_utility(df: DataFrame, schema: ContextSchema, record_id, detector: Detector, start: int | None = None) -> float:
    """The largest utility of a record's valid contexts, from one enumeration as a DataFrame plan; NaN if it has none."""
    found = valid_contexts(df, schema, record_id, detector, start).agg(F.max("u")).first()[0]
    return float("nan") if found is None else float(found)


def run_trials(spark, searches: dict[str, Search], grid: list[tuple[str, float, int]], repetitions: int, seed: int = 0, timed: bool = True, per_task: int = 10, best: dict[str, float] | None = None, setup: dict[str, float] | None = None) -> DataFrame:
    """Trials of every (method, eps, n) for every record, in one job: a row each with time, utility and ratio.

    `searches` go to the tasks with the code; each was checked to be small. `best` has the ratio's denominators (see
    best_utility); a record without one has no ratio. `setup` has the seconds of the scan, cells and slice of a record,
    which every release needs and which count in its time.
    """
    best, setup = best or {}, setup or {}
    rows = [(rid, m, float(e), int(n), t) for rid in searches for m, e, n in grid for t in range(0, repetitions, per_task)]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import time

        for batch in batches:
            out = []
            for rid, m, e, n, first in batch.itertuples(index=False):
                base = searches[rid]
                top = best.get(rid, float("nan"))
                for trial in range(first, min(first + per_task, repetitions)):
                    s = Search(base.schema, base.part, base.detector, base.cell, base.x, base.start, base.overlap, base.utility, base.sensitivity)
                    began = time.perf_counter()
                    try:
                        o = s.run(m, e, n, SeededNoise(seed), trial)
                    except NoValidContext:
                        continue
                    took = time.perf_counter() - began + setup.get(rid, 0.0)
                    out.append((rid, trial, m, base.detector.name, "overlap" if base.overlap else "population", e, n, took if timed else 0.0, o.ctx, o.utility, o.utility / top if top else float("nan"), o.verified, o.draws, o.trials))
            yield pd.DataFrame(out, columns=[c.split()[0] for c in TRIAL_SCHEMA.split(", ")])

    work = spark.createDataFrame(rows, "rid string, m string, e double, n int, t int").repartition(min(len(rows), 4 * spark.sparkContext.defaultParallelism))
    return work.mapInPandas(run, TRIAL_SCHEMA)


class Verifier:
    """Verification of contexts as plans, for tables whose slices are too large to ship.

    Moments come from cells against contexts. Values near the record are checkpointed once; LOF keeps the nearest
    distinct values on either side of each context (a bounded group), the histogram counts the record's bin by range.
    """

    def __init__(self, df: DataFrame, schema: ContextSchema, detector: Detector, x: int):
        self.detector, self.x = detector, x
        self.cells = cut(build_cells(df, schema))
        self.values = None
        if isinstance(detector, (LOF, Histogram)):
            ends = self.cells.agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.sum("n").alias("n")).toPandas()  # one row
            self.values = cut(detector.values(encode(df, schema), ends, x))

    def valid(self, contexts: DataFrame) -> DataFrame:
        """(ctx, u) of the valid ones, with their population."""
        stats = context_stats(self.cells, contexts.select("ctx").distinct())
        d, x = self.detector, self.x
        if type(d) is Grubbs and d.mode == "deviation":
            return grubbs_columns(stats, x, d.alpha, d.sides).where("is_outlier").select("ctx", F.col("n").alias("u"))
        if isinstance(d, LOF):
            return self._lof(cut(stats.select("ctx", "n")))
        if isinstance(d, Histogram):
            return self._histogram(stats)
        if d.wants_values:
            raise TypeError(f"{d.name} has no plan for contexts")

        def judge(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            # a context's moments are a slice of one cell that every context holds
            for b in batches:
                keep = [bool(d.flags(Slice(np.zeros(1, np.int64), *(np.array([r[k]], np.float64 if k in ("s", "ss") else np.int64) for k in ("n", "s", "ss", "lo", "hi"))), np.zeros(1, np.int64), x)[0][0]) for _, r in b.iterrows()]
                yield b.loc[keep, ["ctx", "n"]].rename(columns={"n": "u"})

        return stats.select("ctx", "n", F.col("s").cast("double"), F.col("ss").cast("double"), "lo", "hi").mapInPandas(judge, "ctx long, u long")

    def _held(self, contexts: DataFrame) -> DataFrame:
        return contexts.join(self.values, F.col("cell").bitwiseAND(F.col("ctx")) == F.col("cell"))

    def _lof(self, sizes: DataFrame) -> DataFrame:
        k, x, limit = self.detector.k, self.x, self.detector.threshold
        counts = self._held(sizes.where(F.col("n") > k)).groupBy("ctx", "n", "x").agg(F.sum("cnt").alias("cnt"))
        side = F.col("x") <= F.lit(x)
        near = Window.partitionBy("ctx", side).orderBy(F.abs(F.col("x") - F.lit(x)))
        few = counts.withColumn("r", F.row_number().over(near)).where(F.col("r") <= 3 * k + 1)

        def judge(frame: pd.DataFrame) -> pd.DataFrame:
            f = frame.sort_values("x")
            xs = f["x"].to_numpy(np.int64)
            score = local_factor(xs, f["cnt"].to_numpy(np.int64), int(np.searchsorted(xs, x)), k)
            return f[["ctx", "n"]].iloc[: int(score > limit)].rename(columns={"n": "u"})

        return few.groupBy("ctx").applyInPandas(judge, "ctx long, u long")

    def _histogram(self, stats: DataFrame) -> DataFrame:
        d, x = self.detector, self.x

        def bins(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for b in batches:
                n, lo, hi = (b[c].to_numpy(np.int64) for c in ("n", "lo", "hi"))
                many, first, end = d.intervals(n, lo, hi, x)
                yield pd.DataFrame({"ctx": b["ctx"], "n": n, "first": first, "end": end, "most": d.limit(n, many)})

        own = stats.where("hi > lo").select("ctx", "n", "lo", "hi").mapInPandas(bins, "ctx long, n long, first long, end long, most double").where("most > 1")
        counts = self._held(own).where("x >= first and x < end").groupBy("ctx", "n", "most").agg(F.sum("cnt").alias("c"))
        return counts.where("c < most").select("ctx", F.col("n").alias("u"))


def smallest_start(df: DataFrame, schema: ContextSchema, record_id, detector: Detector) -> int:
    """The starting context `minimal` from one enumeration as a plan, for many free bits."""
    found = valid_contexts(df, schema, record_id, detector).agg(F.min(F.struct(F.bit_count("ctx").alias("w"), "ctx")).alias("b")).first()["b"]
    if found is None:
        raise NoValidContext("the record is an outlier in no context")
    return found["ctx"]


def lockstep(df: DataFrame, schema: ContextSchema, record_id, method: str, eps: float, n: int, start: int, trials: int, noise, detector: Detector | None = None) -> DataFrame:
    """(trial, ctx, u): walk, dfs or bfs of many trials as DataFrames, one step of all trials at a time.

    For cells too many to ship: state, memo and candidates stay distributed, and each step's lineage is cut. Same
    noise keys as the in-memory search, hence the same draws.
    """
    detector = detector or Grubbs()
    spark = df.sparkSession
    cell, x = lookup_record(df, schema, record_id)
    verifier = Verifier(df, schema, detector, x)
    eps1 = allocate(method, eps, n)
    memo = cut(verifier.valid(spark.createDataFrame([(start,)], "ctx long")))
    if memo.isEmpty():
        raise NoValidContext("the search needs a context in which the record is an outlier")
    tried = spark.createDataFrame([(start,)], "ctx long")
    first = spark.range(trials).select(F.col("id").cast("int").alias("trial")).crossJoin(memo.select("ctx", "u"))  # one context for each trial
    visited = first.where("false").withColumn("step", F.lit(0))
    frontier = first.withColumn("depth", F.lit(0))
    if method != "bfs":
        visited, frontier = cut(first.withColumn("step", F.lit(0))), None
    top = first.withColumn("depth", F.lit(0))  # the stack's entries for dfs, the position for walk

    def expand(at: DataFrame) -> DataFrame:
        nonlocal memo, tried
        around = neighbors(at.select("trial", "ctx"), schema.t).where(F.col("neighbor").bitwiseAND(F.lit(cell)) == F.lit(cell)).select("trial", F.col("ctx").alias("parent"), F.col("neighbor").alias("ctx"))
        new = cut(around.select("ctx").distinct().join(tried, "ctx", "left_anti"))
        memo = cut(memo.unionByName(verifier.valid(new)))
        tried = cut(tried.unionByName(new))
        return around.join(memo, "ctx")

    def drawn(cands: DataFrame, step, factor: float) -> DataFrame:
        key = noise.column(F.col("trial"), F.lit(step), F.col("ctx"))
        return arg_max(cands, key, factor, ["trial"]).select("trial", "best.ctx", "best.u")

    steps = 0
    while steps < (n if method == "bfs" else n - 1):
        if method == "bfs":
            pick = cut(drawn(frontier, steps, eps1))
            if pick.isEmpty():
                break
            visited = cut(visited.unionByName(pick.withColumn("step", F.lit(steps))))
            frontier = frontier.join(pick.select("trial", "ctx"), ["trial", "ctx"], "left_anti").select("trial", "ctx", "u")
            kids = expand(pick).select("trial", "ctx", "u").join(visited.select("trial", "ctx"), ["trial", "ctx"], "left_anti")
            frontier = cut(frontier.unionByName(kids).dropDuplicates(["trial", "ctx"]))
            steps += 1
        elif method == "walk":
            kids = expand(top)
            order = noise_uniform_column(noise, F.col("trial"), F.lit(steps + 1), F.col("ctx"))
            top = cut(kids.withColumn("__order", order).groupBy("trial").agg(F.min_by(F.struct("ctx", "u"), F.struct("__order", "ctx")).alias("b")).select("trial", "b.ctx", "b.u"))
            if top.isEmpty():
                break
            visited = cut(visited.unionByName(top.withColumn("step", F.lit(steps + 1))))
            steps += 1
        else:  # dfs: trials whose top has no child go back, the others go on; each has its own count of visits
            current = top.groupBy("trial").agg(F.max_by(F.struct("ctx", "u", "depth"), "depth").alias("b")).select("trial", "b.*")
            sizes = visited.groupBy("trial").agg(F.count(F.lit(1)).alias("k")).where(F.col("k") < n)
            current = cut(current.join(sizes, "trial"))
            if current.isEmpty():
                break
            kids = expand(current).select("trial", "ctx", "u").join(visited.select("trial", "ctx"), ["trial", "ctx"], "left_anti").join(sizes, "trial")
            key = noise.column(F.col("trial"), F.col("k"), F.col("ctx"))
            pick = cut(arg_max(kids, key, eps1, ["trial"]).select("trial", "best.ctx", "best.u"))
            stuck = current.join(pick.select("trial"), "trial", "left_anti")
            top = top.join(stuck.select("trial", "depth"), ["trial", "depth"], "left_anti")
            deeper = pick.join(current.select("trial", "depth"), "trial").select("trial", "ctx", "u", (F.col("depth") + 1).alias("depth"))
            top = cut(top.unionByName(deeper))
            visited = cut(visited.unionByName(pick.withColumn("step", F.lit(0))))
    return drawn(visited, "final", eps1)


def noise_uniform_column(noise, *key):
    """The uniform number under a Gumbel column."""
    return F.exp(-F.exp(-noise.column(*key)))


def evaluate_masks(part: Slice, detector: Detector, masks: list[int], x: int) -> list[bool]:
    return detector.flags(part, np.array(masks, np.int64), x)[0].tolist()
