"""Outlier detectors and the verification of contexts.

A detector decides whether a record's metric is abnormal in a context's population. It works on a Slice: the cells'
exact moments and, where the detector needs them, counts of values near the record. Slices are small whatever the
table's size, so contexts are verified in batches of masks: in memory for searches, or by `verify` over a DataFrame
of contexts, partition by partition. All arithmetic on thresholds starts from exact integers.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from fractions import Fraction

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ctxrelease.functions.student import critical_column, critical_values
from ctxrelease.plans.cells import build_cells, encode
from ctxrelease.plans.runtime import BROADCAST_LIMIT_BYTES, bounded_broadcast, cut
from ctxrelease.schema import ContextSchema


class SliceTooLarge(ValueError):
    """What a detector needs of the data doesn't fit a task; use the distributed methods."""


@dataclass
class Slice:
    """Cells with moments; values near the record as (cell, x, cnt), sorted by x."""

    cell: np.ndarray
    n: np.ndarray
    s: np.ndarray
    ss: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    v_cell: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    v_x: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    v_cnt: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))

    def stats(self, ctxs: np.ndarray) -> dict[str, np.ndarray]:
        """Moments of contexts; sums of floats of exact integers, in the order of cells (which is fixed)."""
        inside = (self.cell[None, :] & ctxs[:, None]) == self.cell[None, :]
        big = np.iinfo(np.int64).max
        return {
            "n": inside @ self.n,
            "s": inside @ self.s,
            "ss": inside @ self.ss,
            "lo": np.where(inside, self.lo[None, :], big).min(1, initial=big),
            "hi": np.where(inside, self.hi[None, :], -big).max(1, initial=-big),
        }

    def value_cells(self) -> np.ndarray:
        """The cells with values."""
        return np.unique(self.v_cell)

    def between(self, cell: int, first: np.ndarray, end: np.ndarray) -> np.ndarray:
        """How many of a cell's rows lie in each range [first, end)."""
        own = self.v_cell == cell
        xs, total = self.v_x[own], np.concatenate([[0], np.cumsum(self.v_cnt[own])])
        return total[np.searchsorted(xs, end)] - total[np.searchsorted(xs, first)]


class Detector:
    name = "detector"
    #: Whether values near the record are needed besides moments.
    wants_values = False

    def flags(self, part: Slice, ctxs: np.ndarray, x: int) -> tuple[np.ndarray, np.ndarray]:
        """(is an outlier, score) of the metric x in each context."""
        raise NotImplementedError

    def values(self, encoded: DataFrame, cells: pd.DataFrame, x: int) -> DataFrame | None:
        return None


@dataclass(frozen=True)
class Grubbs(Detector):
    """Largest-deviation test: the studentised deviation against a critical value from Student's distribution.

    mode `deviation`: the record's own deviation exceeds it; `extreme`: the record is the farthest one, too.
    Removing the farthest value while it is significant is `iterative_flags`, for whole populations.
    """

    alpha: float = 0.05
    mode: str = "deviation"
    sides: int = 2
    name = "grubbs"

    def flags(self, part, ctxs, x):
        st = part.stats(ctxs)
        n = st["n"].astype(np.float64)
        with np.errstate(all="ignore"):
            mean = st["s"] / n
            var = (st["ss"] - st["s"] * mean) / (n - 1)
            score = np.abs(x - mean) / np.sqrt(var)
        score = np.where((n >= 3) & (var > 0), score, 0.0)
        out = score > critical_values(st["n"].astype(np.int64), self.alpha, self.sides)
        if self.mode == "extreme":
            out &= np.abs(x - mean) >= np.maximum(st["hi"] - mean, mean - st["lo"]) - 1e-9
        return out, score


@dataclass(frozen=True)
class Histogram(Detector):
    """Equal-width bins, as many as the root of the size; an outlier's bin holds less than a share of the rows.

    A bin holds its own record, so nothing is an outlier unless cut * n > 1. From n = (1/cut)^2 rows on an average
    bin falls below the share; cut="relative" compares with a share of the average bin instead.
    """

    share: float = 2.5e-3
    cut: str = "fixed"
    relative: float = 0.05
    bins: int | None = None
    name = "histogram"
    wants_values = True

    def limit(self, n: np.ndarray, bins: np.ndarray) -> np.ndarray:
        return self.share * n if self.cut == "fixed" else self.relative * n / np.maximum(bins, 1)

    def intervals(self, n, lo, hi, x):
        """(bins, first, end): the whole numbers of the record's bin."""
        bins = np.maximum(1, np.floor(np.sqrt(n.astype(np.float64)))).astype(np.int64) if self.bins is None else np.full(n.shape, self.bins, np.int64)
        wide = np.maximum(hi - lo, 1)
        b = np.minimum((x - lo) * bins // wide, bins - 1)
        first = lo - (-(b * wide) // bins)
        end = np.where(b == bins - 1, hi + 1, lo - (-((b + 1) * wide) // bins))
        return bins, first, end

    def values(self, encoded, cells, x):
        lo, hi, n = int(cells["lo"].min()), int(cells["hi"].max()), int(cells["n"].sum())
        least = int(1 / self.share) if self.cut == "fixed" else 4
        reach = (hi - lo) // max(1, int(np.sqrt(least)) if self.bins is None else self.bins) + 2
        return encoded.where((F.col("x") >= x - reach) & (F.col("x") <= x + reach)).groupBy("cell", "x").agg(F.count(F.lit(1)).alias("cnt"))

    def flags(self, part, ctxs, x):
        st = part.stats(ctxs)
        n = st["n"].astype(np.int64)
        ok = (n > 0) & (st["hi"] > st["lo"])
        lo, hi = np.where(ok, st["lo"], 0), np.where(ok, st["hi"], 1)
        bins, first, end = self.intervals(np.maximum(n, 1), lo, hi, x)
        limit = self.limit(n, bins)
        ok &= limit > 1  # the record's bin holds at least the record
        count = np.zeros(len(ctxs), np.int64)
        for cell in part.value_cells():
            inside = (cell & ctxs) == cell
            count[inside] += part.between(cell, first[inside], end[inside])
        return ok & (count < limit), np.where(ok, count, n).astype(np.float64)


@dataclass(frozen=True)
class LOF(Detector):
    """Local outlier factor of the one-dimensional metric, neighbourhoods with ties.

    In one dimension a value's factor depends on the 3k nearest distinct values on each side only, and the nearest
    values of a population are among the nearest values of its cells.
    """

    k: int = 10
    threshold: float = 1.5
    name = "lof"
    wants_values = True

    def values(self, encoded, cells, x):
        counts = encoded.groupBy("cell", "x").agg(F.count(F.lit(1)).alias("cnt"))
        sides = []
        for below in (True, False):
            side = counts.where(F.col("x") <= x if below else F.col("x") > x)
            order = Window.partitionBy("cell").orderBy(F.desc("x") if below else F.asc("x"))
            sides.append(side.withColumn("__r", F.row_number().over(order)).where(F.col("__r") <= 3 * self.k + 1).drop("__r"))
        return sides[0].unionByName(sides[1])

    def flags(self, part, ctxs, x):
        n = part.stats(ctxs)["n"]
        score = np.zeros(len(ctxs))
        for i, c in enumerate(ctxs):
            if n[i] > self.k:
                xs, cnt = self.distinct(part, c)
                p = int(np.searchsorted(xs, x))
                a, b = max(0, p - 3 * self.k), min(len(xs), p + 3 * self.k + 1)
                score[i] = local_factor(xs[a:b], cnt[a:b], p - a, self.k)
        return score > self.threshold, score


    def distinct(self, part: Slice, ctx) -> tuple[np.ndarray, np.ndarray]:
        """A context's distinct values and their counts; a slice's values lie in rising order."""
        inside = (part.v_cell & ctx) == part.v_cell
        xs = part.v_x[inside]
        first = np.flatnonzero(np.concatenate([[True], xs[1:] != xs[:-1]])) if len(xs) else np.zeros(0, np.int64)
        return xs[first], np.add.reduceat(part.v_cnt[inside], first) if len(xs) else first

    def reach(self, part: Slice, ctx: int, x: int) -> tuple[int, int]:
        """The range of values that the factor of x in a context depends on; open where fewer values lie on a side."""
        xs, _ = self.distinct(part, ctx)
        p, wide = int(np.searchsorted(xs, x)), 3 * self.k + 1
        big = np.iinfo(np.int64).max
        return (int(xs[p - wide]) if p >= wide else -big), (int(xs[p + wide]) if p + wide < len(xs) else big)


def _neighbour_distances(xs: np.ndarray, cnt: np.ndarray, d: np.ndarray, k: int) -> np.ndarray:
    """The distance within which each value has k other points."""
    n = len(xs)
    if n > k and cnt.max() == 1:
        # without ties the k nearest are a run of k+1 values around it: the run with the least reach
        left = np.arange(n)[:, None] - np.arange(k + 1)[None, :]
        ok = (left >= 0) & (left + k < n)
        left = np.where(ok, left, 0)
        return np.where(ok, np.maximum(xs[:, None] - xs[left], xs[left + k] - xs[:, None]), np.inf).min(1)
    order = np.argsort(d, axis=1, kind="stable")
    total = np.cumsum(cnt[order], axis=1) - 1  # the value itself is no neighbour
    return d[np.arange(n), order[np.arange(n), np.minimum((total < k).sum(1), n - 1)]]


def local_factor(xs: np.ndarray, cnt: np.ndarray, p: int, k: int) -> float:
    """The factor of distinct value p among values with counts."""
    xs = xs.astype(np.float64)
    d = np.abs(xs[:, None] - xs[None, :])
    reach = _neighbour_distances(xs, cnt, d, k)
    rows = np.flatnonzero(d[p] <= reach[p])  # p is among them
    some = d[rows]
    weight = np.where(some <= reach[rows, None], cnt[None, :], 0)
    weight[np.arange(len(rows)), rows] -= 1
    total = (weight * np.maximum(some, reach[None, :])).sum(1)
    with np.errstate(all="ignore"):
        density = np.where(total > 0, weight.sum(1) / total, np.inf)
    me = int(np.searchsorted(rows, p))
    own, w = density[me], weight[me][rows]
    others, w = density[w > 0], w[w > 0]
    if np.isinf(own):
        return 1.0 if np.isinf(others).all() else 0.0
    return float((w * others).sum() / w.sum() / own)


@dataclass(frozen=True)
class IQR(Detector):
    """Beyond the quartiles by a multiple of their distance. Quartiles are exact: the values of ranks ceil(n/4) and ceil(3n/4).

    Needs the counts of all distinct values; `take_slice` refuses datasets whose counts don't fit.
    """

    reach: float = 1.5
    name = "iqr"
    wants_values = True

    def values(self, encoded, cells, x):
        return encoded.groupBy("cell", "x").agg(F.count(F.lit(1)).alias("cnt"))

    def flags(self, part, ctxs, x):
        flag, score = np.zeros(len(ctxs), bool), np.zeros(len(ctxs))
        for i, c in enumerate(ctxs):
            inside = (part.v_cell & c) == part.v_cell
            total = np.cumsum(part.v_cnt[inside])
            if not len(total):
                continue
            n, xs = int(total[-1]), part.v_x[inside]
            low, high = (int(xs[np.searchsorted(total, -(-q * n // 4))]) for q in (1, 3))
            wide = high - low
            away = max(low - x, x - high, 0)
            flag[i], score[i] = away > self.reach * wide, away / wide if wide else float(away > 0)
        return flag, score


@dataclass(frozen=True)
class Plugin(Detector):
    """A caller's rule on moments: fn(n, mean, sd, lo, hi, x) -> (is an outlier, score), all arrays but x."""

    fn: Callable
    name: str = "plugin"

    def flags(self, part, ctxs, x):
        st = part.stats(ctxs)
        n = st["n"].astype(np.float64)
        with np.errstate(all="ignore"):
            mean = st["s"] / n
            sd = np.sqrt((st["ss"] - st["s"] * mean) / (n - 1))
        return self.fn(n, mean, sd, st["lo"], st["hi"], x)


def _z_rule(n, mean, sd, lo, hi, x, limit):
    with np.errstate(all="ignore"):
        z = np.where((n >= 2) & (sd > 0), np.abs(x - mean) / sd, 0.0)
    return z > limit, z


def ZScore(limit: float = 3.0) -> Plugin:
    return Plugin(lambda *a: _z_rule(*a, limit), f"zscore{limit:g}")


def _range_rule(n, mean, sd, lo, hi, x, share):
    wide = np.where(n >= 3, hi - lo, 0)
    with np.errstate(all="ignore"):
        at = np.where(wide > 0, np.abs(x - mean) / np.maximum(wide, 1), 0.0)
    return at > share, at


def RangeShare(share: float = 0.75) -> Plugin:
    """Far from the mean by a share of the whole range."""
    return Plugin(lambda *a: _range_rule(*a, share), f"range{share:g}")


DETECTORS: dict[str, Callable[[], Detector]] = {"grubbs": Grubbs, "histogram": Histogram, "lof": LOF, "iqr": IQR, "zscore": ZScore, "range": RangeShare}


def register_detector(name: str, make: Callable[[], Detector]) -> None:
    DETECTORS[name] = make


def take_slice(df: DataFrame, schema: ContextSchema, detector: Detector, x: int, cells: DataFrame | None = None) -> Slice:
    """Collects what verification needs, after checking that it is small."""
    cells = build_cells(df, schema) if cells is None else cells
    limit = BROADCAST_LIMIT_BYTES // 48
    top = cells.orderBy("cell").limit(limit + 1).toPandas()
    if len(top) > limit:
        raise SliceTooLarge(f"more than {limit} cells")
    arrays = {c: top[c].to_numpy(dtype=np.float64 if c in ("s", "ss") else np.int64) for c in ("cell", "n", "s", "ss", "lo", "hi")}
    wanted = detector.values(encode(df, schema), top, x) if detector.wants_values and len(top) else None
    if wanted is not None:
        v = wanted.limit(limit + 1).toPandas().sort_values(["x", "cell"], kind="stable")
        if len(v) > limit:
            raise SliceTooLarge(f"more than {limit} values near the record")
        arrays |= {"v_cell": v["cell"].to_numpy(np.int64), "v_x": v["x"].to_numpy(np.int64), "v_cnt": v["cnt"].to_numpy(np.int64)}
    return Slice(**arrays)


def verify(contexts: DataFrame, part: Slice, detector: Detector, x: int) -> DataFrame:
    """(ctx, population, is_outlier, score) of a DataFrame of contexts; the slice goes to tasks with the code."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for at in range(0, len(batch), 4096):
                ctxs = batch["ctx"].to_numpy(np.int64)[at : at + 4096]
                flag, score = detector.flags(part, ctxs, x)
                yield pd.DataFrame({"ctx": ctxs, "population": part.stats(ctxs)["n"], "is_outlier": flag, "score": score})

    return contexts.select("ctx").mapInPandas(run, "ctx long, population long, is_outlier boolean, score double")


def grubbs_columns(stats: DataFrame, x: int, alpha: float = 0.05, sides: int = 2) -> DataFrame:
    """Adds score and is_outlier to a DataFrame of folded contexts, by built-in expressions only."""
    n, s, ss = F.col("n").cast("double"), F.col("s").cast("double"), F.col("ss").cast("double")
    mean = s / n
    var = (ss - s * mean) / (n - 1)
    score = F.when((F.col("n") >= 3) & (var > 0), F.abs(F.lit(float(x)) - mean) / F.sqrt(var)).otherwise(0.0)
    return stats.withColumn("score", score).withColumn("is_outlier", F.coalesce(F.col("score") > critical_column(F.col("n"), alpha, sides), F.lit(False)))


def grubbs_bounds(stats: DataFrame, alpha: float = 0.05, sides: int = 2) -> DataFrame:
    """(ctx, n, mean, reach) of contexts in which some value may be an outlier: those farther than `reach` from the mean."""
    n, s, ss = F.col("n").cast("double"), F.col("s").cast("double"), F.col("ss").cast("double")
    mean = s / n
    return stats.where("n >= 3").select("ctx", "n", mean.alias("mean"), (critical_column(F.col("n"), alpha, sides) * F.sqrt(F.greatest((ss - s * mean) / (n - 1), F.lit(0.0)))).alias("reach")).where("reach > 0")


def iterative_outliers(values: np.ndarray, counts: np.ndarray, alpha: float = 0.05, moments: tuple[int, int, int] | None = None) -> set[int]:
    """Values removed one by one while the farthest is significant. values: distinct, sorted whole numbers.

    moments: (n, sum, sum of squares) of the population where `values` holds its ends only.
    """
    lo, hi, left = 0, len(values) - 1, counts.astype(np.int64).copy()
    n, s, ss = moments or (int(left.sum()), sum(int(v) * int(c) for v, c in zip(values, left)), sum(int(v) ** 2 * int(c) for v, c in zip(values, left)))
    gone: set[int] = set()
    while n >= 3 and lo <= hi:
        mean = Fraction(s, n)
        var = (ss - s * mean) / (n - 1)
        if var <= 0:
            break
        low, high = mean - int(values[lo]), int(values[hi]) - mean
        far = hi if high >= low else lo
        if float(max(low, high)) / float(var) ** 0.5 <= critical_values(np.array([n]), alpha)[0]:
            break
        v = int(values[far])
        gone.add(v)
        n, s, ss = n - 1, s - v, ss - v * v
        left[far] -= 1
        if not left[far]:
            lo, hi = (lo + 1, hi) if far == lo else (lo, hi - 1)
    return gone


def iterative_flags(df: DataFrame, schema: ContextSchema, ctx: int, alpha: float = 0.05, window: int = 1000) -> DataFrame:
    """(record_id, x, is_outlier) of every record of a context, by Grubbs' test repeated without the farthest value.

    Only extreme values can go, so the driver sees moments and the `window` lowest and highest distinct values; if all
    of a side's go, the window doubles and the removal starts again. Ties with a removed value go with it.
    """
    rows = encode(df, schema).where(F.col("cell").bitwiseAND(F.lit(ctx)) == F.col("cell"))
    d = F.col("x").cast("decimal(18,0)")
    n, s, ss = rows.agg(F.count(F.lit(1)), F.sum(d.cast("decimal(28,0)")), F.sum((d * d).cast("decimal(36,0)"))).first()
    counts = rows.groupBy("x").agg(F.count(F.lit(1)).alias("cnt"))
    while n >= 3:
        low, high = ([(r[0], r[1]) for r in counts.orderBy(order).limit(window).collect()] for order in (F.asc("x"), F.desc("x")))
        ends = dict([*low, *high])
        gone = iterative_outliers(np.array(sorted(ends)), np.array([ends[v] for v in sorted(ends)]), alpha, (n, int(s), int(ss)))
        whole = len(low) < window
        if whole or not (low[-1][0] in gone or high[-1][0] in gone):
            break
        window *= 2
    else:
        gone = set()
    below, above = [v for v in gone if v < int(s or 0) / max(n, 1)], [v for v in gone if v >= int(s or 0) / max(n, 1)]
    out = F.lit(False)
    if below:
        out = out | (F.col("x") <= max(below))
    if above:
        out = out | (F.col("x") >= min(above))
    return rows.select("record_id", "x", out.alias("is_outlier"))


def flag_all(df: DataFrame, schema: ContextSchema, detector: Detector, ctx: int) -> DataFrame:
    """(record_id, x, is_outlier) of every record of one context, as DataFrame plans."""
    rows = encode(df, schema).where(F.col("cell").bitwiseAND(F.lit(ctx)) == F.col("cell"))
    d = F.col("x").cast("decimal(18,0)")
    total = rows.agg(F.count(F.lit(1)).alias("n"), F.sum(d.cast("decimal(28,0)")).alias("s"), F.sum((d * d).cast("decimal(36,0)")).alias("ss"), F.min("x").alias("lo"), F.max("x").alias("hi")).first()
    n = total["n"]
    if isinstance(detector, Grubbs):
        if n < 3:
            return rows.select("record_id", "x", F.lit(False).alias("is_outlier"))
        mean = float(total["s"]) / n
        sd = ((float(total["ss"]) - float(total["s"]) * mean) / (n - 1)) ** 0.5
        crit = float(critical_values(np.array([n]), detector.alpha, detector.sides)[0])
        far = F.abs(F.col("x").cast("double") - mean) / F.lit(sd) > crit if sd > 0 else F.lit(False)
        return rows.select("record_id", "x", far.alias("is_outlier"))
    if isinstance(detector, Histogram):
        if n == 0 or total["lo"] == total["hi"]:
            return rows.select("record_id", "x", F.lit(False).alias("is_outlier"))
        bins = max(1, int(np.floor(np.sqrt(n)))) if detector.bins is None else detector.bins
        wide = total["hi"] - total["lo"]
        b = F.least(F.expr(f"((x - {total['lo']}L) * {bins}L) div {wide}L"), F.lit(bins - 1))
        limit = float(detector.limit(np.array([n]), np.array([bins]))[0])
        binned = rows.withColumn("bin", b)
        rare = binned.groupBy("bin").agg(F.count(F.lit(1)).alias("c"))  # at most `bins` rows
        return binned.join(rare, "bin").select("record_id", "x", (F.col("c") < limit).alias("is_outlier"))
    if isinstance(detector, LOF):
        return _lof_all(rows, detector)
    raise TypeError(f"{detector.name} has no plan for whole populations")


def ranked_values(values: DataFrame, parts: int | None = None) -> DataFrame:
    """Adds `rank` (from 0) to distinct x in rising order, in range partitions: counts of partitions come before ranks in them.

    The cut points are checkpointed with the rows, so that both passes see the same partitions.
    """
    spark = values.sparkSession
    parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = cut(values.repartitionByRange(parts, "x").withColumn("__part", F.spark_partition_id()))
    sizes = sorted((r[0], r[1]) for r in dealt.groupBy("__part").agg(F.count(F.lit(1))).collect())  # a row per partition
    starts, at = [], 0
    for p, k in sizes:
        starts.append((p, at))
        at += k
    base = bounded_broadcast(spark.createDataFrame(starts or [(0, 0)], "__part int, __start long"), parts, 16)
    nth = F.row_number().over(Window.partitionBy("__part").orderBy("x")) - 1
    return dealt.withColumn("__nth", nth).join(base, "__part").withColumn("rank", F.col("__start") + F.col("__nth")).drop("__part", "__start", "__nth")


def _lof_all(rows: DataFrame, detector: LOF) -> DataFrame:
    """LOF of all records: distinct values in blocks by rank, each with copies of the 3k+1 values on either side."""
    k = detector.k
    ranked = ranked_values(rows.groupBy("x").agg(F.count(F.lit(1)).alias("cnt")))
    size = 4096
    margin = 3 * k + 1
    block = F.floor(F.col("rank") / size)
    blocks = ranked.withColumn("block", F.explode(F.array_distinct(F.array(F.floor((F.col("rank") - margin) / size), block, F.floor((F.col("rank") + margin) / size)))))

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        f = frame.sort_values("x")
        xs, cnt, rank, own = f["x"].to_numpy(np.int64), f["cnt"].to_numpy(np.int64), f["rank"].to_numpy(), int(f["block"].iloc[0])
        out = []
        for p in np.flatnonzero(rank // size == own):
            a, b = max(0, p - 3 * k), min(len(xs), p + 3 * k + 1)
            few = cnt[a:b].sum() <= k
            out.append((xs[p], 0.0 if few else local_factor(xs[a:b], cnt[a:b], int(p - a), k)))
        return pd.DataFrame(out, columns=["x", "score"]).astype({"x": "int64", "score": "float64"})

    scores = blocks.groupBy("block").applyInPandas(run, "x long, score double")
    return rows.join(scores, "x").select("record_id", "x", (F.col("score") > detector.threshold).alias("is_outlier"))
