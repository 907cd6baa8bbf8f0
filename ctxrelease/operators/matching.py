"""How often neighbouring datasets keep a record's valid contexts, and how far selection probabilities move.

A neighbour is a delta on the cells: a removed or added record changes one cell's moments. No dataset is copied;
deltas are dealt to tasks with the base slice, and each task compares enumerations in memory.
"""

from __future__ import annotations

import atexit
import os
import shutil
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, replace
from functools import lru_cache
from urllib.parse import urlparse

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxrelease.functions.mechanism import allocate
from ctxrelease.plans.cells import build_cell_values, encode
from ctxrelease.plans.runtime import BROADCAST_LIMIT_BYTES, shared_dir
from ctxrelease.schema import ContextSchema

from .detectors import IQR, LOF, Detector, Histogram, Slice, SliceTooLarge, take_slice
from .search import Search


def pick_records(df: DataFrame, schema: ContextSchema, k: int, seed: int, exclude: list | None = None) -> DataFrame:
    """(record_id, cell, x) of k records in the order of a seeded hash."""
    rows = encode(df, schema)
    if exclude:
        rows = rows.where(~F.col("record_id").isin(*exclude))
    return rows.orderBy(F.xxhash64(F.col("record_id"), F.col("x"), F.lit(seed)), "record_id").limit(k)


def shared_slice(df: DataFrame, schema: ContextSchema, cells: DataFrame | None = None) -> Slice:
    """A slice with the counts of all distinct values, for many records at once; refused where they don't fit.

    Where they don't, give each record its own slice by take_slice.
    """
    return take_slice(df, schema, IQR(), 0, cells)


@lru_cache(maxsize=None)
def _mapped(path: str) -> np.ndarray:
    return np.memmap(path, np.int64, "r")


@dataclass
class StoredSlice(Slice):
    """Cells with moments; the counts of all their values lie in files of a folder that driver and tasks share.

    A cell has its distinct values in rising order, and the running sum of their counts after a zero. Tasks map the files, so
    they read only the pages that a search touches. `gone` holds removed (cell, x).
    """

    folder: str = ""
    gone: tuple = ()

    def value_cells(self) -> np.ndarray:
        return self.cell

    def values_of(self, cell: int) -> tuple[np.ndarray, np.ndarray]:
        return _mapped(f"{self.folder}/{cell}.x"), _mapped(f"{self.folder}/{cell}.sum")

    def between(self, cell: int, first: np.ndarray, end: np.ndarray) -> np.ndarray:
        xs, total = self.values_of(cell)
        left = np.array(sorted(x for c, x in self.gone if c == cell), np.int64)
        return total[np.searchsorted(xs, end)] - total[np.searchsorted(xs, first)] - (np.searchsorted(left, end) - np.searchsorted(left, first))

    def near(self, x: int, wide: int) -> Slice:
        """A slice with the nearest distinct values of each cell."""
        parts = []
        for cell in self.cell:
            xs, total = self.values_of(cell)
            p = int(np.searchsorted(xs, x, "right"))
            a, b = max(0, p - wide - 1), min(len(xs), p + wide)
            parts.append((np.full(b - a, cell, np.int64), np.array(xs[a:b]), np.diff(total[a : b + 1])))
        v_cell, v_x, v_cnt = (np.concatenate(c) for c in zip(*parts))
        order = np.lexsort((v_cell, v_x))
        return Slice(self.cell, self.n, self.s, self.ss, self.lo, self.hi, v_cell[order], v_x[order], v_cnt[order])


def stored_slice(df: DataFrame, schema: ContextSchema, cells: DataFrame | None = None) -> StoredSlice:
    """A slice whose values are files beside the session's checkpoints, one task a cell, streamed; for tables of any size."""
    spark = df.sparkSession
    root = shared_dir(spark)
    if urlparse(root).scheme not in ("", "file"):
        raise SliceTooLarge(f"{root} can't be mapped by tasks; spark.checkpoint.dir must be a mounted folder")
    folder = f"{urlparse(root).path}/values-{uuid.uuid4().hex}"
    os.makedirs(folder)
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    part = take_slice(df, schema, Detector(), 0, cells)

    def write(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        """A task's rows come cell by cell, by rising value; a cell's files get their names when they are whole."""
        tag, cell, sums, files = uuid.uuid4().hex, None, 0, ()

        def close():
            for f, kind in zip(files, ("x", "sum")):
                f.close()
                os.replace(f.name, f"{folder}/{cell}.{kind}")

        for batch in batches:
            for c, g in batch.groupby("cell", sort=False):
                if c != cell:
                    close()
                    cell, sums = int(c), 0
                    files = tuple(open(f"{folder}/{tag}-{cell}.{kind}", "wb") for kind in ("x", "sum"))
                    files[1].write(np.zeros(1, np.int64).tobytes())
                total = np.cumsum(g["cnt"].to_numpy(np.int64)) + sums
                sums = int(total[-1])
                files[0].write(g["x"].to_numpy(np.int64).tobytes())
                files[1].write(total.tobytes())
        close()
        yield pd.DataFrame({"done": [1]})

    build_cell_values(df, schema).repartition("cell").sortWithinPartitions("cell", "x").mapInPandas(write, "done int").count()
    return StoredSlice(part.cell, part.n, part.s, part.ss, part.lo, part.hi, folder=folder)


def all_values(df: DataFrame, schema: ContextSchema, cells: DataFrame | None = None) -> Slice:
    """The counts of all distinct values: shipped with the code where they fit, else stored."""
    try:
        return shared_slice(df, schema, cells)
    except SliceTooLarge:
        return stored_slice(df, schema, cells)


def own_slice(part: Slice, detector: Detector, x: int, removals: int = 0) -> Slice:
    """A record's part of a shared slice: for LOF the nearest distinct values of each cell, with spares for removals."""
    if not isinstance(detector, LOF):
        if isinstance(part, StoredSlice) and detector.wants_values and not isinstance(detector, Histogram):
            raise TypeError(f"{detector.name} doesn't work on stored values")
        return part
    wide = 3 * detector.k + 1 + removals
    if isinstance(part, StoredSlice):
        return part.near(x, wide)
    keep = np.zeros(len(part.v_x), bool)
    for cell in part.cell:
        own = np.flatnonzero(part.v_cell == cell)  # by rising x
        p = int(np.searchsorted(part.v_x[own], x, "right"))
        keep[own[max(0, p - wide - 1) : p + wide]] = True
    return replace(part, v_cell=part.v_cell[keep], v_x=part.v_x[keep], v_cnt=part.v_cnt[keep])


def outliers_among(spark: SparkSession, schema: ContextSchema, part: Slice, detector: Detector, records: list[tuple[int, int]]) -> list[int]:
    """Which of some records (cell, x) have a non-empty valid set: their places in the list, in rising order."""

    def judge(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            keep = []
            for k, cell, x in batch.itertuples(index=False):
                s = Search(schema, own_slice(part, detector, int(x)), detector, int(cell), int(x))
                masks = s.all_candidates()
                # small contexts first: most outliers show there, and one valid context is enough
                if any(s.valid_among(masks[at : at + 64]) for at in range(0, len(masks), 64)):
                    keep.append(k)
            yield pd.DataFrame({"k": keep}, dtype="int64")

    some = [(k, int(c), int(x)) for k, (c, x) in enumerate(records)]
    frame = spark.createDataFrame(some, "k long, cell long, x long").repartition(4 * spark.sparkContext.defaultParallelism)
    return sorted(r[0] for r in frame.mapInPandas(judge, "k long").collect())


def highest_outlier(df: DataFrame, schema: ContextSchema, detector: Detector, below: int) -> object | None:
    """The id of the record with the largest metric up to `below` that has a valid context, ties to the smaller id; None without one.

    Records of a cell with equal metrics are judged once. A value with more than k copies in its own cell has them in every context
    that holds it, so its density is infinite and its local outlier factor at most 1.
    """
    spark = df.sparkSession
    pairs = encode(df, schema).where(F.col("x") <= below).groupBy("cell", "x").agg(F.count(F.lit(1)).alias("cnt"), F.min("record_id").alias("record_id"))
    if isinstance(detector, LOF) and detector.threshold >= 1:
        pairs = pairs.where(F.col("cnt") <= detector.k)
    limit = BROADCAST_LIMIT_BYTES // 48
    found = pairs.orderBy(F.desc("x"), "record_id").limit(limit + 1).select("record_id", "cell", "x").collect()
    if len(found) > limit:
        raise SliceTooLarge(f"more than {limit} values that may be outliers")
    if not found:
        return None
    part = shared_slice(df, schema)
    step = 4 * spark.sparkContext.defaultParallelism
    for at in range(0, len(found), step):
        hits = outliers_among(spark, schema, part, detector, [(r["cell"], r["x"]) for r in found[at : at + step]])
        if hits:
            return found[at + hits[0]]["record_id"]
    return None


def random_outliers(spark: SparkSession, df: DataFrame, schema: ContextSchema, part: Slice, detector: Detector, many: int, seed: int = 11, tries: int = 4096) -> list[tuple[object, int, int]]:
    """(id, cell, x) of up to `many` records with a non-empty valid set, in the order of a seeded hash.

    Half of the tries are records drawn from all rows, half from those farther than two deviations from the whole
    table's mean, where valid sets are less rare.
    """
    rows = encode(df, schema)
    n, s, ss = (float(part.n.sum()), float(part.s.sum()), float(part.ss.sum()))
    spread = max((ss - s * s / n) / n, 0.0) ** 0.5
    order = (F.xxhash64(F.col("record_id"), F.col("x"), F.lit(seed)), "record_id")
    found = rows.orderBy(*order).limit(tries // 2).unionByName(rows.where(F.abs(F.col("x") - s / n) > 2 * spread).orderBy(*order).limit(tries // 2))
    picked = sorted({(r[1], r[2], str(r[0])): r[0] for r in found.collect()}.items(), key=lambda kv: zlib.crc32(f"{seed}|{kv[0][2]}".encode()))

    out: list[tuple[object, int, int]] = []
    step = max(64, 2 * many)
    for at in range(0, len(picked), step):
        hits = outliers_among(spark, schema, part, detector, [(c, x) for (c, x, _), _ in picked[at : at + step]])
        out += [(picked[at + k][1], picked[at + k][0][0], picked[at + k][0][1]) for k in hits]
        if len(out) >= many:
            break
    return out[:many]


def remove_records(part: Slice, removed: list[tuple[int, int]], edges: dict[int, tuple[np.ndarray, np.ndarray]]) -> Slice:
    """The slice without some (cell, x). `edges`: each cell's smallest and largest values, more than are removed."""
    n, s, ss, lo, hi, cnt = (a.copy() for a in (part.n, part.s, part.ss, part.lo, part.hi, part.v_cnt))
    gone: dict[int, list[int]] = {}
    for cell, x in removed:
        i = int(np.searchsorted(part.cell, cell))
        n[i], s[i], ss[i] = n[i] - 1, s[i] - x, ss[i] - float(x) * x
        gone.setdefault(cell, []).append(x)
        at = np.flatnonzero((part.v_cell == cell) & (part.v_x == x))
        if len(at):
            cnt[at[0]] -= 1
    for cell, xs in gone.items():
        i = int(np.searchsorted(part.cell, cell))
        low, high = (list(e) for e in edges[cell])
        for x in xs:
            for e in (low, high):
                if x in e:
                    e.remove(x)
        if n[i] > 0:
            lo[i], hi[i] = min(low), max(high)
    keep, live = n > 0, cnt > 0
    if isinstance(part, StoredSlice):
        part = replace(part, gone=(*part.gone, *removed))
    return replace(part, cell=part.cell[keep], n=n[keep], s=s[keep], ss=ss[keep], lo=lo[keep], hi=hi[keep], v_cell=part.v_cell[live], v_x=part.v_x[live], v_cnt=cnt[live])


def cell_edges(df: DataFrame, schema: ContextSchema, k: int, cells: set[int] | None = None) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """The k+1 smallest and largest values of each cell, or of some: enough to know their range after k removals."""
    from pyspark.sql import Window

    own = encode(df, schema)
    if cells is not None:
        own = own.where(F.col("cell").isin(*cells))
    rows = own.groupBy("cell", "x").agg(F.least(F.count(F.lit(1)), F.lit(k + 1)).cast("int").alias("c")).select("cell", "x", F.explode(F.array_repeat(F.lit(0), F.col("c"))).alias("copy"))
    out: dict[int, tuple[np.ndarray, np.ndarray]] = {}
    parts = []
    for side, order in (("low", F.asc("x")), ("high", F.desc("x"))):
        w = Window.partitionBy("cell").orderBy(order)
        parts.append(rows.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k + 1).select("cell", "x", F.lit(side).alias("side")))
    limit = BROADCAST_LIMIT_BYTES // 32
    found = parts[0].unionByName(parts[1]).limit(limit + 1).toPandas()
    if len(found) > limit:
        raise SliceTooLarge(f"more than {limit} smallest and largest values of cells")
    for cell, g in found.groupby("cell"):
        out[int(cell)] = (g.loc[g["side"] == "low", "x"].to_numpy(), g.loc[g["side"] == "high", "x"].to_numpy())
    return out


MATCH_SCHEMA = "detector string, delta_size int, record_id string, pair int, exact boolean, jaccard double, max_ratio double, log_ratio double"


class Enumeration:
    """All candidate contexts of a record, judged on a slice, and judged anew after removals.

    A removal can only change contexts that hold a removed record; for LOF, only those in which a removed value lies
    among the values near the record that its factor depends on.
    """

    def __init__(self, schema: ContextSchema, part: Slice, detector: Detector, cell: int, x: int):
        self.detector, self.part, self.cell, self.x = detector, part, cell, x
        self.ctxs = np.array(Search(schema, part, detector, cell, x).all_candidates(), np.int64)
        self.valid, self.size = self._judge(part, self.ctxs)
        if isinstance(detector, LOF):
            spans = [detector.reach(part, int(c), x) for c in self.ctxs]
            self.low, self.high = np.array([a for a, _ in spans]), np.array([b for _, b in spans])

    def _judge(self, part: Slice, ctxs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        valid, size = np.zeros(len(ctxs), bool), np.zeros(len(ctxs))
        for at in range(0, len(ctxs), 2048):
            some = ctxs[at : at + 2048]
            valid[at : at + 2048], size[at : at + 2048] = self.detector.flags(part, some, self.x)[0], part.stats(some)["n"]
        return valid, size

    def without(self, removed: list[tuple[int, int]], edges) -> tuple[np.ndarray, np.ndarray]:
        """(valid, population) by context after a removal."""
        part = remove_records(self.part, removed, edges)
        touched = np.zeros(len(self.ctxs), bool)
        size = self.size.copy()
        for cell, x in removed:
            held = (self.ctxs & cell) == cell
            size[held] -= 1
            touched |= held & (self.low <= x) & (x <= self.high) if isinstance(self.detector, LOF) else held
        valid = self.valid.copy()
        if touched.any():
            valid[touched] = self._judge(part, self.ctxs[touched])[0]
        return valid, size


def _law(size: np.ndarray, valid: np.ndarray, eps1: float) -> np.ndarray:
    """Logarithms of selection probabilities, minus infinity where a context isn't valid."""
    score = np.where(valid, eps1 * size, -np.inf)
    top = score.max()
    return score - top - np.log(np.exp(score - top).sum())


def match_pairs(spark: SparkSession, schema: ContextSchema, records: list[tuple[object, int, int]], part: Slice, detector: Detector, deltas: dict[int, list[list[tuple[int, int]]]], edges, eps: float = 0.2) -> DataFrame:
    """A row for each (record, neighbour): do the valid sets agree, and the largest probability ratio on their intersection.

    records: (id, cell, x); part: a shared slice; deltas: by size, lists of removed (cell, x). A record's neighbours share one task and
    one enumeration; records without a valid context give no rows.
    """
    eps1 = allocate("direct", eps, 0)
    known = {str(rid): (cell, x) for rid, cell, x in records}
    most = max(deltas, default=0)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for (rid,) in batch.itertuples(index=False):
                cell, x = known[rid]
                base = Enumeration(schema, own_slice(part, detector, x, most), detector, cell, x)
                if not base.valid.any():
                    continue
                law = _law(base.size, base.valid, eps1)
                for size, sets in deltas.items():
                    for k, gone in enumerate(sets):
                        valid, left = base.without([d for d in gone if d != (cell, x)], edges)  # the record itself stays
                        common, union = int((base.valid & valid).sum()), int((base.valid | valid).sum())
                        log_ratio = float("nan")
                        if common:
                            both = base.valid & valid
                            log_ratio = float(np.abs(law[both] - _law(left, valid, eps1)[both]).max())
                        with np.errstate(over="ignore"):  # the logarithm stays where the ratio is beyond doubles
                            ratio = float(np.exp(log_ratio))
                        out.append((detector.name, size, rid, k, bool((base.valid == valid).all()), common / union if union else 1.0, ratio, log_ratio))
            yield pd.DataFrame(out, columns=[c.split()[0] for c in MATCH_SCHEMA.split(", ")])

    frame = spark.createDataFrame([(r,) for r in known], "rid string").repartition(min(max(1, len(known)), 4 * spark.sparkContext.defaultParallelism))
    return frame.mapInPandas(run, MATCH_SCHEMA)


def match_summary(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy("detector", "delta_size").agg(F.count(F.lit(1)).alias("pairs"), F.avg(F.col("exact").cast("double")).alias("exact_rate"), F.avg("jaccard").alias("jaccard"))


def ratio_summary(pairs: DataFrame, eps: float = 0.2) -> DataFrame:
    """Largest probability ratio on non-matching pairs, against the bound of the budget."""
    apart = pairs.where("not exact and not isnan(max_ratio)")
    bound = float(np.exp(eps))
    return apart.groupBy("detector").agg(F.max("max_ratio").alias("max_ratio"), F.lit(bound).alias("bound"), F.count_if(F.col("max_ratio") > bound).alias("violations"))
