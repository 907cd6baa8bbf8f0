"""The experiments on the given tables, and streams. Times and trained noise have no SQL; budgets and sizes are parameters."""

from __future__ import annotations

import math
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxrelease.functions import mechanism as mech
from ctxrelease.operators import detectors as det
from ctxrelease.operators import matching, measures, release
from ctxrelease.plans import cells as pl
from ctxrelease.plans.runtime import cut
from ctxrelease.sources import workloads as wl
from ctxrelease.streaming import windows

QUERIES: dict = {}
SQL: dict[str, str] = {}

#: Repetitions, samples and budget of the published runs.
REPETITIONS, SAMPLES, EPS = 200, 50, 0.2
#: Random outliers and neighbours of each size in matching, and outliers in the ratio test.
OUTLIERS, NEIGHBOURS, RATIO_OUTLIERS = 100, 50, 200


def trials(spark: SparkSession, sf_dir: str, dataset: str, grid, detector: det.Detector | None = None, overlap: bool = False, repetitions: int = REPETITIONS, rank: int = 0) -> DataFrame:
    """Seeded trials for the record of a given rank; the starting context is drawn from the valid ones.

    A record without a valid context gives way to the next lower one that has some. Without any, no trial publishes a
    context, and each has a row without results. A release's time is that of its search and of the scan, cells and slice
    before it, which are measured once.
    """
    df, schema = wl.workload(spark, sf_dir, dataset)
    detector = detector or det.LOF()
    rid = wl.top_records(df, schema, rank + 1)[rank]
    if math.isnan(release.best_utility(df, schema, rid, detector)):
        rid = matching.highest_outlier(df, schema, detector, pl.lookup_record(df, schema, rid)[1])
        if rid is None:
            rows = [(None, t, m, detector.name, "overlap" if overlap else "population", float(e), int(k), *[None] * 7) for m, e, k in grid for t in range(repetitions)]
            return spark.createDataFrame(rows, release.TRIAL_SCHEMA)
    began = time.perf_counter()
    search = release.make_search(df, schema, rid, detector, "uniform", overlap, mech.SeededNoise(7))
    setup = time.perf_counter() - began
    best = release.best_utility(df, schema, rid, detector, search.start if overlap else None)
    return release.run_trials(spark, {str(rid): search}, grid, repetitions, best={str(rid): best}, setup={str(rid): setup})


def _summary(t: DataFrame, by: list[str]) -> DataFrame:
    """Runtime, utility with its interval, and counters in one pass over the trials."""
    return t.groupBy(*by).agg(*measures.runtime_columns(), *measures.utility_columns(), *measures.counter_columns())


def _add(name: str, fn) -> None:
    QUERIES[name] = fn


_METHODS = [(m, EPS, SAMPLES) for m in mech.METHODS]
for _d in ("e14", "li12", "li16"):
    _add(f"w_samplers_{_d}", lambda s, d, n=_d: _summary(trials(s, d, n, _METHODS), ["method"]))
    _add(f"w_overlap_{_d}", lambda s, d, n=_d: _summary(trials(s, d, n, [("dfs", EPS, SAMPLES), ("bfs", EPS, SAMPLES)], overlap=True), ["method"]))
    _add(f"w_epsilon_{_d}", lambda s, d, n=_d: _summary(trials(s, d, n, [("bfs", e, SAMPLES) for e in (0.05, 0.1, 0.2, 0.4)]), ["eps"]))
    _add(f"w_samples_{_d}", lambda s, d, n=_d: _summary(trials(s, d, n, [("bfs", EPS, k) for k in (25, 50, 100, 200)]), ["n"]))
    _add(f"w_detectors_{_d}", lambda s, d, n=_d: _detectors(s, d, n))
for _d in ("e14", "li12"):
    _add(f"w_match_{_d}", lambda s, d, n=_d: matching.match_summary(match(s, d, n)))
    _add(f"w_ratio_{_d}", lambda s, d, n=_d: matching.ratio_summary(match(s, d, n, RATIO_OUTLIERS, NEIGHBOURS, (1,))))


def _detectors(spark, sf_dir, dataset):
    parts = [trials(spark, sf_dir, dataset, [("bfs", EPS, SAMPLES)], k()) for k in (det.Grubbs, det.Histogram)]
    return _summary(parts[0].unionByName(parts[1]), ["detector"])


def match(spark: SparkSession, sf_dir: str, dataset: str, outliers: int = OUTLIERS, neighbours: int = NEIGHBOURS, sizes=(1, 5, 10, 25)) -> DataFrame:
    """Pairs (random outlier, neighbouring dataset) for all detectors."""
    df, schema = wl.workload(spark, sf_dir, dataset)
    cells = cut(pl.build_cells(df, schema))
    part = matching.all_values(df, schema, cells)
    edges = matching.cell_edges(df, schema, max(sizes))
    # one draw of records in the order of a seeded hash, dealt to the neighbours: no record is drawn twice for one of them
    drawn = [(r["cell"], r["x"]) for r in matching.pick_records(df, schema, neighbours * sum(sizes), 1000).collect()]
    gone, at = {}, 0
    for k in sizes:
        gone[k] = [drawn[at + j * k : at + (j + 1) * k] for j in range(neighbours)]
        at += neighbours * k
    out = None
    for make in (det.Grubbs, det.Histogram, det.LOF):
        known = matching.random_outliers(spark, df, schema, part, make(), outliers)
        if known:
            found = matching.match_pairs(spark, schema, known, part, make(), gone, edges, EPS)
            out = found if out is None else out.unionByName(found)
    return out if out is not None else spark.createDataFrame([], matching.MATCH_SCHEMA)


def _headline(spark, sf_dir):
    """The full-size schema: direct selection over all its candidate contexts against the samplers, on the top record.

    Direct selection runs as one plan (folded cells, built-in test, arg max); its time is the wall time of that plan.
    """
    df, schema = wl.workload(spark, sf_dir, "e25")
    rid = wl.top_records(df, schema)[0]
    began = time.perf_counter()
    valid = cut(release.valid_contexts(df, schema, rid, det.Grubbs()).select("ctx", "u"))
    drawn = mech.exp_mechanism(valid, mech.allocate("direct", EPS, 0), mech.SeededNoise(0), tag=(0, 0)).first()
    took = time.perf_counter() - began
    best = float(valid.agg(F.max("u")).first()[0])
    began = time.perf_counter()
    search = release.make_search(df, schema, rid, det.Grubbs(), "uniform", noise=mech.SeededNoise(7))
    setup = time.perf_counter() - began
    grid = [(m, EPS, SAMPLES) for m in ("uniform", "walk", "dfs", "bfs")]
    sampled = _summary(release.run_trials(spark, {str(rid): search}, grid, REPETITIONS, best={str(rid): best}, setup={str(rid): setup}), ["method"])
    direct = spark.createDataFrame([("direct", took, took, took, drawn["u"] / best, drawn["u"] / best, drawn["u"] / best, float(1 << len(search.free)), 1.0, 0.0)], sampled.schema)
    return direct.unionByName(sampled)


_add("w_headline_e25", _headline)
_add("w_counters_li12", lambda s, d: measures.counters(trials(s, d, "li12", _METHODS, det.Grubbs()), ["method"]))
_add("w_samplers_grubbs_li16", lambda s, d: _summary(trials(s, d, "li16", _METHODS, det.Grubbs()), ["method"]))
_add("w_bootstrap_e14", lambda s, d: measures.bootstrap_interval(trials(s, d, "e14", _METHODS), ["method"]))


def _sensitivity(spark, sf_dir, name):
    """Largest change of any context's population when one record goes: both enumerations, compared."""
    df, schema = wl.workload(spark, sf_dir, name)
    encoded = pl.encode(df, schema)
    gone = matching.pick_records(df, schema, 1, 3).first()
    before = pl.fold_contexts(pl.moments(encoded.groupBy("cell")), schema).select("ctx", F.col("n").alias("u"))
    after = pl.fold_contexts(pl.moments(encoded.where(F.col("record_id") != F.lit(gone["record_id"])).groupBy("cell")), schema).select("ctx", F.col("n").alias("u"))
    return mech.empirical_sensitivity(before, after).select(F.col("sensitivity").cast("long").alias("sensitivity"))


def _sensitivity_sql(name: str, pick: str) -> str:
    full = wl.SCHEMAS[name].full
    return f"""WITH enc AS ({wl.encoded_sql(name)}), gone AS (SELECT record_id FROM enc ORDER BY {pick} LIMIT 1),
per AS (SELECT cell, count(*) AS n1, count(*) FILTER (record_id <> (SELECT record_id FROM gone)) AS n2 FROM enc GROUP BY cell),
both_sides AS (SELECT c.ctx, sum(n1) AS u1, sum(n2) AS u2 FROM range({full + 1}) AS c(ctx) JOIN per ON cell & c.ctx = cell GROUP BY c.ctx)
SELECT max(abs(u1 - u2))::BIGINT AS sensitivity FROM both_sides"""


for _d in ("e14", "doc13"):
    _add(f"sensitivity_population_{_d}", lambda s, d, n=_d: _sensitivity(s, d, n))
    SQL[f"sensitivity_population_{_d}"] = _sensitivity_sql(_d, "record_id")

for _k in ("tumbling", "sliding", "session"):
    _add(f"stream_{_k}", lambda s, d, k=_k: windows.run_to_table(s, getattr(windows, k)(windows.events_stream(s, d)), "complete"))
SQL["stream_tumbling"] = "SELECT date_trunc('day', ts)::TIMESTAMP AS window_start, event_type, count(*) AS n FROM events GROUP BY 1, 2"
SQL["stream_sliding"] = "SELECT s AS window_start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 6 HOUR, ts) - k * INTERVAL 6 HOUR FOR k IN [0, 1, 2, 3]])::TIMESTAMP AS s FROM events) GROUP BY 1"
SQL["stream_session"] = """SELECT user_id, min(ts)::TIMESTAMP AS session_start, count(*) AS n FROM (
  SELECT user_id, ts, sum(opens) OVER (PARTITION BY user_id ORDER BY ts) AS session FROM (
    SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 6 HOUR THEN 0 ELSE 1 END AS opens FROM events)) GROUP BY user_id, session"""
_add("stream_dedup", lambda s, d: windows.run_to_table(s, windows.deduplicated(windows.events_stream(s, d)), "append"))
SQL["stream_dedup"] = "SELECT event_id, event_type FROM events"
_add("stream_static_join", lambda s, d: windows.run_to_table(s, windows.with_domain(windows.events_stream(s, d), wl.EVENT_TYPES), "append"))
SQL["stream_static_join"] = "SELECT event_id, (CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 WHEN 'view' THEN 4 END)::INT AS ordinal FROM events"
_add("stream_running_cells", lambda s, d: windows.run_to_table(s, windows.running_cells(windows.events_stream(s, d), wl.SCHEMAS["e14"]), "complete"))
SQL["stream_running_cells"] = f"SELECT cell, n, s::BIGINT AS s FROM ({wl.cells_sql('e14')})"
_add("stream_user_state", lambda s, d: windows.run_to_table(s, windows.user_totals(windows.events_stream(s, d)), "update").groupBy("user_id").agg(F.max("n").alias("n")))
SQL["stream_user_state"] = "SELECT user_id, count(*) AS n FROM events GROUP BY 1"
_add("stream_foreachbatch_release", lambda s, d: windows.release_each_batch(s, d))
