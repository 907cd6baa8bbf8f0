"""Times the headline queries: a line to stderr after each step, one JSON line to stdout at the end.

Steps that would start after BENCH_SECONDS (default 900) are left out and listed, so that a slow machine loses those only.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ctxrelease import queries_experiments as ex
from ctxrelease.functions import mechanism as mech
from ctxrelease.operators import detectors as det
from ctxrelease.operators import measures, release
from ctxrelease.plans import cells as pl
from ctxrelease.queries_core import hidden, reference_file
from ctxrelease.sources import workloads as wl

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
LIMIT = float(os.environ.get("BENCH_SECONDS", "900"))
REPETITIONS, EPS, SAMPLES = 200, 0.2, 50


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false").config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    began, took, left_out = time.perf_counter(), {}, []
    releases: dict[str, dict] = {}

    def timed(name, fn):
        if time.perf_counter() - began > LIMIT:
            left_out.append(name)
            return None
        start = time.perf_counter()
        out = fn()
        took[name] = round(time.perf_counter() - start, 3)
        print(f"{name}: {took[name]} s", file=sys.stderr, flush=True)
        return out

    df, schema = wl.workload(spark, SF_DIR, "e14")
    timed("cells_e14", lambda: pl.build_cells(df, schema).count())
    rid = wl.top_records(df, schema)[0]
    timed("enumerate_grubbs_e14", lambda: release.valid_contexts(df, schema, rid, det.Grubbs()).count())
    timed("direct_release_e14", lambda: release.direct_release(df, schema, rid, det.Grubbs(), EPS, mech.SeededNoise(0)).collect())
    li, li_schema = wl.workload(spark, SF_DIR, "li12")
    timed("cells_li12", lambda: pl.build_cells(li, li_schema).count())
    timed("reference_file_li12", lambda: reference_file(li, li_schema).count())
    timed("hidden_outliers_li12", lambda: hidden(li, li_schema).count())
    timed("flag_all_lof_e14", lambda: det.flag_all(df, schema, det.LOF(), schema.full).where("is_outlier").count())

    def experiment(name, dataset, grid, detector):
        """All trials of a grid; a release's seconds hold its scan, cells and slice."""
        t = timed(name, lambda: ex.trials(spark, SF_DIR, dataset, grid, detector, repetitions=REPETITIONS).groupBy("method", "detector").agg(*measures.runtime_columns(), *measures.utility_columns()).collect())
        for r in t or []:
            releases[f"{dataset} {r['detector']} {r['method']}"] = {k: round(r[k], 4) for k in ("t_min", "t_max", "t_avg", "utility", "ci_lo", "ci_hi")}

    methods = [(m, EPS, SAMPLES) for m in mech.METHODS]
    experiment("samplers_lof_e14_x200", "e14", methods, det.LOF())
    experiment("bfs_grubbs_e14_x200", "e14", [("bfs", EPS, SAMPLES)], det.Grubbs())
    experiment("bfs_histogram_e14_x200", "e14", [("bfs", EPS, SAMPLES)], det.Histogram())
    experiment("samplers_lof_li12_x200", "li12", methods, det.LOF())
    big, wide = wl.workload(spark, SF_DIR, "e25")
    top = wl.top_records(big, wide)[0]
    timed("bfs_grubbs_e25", lambda: release.release_context(big, wide, top, "grubbs", n=SAMPLES, noise=mech.SeededNoise(0)))
    rows = timed("headline_e25_direct_and_samplers", lambda: ex.QUERIES["w_headline_e25"](spark, SF_DIR).collect())
    for r in rows or []:
        releases[f"e25 grubbs {r['method']}"] = {k: round(r[k], 4) for k in ("t_min", "t_max", "t_avg", "utility", "ci_lo", "ci_hi")}
    timed("matching_grubbs_lof_histogram_e14", lambda: ex.match(spark, SF_DIR, "e14", 20, 10).agg(F.count(F.lit(1))).collect())
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(SF_DIR.rstrip("/")), "releases": releases, "left_out": left_out}), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
