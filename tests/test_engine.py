"""Pieces of the engine against plain definitions: quantiles, LOF in all contexts, matching, noise, ledger, iterated tests."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from ctxrelease.functions import mechanism as mech
from ctxrelease.functions.student import critical_column, critical_values
from ctxrelease.functions.udf import release_contexts
from ctxrelease.operators import detectors as det
from ctxrelease.operators import matching, release
from ctxrelease.operators.search import Search, starting_context
from ctxrelease.plans import cells as pl
from ctxrelease.queries_core import hidden, reference_file, reference_list
from ctxrelease.schema import AttributeSpec, ContextSchema
from ctxrelease.sources import workloads as wl

from .test_methods import SCHEMA, make_slice, sample, searcher

#: Two-sided critical values at 0.05 as printed in tables of the test.
PRINTED = {3: 1.1543, 4: 1.4812, 5: 1.7150, 6: 1.8871, 7: 2.0200, 8: 2.1266, 9: 2.2150, 10: 2.2900, 15: 2.5483, 20: 2.7082, 30: 2.9085, 50: 3.1282, 100: 3.3841}


def test_critical_values(spark):
    got = critical_values(np.array(list(PRINTED)))
    assert np.allclose(got, list(PRINTED.values()), atol=1.5e-4)
    n = np.unique(np.concatenate([np.arange(3, 1200), np.geomspace(1200, 10**14, 400).astype(np.int64)]))
    frame = spark.createDataFrame([(int(x),) for x in [1, 2, *n]], "n long")
    for alpha, sides in ((0.05, 2), (0.01, 1)):
        table = {r[0]: r[1] for r in frame.select("n", critical_column(F.col("n"), alpha, sides)).collect()}
        assert table[1] is None and table[2] is None
        assert np.allclose([table[int(x)] for x in n], critical_values(n, alpha, sides), rtol=1e-9)


def test_critical_values_take_no_time():
    import time

    sizes = np.arange(3, 2051)
    critical_values(sizes)
    began = time.perf_counter()
    for _ in range(20):
        critical_values(sizes)
    assert (time.perf_counter() - began) / 20 < 0.02


def plain_factor(xs: np.ndarray, me: int, k: int) -> float:
    """The factor by its definition over all points."""
    if len(xs) <= k:
        return 0.0
    d = np.abs(xs[:, None] - xs[None, :])
    np.fill_diagonal(d, np.inf)
    kd = np.sort(d, 1)[:, k - 1]
    near = d <= kd[:, None]
    total = np.where(near, np.maximum(d, kd[None, :]), 0).sum(1)
    with np.errstate(all="ignore"):
        lrd = np.where(total > 0, near.sum(1) / total, np.inf)
    if np.isinf(lrd[me]):
        return 1.0 if np.isinf(lrd[near[me]]).all() else 0.0
    return float(lrd[near[me]].mean() / lrd[me])


@pytest.mark.parametrize("seed,ties", [(1, False), (2, True)])
def test_lof_of_all_contexts_equals_definition(spark, seed, ties):
    rows, (cell, x) = sample(seed)
    if ties:
        rows = [(c, v // 40 * 40) for c, v in rows]
        x = x // 40 * 40
    s = Search(SCHEMA, make_slice(rows), det.LOF(4), cell, x)
    for c in s.all_candidates():
        xs = np.array([v for k, v in rows if k & c == k], float)
        want = plain_factor(xs, int(np.flatnonzero(xs == x)[0]), 4)
        assert math.isclose(det.LOF(4).flags(s.part, np.array([c]), x)[1][0], want, rel_tol=1e-9, abs_tol=1e-12)
    # the slice that a plan collects gives the same verdicts
    frame = spark.createDataFrame([(i, *_values(c), v / 10_000) for i, (c, v) in enumerate(rows)], "id long, a string, b string, c string, v double")
    part = det.take_slice(frame, SCHEMA, det.LOF(4), x)
    assert np.allclose(det.LOF(4).flags(part, np.array(s.all_candidates()), x)[1], det.LOF(4).flags(s.part, np.array(s.all_candidates()), x)[1])
    flagged = {r["record_id"]: r["is_outlier"] for r in det.flag_all(frame, SCHEMA, det.LOF(4), SCHEMA.full).collect()}
    every = np.array([v for _, v in rows], float)
    assert flagged == {i: plain_factor(every, i, 4) > 1.5 for i in range(len(rows))}


def _values(cell):
    return [a.domain[j] for i, a in enumerate(SCHEMA.attrs) for j in range(len(a.domain)) if cell & SCHEMA.bit(i, j)]


@pytest.mark.parametrize("detector", [det.Grubbs(), det.LOF(5), det.LOF(3, 1.2), det.Histogram(0.02), det.IQR()])
def test_matching_equals_enumeration_of_smaller_tables(detector):
    rows, (cell, x) = sample()
    edges = {c: (np.sort([v for k, v in rows if k == c])[:30], np.sort([v for k, v in rows if k == c])[::-1][:30]) for c in {k for k, _ in rows}}
    rng = np.random.default_rng(0)
    for n in (1, 5):
        part = matching.own_slice(make_slice(rows), detector, x, n)
        base = matching.Enumeration(SCHEMA, part, detector, cell, x)
        for _ in range(30):
            gone = set(rng.choice(len(rows) - 1, n, replace=False).tolist())
            valid, size = base.without([rows[i] for i in gone], edges)
            other = make_slice([r for i, r in enumerate(rows) if i not in gone])
            assert (valid == detector.flags(other, base.ctxs, x)[0]).all() and (size == other.stats(base.ctxs)["n"]).all()


def test_random_outliers_have_valid_contexts(spark):
    df, schema = wl.workload(spark, "/root/testdata/sf0.001", "doc13")
    part = matching.shared_slice(df, schema)
    found = matching.random_outliers(spark, df, schema, part, det.Grubbs(), 10)
    assert 1 <= len(found) <= 10
    for _, cell, x in found:
        assert Search(schema, part, det.Grubbs(), cell, x).valid()


def test_reference_lists_and_hidden_outliers_by_brute_force(spark):
    rows, _ = sample(3, 120)
    rows = [*rows, (rows[0][0], 900_000)]
    frame = spark.createDataFrame([(i, *_values(c), v / 10_000) for i, (c, v) in enumerate(rows)], "id long, a string, b string, c string, v double")
    want, per = set(), {}
    for ctx in range(1 << SCHEMA.t):
        own = [(i, v) for i, (c, v) in enumerate(rows) if c & ctx == c]
        if not own or not SCHEMA.wellformed(ctx):
            continue
        xs = np.array([v for _, v in own], float)
        hits = []
        if len(xs) >= 3 and xs.std(ddof=1) > 0:
            crit = critical_values(np.array([len(xs)]))[0]
            hits = [i for i, v in own if abs(v - xs.mean()) / xs.std(ddof=1) > crit]
        per[ctx] = (len(xs), len(hits))
        want |= {(ctx, i) for i in hits}
    assert {(r["ctx"], r["record_id"]) for r in reference_list(frame, SCHEMA).collect()} == want and want
    assert {r["ctx"]: (r["population"], r["n_outliers"]) for r in reference_file(frame, SCHEMA).collect()} == per
    globally = {i for c, i in want if c == SCHEMA.full}
    assert {r["record_id"] for r in hidden(frame, SCHEMA).collect()} == {i for _, i in want} - globally


def test_iterated_test_equals_the_plain_loop(spark):
    rng = np.random.default_rng(2)
    xs = [*rng.normal(500, 20, 300).astype(int).tolist(), 900, 905, 905, 100, 1200]
    schema = ContextSchema("one", (AttributeSpec("a", "a", ("0",)),), "v", "id")
    frame = spark.createDataFrame([(i, "0", x / 10_000) for i, x in enumerate(xs)], "id long, a string, v double")
    left, gone = list(xs), set()
    while len(left) >= 3:
        v = np.array(left, float)
        far = left[int(np.abs(v - v.mean()).argmax())]
        if abs(far - v.mean()) / v.std(ddof=1) <= critical_values(np.array([len(v)]))[0]:
            break
        gone.add(far)
        left.remove(far)
    assert len(gone) > 3
    for window in (2, 1000):
        got = {r["record_id"]: r["is_outlier"] for r in det.iterative_flags(frame, schema, 1, window=window).collect()}
        assert got == {i: x in gone for i, x in enumerate(xs)}
    assert not any(r["is_outlier"] for r in det.iterative_flags(frame.where("id < 2"), schema, 1).collect())


def test_quartile_detector():
    rows, (cell, x) = sample()
    s = Search(SCHEMA, make_slice(rows), det.IQR(), cell, x)
    for c in s.all_candidates():
        xs = sorted(v for k, v in rows if k & c == k)
        low, high = xs[-(-len(xs) // 4) - 1], xs[-(-3 * len(xs) // 4) - 1]
        assert det.IQR().flags(s.part, np.array([c]), x)[0][0] == (max(low - x, x - high, 0) > 1.5 * (high - low))


def test_secure_noise_leaves_no_key(spark):
    noise = mech.SecureNoise()
    frame = spark.range(4000).select(F.col("id").alias("ctx"), F.lit(1.0).alias("u"))
    values = frame.withColumn("g", noise.column(F.col("ctx"))).cache()
    got = [r["g"] for r in values.collect()]
    assert len(set(got)) == 4000 and abs(np.mean(got) - 0.5772) < 0.1 and abs(np.var(got) - math.pi**2 / 6) < 0.3
    assert not vars(noise)
    first = mech.exp_mechanism(frame, 0.1, noise).first()["ctx"]
    assert any(mech.exp_mechanism(frame, 0.1, noise).first()["ctx"] != first for _ in range(5))
    assert len({noise.uniform(1, 2) for _ in range(100)}) == 100


def test_ledger_refuses_and_reverses(spark, tmp_path):
    ledger = mech.BudgetLedger(spark, f"{tmp_path}/ledger", 0.3)
    ledger.charge(1, "bfs", 0.2)
    with pytest.raises(mech.BudgetExceeded):
        ledger.charge(1, "bfs", 0.2)
    # another writer enters between the check and the entry: the sum decides, and the late entry is reversed
    other = mech.BudgetLedger(spark, f"{tmp_path}/ledger", 0.3)
    real, calls = other.remaining, []

    def slow():
        calls.append(1)
        left = real()
        ledger.charge(2, "dfs", 0.1)
        return left

    other.remaining = slow
    with pytest.raises(mech.BudgetExceeded):
        other.charge(3, "walk", 0.1)
    assert math.isclose(ledger.spent(), 0.3)


def test_uniform_stops_after_its_trials():
    s, _ = searcher(det.LOF(5))
    valid = s.valid()
    s.memo.clear()
    o = s.uniform(0.2, len(valid) + 5, mech.SeededNoise(1), max_trials=3000)
    assert o.ctx in valid and o.trials == 3000 and set(o.path) <= set(valid) and len(o.path) == len(set(o.path))
    few = s.uniform(0.2, 2, mech.SeededNoise(1))
    assert len(few.path) == 2 and few.trials < 3000


def test_smallest_start_is_found_layer_by_layer():
    s, _ = searcher()
    valid = s.valid()
    assert starting_context(s) == min(valid, key=lambda c: (c.bit_count(), c))


def test_population_sensitivity_is_one(spark):
    rows, _ = sample(5, 80)
    frame = spark.createDataFrame([(i, *_values(c), v / 10_000) for i, (c, v) in enumerate(rows)], "id long, a string, b string, c string, v double")
    before, after = (pl.fold_contexts(pl.build_cells(d, SCHEMA), SCHEMA).select("ctx", F.col("n").alias("u")) for d in (frame, frame.where("id <> 7")))
    assert mech.empirical_sensitivity(before, after).first()[0] == 1
    assert mech.empirical_sensitivity(before, before).first()[0] == 0
    assert mech.empirical_sensitivity(before, pl.fold_contexts(pl.build_cells(frame.where("id > 9"), SCHEMA), SCHEMA).select("ctx", F.col("n").alias("u"))).first()[0] == 10


def test_releases_of_several_records(spark):
    df, schema = wl.workload(spark, "/root/testdata/sf0.001", "doc13")
    ids = wl.top_records(df, schema, 2)
    out = release_contexts(df, schema, ids, "grubbs", n=5, noise=mech.SeededNoise(0)).collect()
    for r in out:
        alone, _ = release.release_context(df, schema, int(r["record_id"]), "grubbs", n=5, noise=mech.SeededNoise(0))
        assert (alone.ctx, alone.predicate) == (r["ctx"], r["predicate"])
    assert len(out) == 2


def test_streams_write_results_from_tasks(spark):
    from ctxrelease.streaming import windows

    sf = "/root/testdata/sf0.001"
    stream = windows.user_totals(windows.events_stream(spark, sf))
    got = {r[0]: r[1] for r in windows.run_to_table(spark, stream, "update").groupBy("user_id").agg(F.max("n")).collect()}
    want = {r[0]: r[1] for r in spark.read.parquet(f"{sf}/events.parquet").groupBy("user_id").count().collect()}
    assert got == want


@pytest.mark.parametrize("detector", [det.LOF(5), det.Histogram(0.02), det.ZScore(2.0)])
@pytest.mark.parametrize("method", ["bfs", "walk"])
def test_lockstep_draws_as_in_memory(spark, detector, method):
    rows, (cell, x) = sample(1, 150)
    frame = spark.createDataFrame([(i, *_values(c), v / 10_000) for i, (c, v) in enumerate(rows)], "id long, a string, b string, c string, v double")
    rid = len(rows) - 1
    search = release.make_search(frame, SCHEMA, rid, detector)
    assert release.smallest_start(frame, SCHEMA, rid, detector) == search.start
    got = {r["trial"]: r["ctx"] for r in release.lockstep(frame, SCHEMA, rid, method, 0.5, 3, search.start, 3, mech.SeededNoise(2), detector).collect()}
    assert got == {t: search.run(method, 0.5, 3, mech.SeededNoise(2), t).ctx for t in range(3)}


def test_cells_outlive_a_session_and_add_up(spark, tmp_path):
    from ctxrelease.sources import sinks

    rows, _ = sample(4, 100)
    frame = spark.createDataFrame([(i, *_values(c), v / 10_000) for i, (c, v) in enumerate(rows)], "id long, a string, b string, c string, v double")
    whole, parts = pl.build_cells(frame, SCHEMA), [pl.build_cells(frame.where(w), SCHEMA) for w in ("id < 40", "id >= 40")]
    sinks.save_cells(parts[0], f"{tmp_path}/cells")
    merged = sinks.merge_cells(sinks.load_cells(spark, f"{tmp_path}/cells"), parts[1])
    assert sorted(map(tuple, merged.select(*whole.columns).collect())) == sorted(map(tuple, whole.collect()))


def test_late_rows_go_and_a_replay_adds_nothing(spark, tmp_path):
    from datetime import datetime, timedelta

    from ctxrelease.streaming import windows

    t0 = datetime(2024, 1, 1)
    batches = [[(0, "click"), (30, "click")], [(72, "view")], [(1, "click"), (73, "view")]]  # hours; hour 1 is late in the third file
    source, out, state = (f"{tmp_path}/{n}" for n in ("in", "out", "state"))

    def run():
        schema = "ts timestamp, event_type string"
        stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(source)
        q = windows.tumbling(stream).writeStream.format("parquet").option("path", out).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()

    for k, rows in enumerate(batches):
        spark.createDataFrame([(t0 + timedelta(hours=h), e) for h, e in rows], "ts timestamp, event_type string").coalesce(1).write.mode("append").parquet(source)
        run()
    run()  # nothing new: nothing is written twice
    got = sorted((r["window_start"].day, r["event_type"], r["n"]) for r in spark.read.parquet(out).collect())
    assert got == [(1, "click", 1), (2, "click", 1)]


def test_output_constrained_neighbours(spark):
    """One record apart with the same non-empty valid set; not if the set changes, is empty, or more records differ."""
    from ctxrelease.operators import measures

    rows, _ = sample()
    frame = spark.createDataFrame([(i, *_values(c), v / 10_000) for i, (c, v) in enumerate(rows)], "id long, a string, b string, c string, v double")
    rid = len(rows) - 1
    valid = release.valid_contexts(frame, SCHEMA, rid, det.Grubbs()).select("ctx", "u")
    less = frame.where("id <> 3")
    same = release.valid_contexts(less, SCHEMA, rid, det.Grubbs()).select("ctx", "u")
    assert measures.are_f_neighbors(frame, less, valid, same)
    assert not measures.are_f_neighbors(frame, frame.where("id > 3"), valid, same)
    assert not measures.are_f_neighbors(frame, less, valid, same.where(f"ctx <> {SCHEMA.full}"))
    assert not measures.are_f_neighbors(frame, less, valid.where("false"), same.where("false"))
