"""Queries of variants and measures with SQL: detector modes, populations, neighbouring datasets, bounds, seeded trials."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxrelease.functions import mechanism as mech
from ctxrelease.operators import detectors as det
from ctxrelease.operators import matching, measures, release
from ctxrelease.operators import search as search_mod
from ctxrelease.plans import cells as pl
from ctxrelease.queries_core import EPS, NOISE, SAMPLES, _best, _searched, _start_sql, _verified, base_sql, bfs_sql, critical_ctes, dfs_sql, grubbs_sql, gumbel_sql, lof_sql, top, uniform_release_sql, walk_sql
from ctxrelease.schema import Context, ContextSchema
from ctxrelease.sources import workloads as wl

QUERIES: dict = {}
SQL: dict[str, str] = {}


def _add(name: str, sql: str | None, fn) -> None:
    QUERIES[name] = fn
    if sql:
        SQL[name] = sql


# populations and domains

_SOME = Context.of(wl.SCHEMAS["e14"], event_type=["click", "error"], day=["0", "6"])


def _population(spark: SparkSession, sf_dir: str) -> DataFrame:
    df, schema = wl.workload(spark, sf_dir, "e14")
    return pl.population(df, Context(schema, _SOME.mask)).select("event_id", "value")


_add("population_e14", "SELECT event_id, value FROM events WHERE event_type IN ('click', 'error') AND dayofweek(ts) IN (0, 6)", _population)


def _leaky(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The control that a release must not use: domains read off the data lose declared values that no record has."""
    df, schema = wl.workload(spark, sf_dir, "e25")
    seen = df.select(*[F.expr(a.expr).cast("string").alias(a.name) for a in schema.attrs], "value", "event_id")
    inferred = ContextSchema.infer(seen, [a.name for a in schema.attrs], "value", "event_id", allow_inferred_domain=True)
    rows = [(a.name, len(a.domain), len(b.domain)) for a, b in zip(schema.attrs, inferred.attrs)]
    return spark.createDataFrame([*rows, ("all contexts", schema.t, inferred.t)], "attr string, declared int, observed int")


_add(
    "leaky_domain_e25",
    "WITH o AS (SELECT count(DISTINCT event_type)::INT AS a, count(DISTINCT hour(ts) // 3)::INT AS b, count(DISTINCT user_id % 8)::INT AS c FROM events) "
    "SELECT 'event_type' AS attr, 9 AS declared, a AS observed FROM o UNION ALL SELECT 'part', 8, b FROM o UNION ALL SELECT 'bucket', 8, c FROM o UNION ALL SELECT 'all contexts', 25, a + b + c FROM o",
    _leaky,
)

# detector modes


def _mode(detector):
    return lambda s, d: _verified(s, d, "doc13", detector).select("ctx", "population", "is_outlier")


_add(
    "grubbs_extreme_verify_doc13",
    f"{grubbs_sql('doc13')} SELECT judged.ctx, judged.n AS population, is_outlier AND abs(x - s / stats.n) >= greatest(hi - s / stats.n, s / stats.n - lo) - 1e-9 AS is_outlier FROM judged JOIN stats ON stats.ctx = judged.ctx, anchor",
    _mode(det.Grubbs(mode="extreme")),
)
_add(
    "hist_relative_verify_doc13",
    f"""{base_sql('doc13')},
bins AS (SELECT ctx, n, lo, hi, greatest(1, floor(sqrt(n)))::BIGINT AS b FROM stats WHERE hi > lo),
own AS (SELECT bins.*, least((x - lo) * b // (hi - lo), b - 1) AS k FROM bins, anchor WHERE 0.05 * n / b > 1),
held AS (SELECT ctx, count(*) AS c FROM own JOIN enc ON cell & ctx = cell AND least((enc.x - lo) * b // (hi - lo), b - 1) = k GROUP BY ctx)
SELECT stats.ctx, stats.n AS population, coalesce(c < 0.05 * stats.n / greatest(1, floor(sqrt(stats.n))), false) AS is_outlier FROM stats LEFT JOIN held ON held.ctx = stats.ctx""",
    _mode(det.Histogram(cut="relative")),
)
_add(
    "iqr_verify_doc13",
    f"""{base_sql('doc13')},
held AS (SELECT cand.ctx, enc.x, row_number() OVER (PARTITION BY cand.ctx ORDER BY enc.x) AS r, count(*) OVER (PARTITION BY cand.ctx) AS n FROM cand JOIN enc ON cell & cand.ctx = cell),
q AS (SELECT ctx, any_value(n) AS n, max(x) FILTER (r = (n + 3) // 4) AS low, max(x) FILTER (r = (3 * n + 3) // 4) AS high FROM held GROUP BY ctx)
SELECT ctx, n AS population, greatest(low - x, x - high, 0) > 1.5 * (high - low) AS is_outlier FROM q, anchor""",
    _mode(det.IQR()),
)

# options of the searches, and a utility of the caller's

for _name in ("e14", "li12"):
    _add(f"dfs_last_release_{_name}", dfs_sql(_name, SAMPLES, "last"), lambda s, d, n=_name: _searched(s, d, n, "dfs", SAMPLES, final="last"))
    _add(f"bfs_inclusive_release_{_name}", bfs_sql(_name, SAMPLES, inclusive=True), lambda s, d, n=_name: _searched(s, d, n, "bfs", SAMPLES, inclusive=True))
    _add(f"walk_distinct_release_{_name}", walk_sql(_name, SAMPLES, True), lambda s, d, n=_name: _searched(s, d, n, "walk", SAMPLES, distinct=True))
    _add(f"uniform_sparse_release_{_name}", uniform_release_sql(_name, SAMPLES, 512, 0.25), lambda s, d, n=_name: _searched(s, d, n, "uniform", SAMPLES, p=0.25))


def _root(stats: dict):
    return stats["n"] ** 0.5


def _own_utility(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Direct selection by the root of the population, whose sensitivity is at most one."""
    df, schema, rid = top(spark, sf_dir, "doc13")
    search_mod.register_utility("root", _root, 1.0)
    public, _ = release.release_context(df, schema, rid, "grubbs", "root", "direct", EPS, noise=NOISE)
    return spark.createDataFrame([(public.ctx,)], "ctx long")


_add("direct_own_utility_doc13", f"{grubbs_sql('doc13')} SELECT max_by(ctx, row(0.1 * sqrt(u) + {gumbel_sql('0', '0', 'ctx')}, ctx)) AS ctx FROM valid", _own_utility)

# neighbouring datasets: one record less, for the records with the smallest ids

_PAIRS = 20


def _neighbour_sql(name: str, rank: int) -> str:
    """Valid sets (Grubbs) of the record of a rank, on the table and without each of _PAIRS other records."""
    schema = wl.SCHEMAS[name]
    return f"""WITH enc AS ({wl.encoded_sql(name)}),
anchor AS (SELECT record_id, cell, x FROM enc ORDER BY x DESC, record_id LIMIT 1 OFFSET {rank}),
gone AS (SELECT row_number() OVER (ORDER BY record_id) - 1 AS pair, cell AS g_cell, x AS g_x FROM (SELECT * FROM enc WHERE record_id <> (SELECT record_id FROM anchor) ORDER BY record_id LIMIT {_PAIRS})),
cells AS (SELECT cell, count(*) AS n, sum(x::HUGEINT) AS s, sum(x::HUGEINT * x) AS ss FROM enc GROUP BY cell),
cand AS (SELECT c.ctx FROM range({1 << schema.t}) AS c(ctx), anchor a WHERE c.ctx & a.cell = a.cell),
whole AS MATERIALIZED (SELECT ctx, sum(n)::BIGINT AS n, sum(s) AS s, sum(ss) AS ss FROM cand JOIN cells ON cell & ctx = cell GROUP BY ctx),
every AS MATERIALIZED (SELECT -1 AS pair, ctx, n, s::DOUBLE AS s, ss::DOUBLE AS ss FROM whole UNION ALL
  SELECT pair, ctx, n - (g_cell & ctx = g_cell)::INT, (s - CASE WHEN g_cell & ctx = g_cell THEN g_x ELSE 0 END)::DOUBLE, (ss - CASE WHEN g_cell & ctx = g_cell THEN g_x::HUGEINT * g_x ELSE 0 END)::DOUBLE FROM whole, gone),
{critical_ctes('every')},
valid AS MATERIALIZED (SELECT pair, ctx, every.n AS u FROM every JOIN k ON k.n = every.n, anchor WHERE ss - s * (s / every.n) > 0 AND abs(x - s / every.n) / sqrt((ss - s * (s / every.n)) / (every.n - 1)) > crit),
law AS MATERIALIZED (SELECT pair, ctx, 0.1 * (u - max(u) OVER (PARTITION BY pair)) AS score, exp(0.1 * (u - max(u) OVER (PARTITION BY pair))) AS e, sum(exp(0.1 * (u - (SELECT max(u) FROM valid b WHERE b.pair = valid.pair)))) OVER (PARTITION BY pair) AS total FROM valid),
sides AS (SELECT g.pair, coalesce(a.ctx, b.ctx) AS ctx, a.ctx IS NOT NULL AS in_a, b.ctx IS NOT NULL AS in_b, a.e / a.total AS p, b.e / b.total AS q
  FROM gone g JOIN (SELECT * FROM law WHERE pair = -1) a ON true FULL JOIN (SELECT * FROM law WHERE pair >= 0) b ON b.pair = g.pair AND b.ctx = a.ctx)"""


def _neighbours(spark: SparkSession, sf_dir: str, name: str, rank: int) -> DataFrame:
    df, schema = wl.workload(spark, sf_dir, name)
    rid = wl.top_records(df, schema, rank + 1)[rank]
    cell, x = pl.lookup_record(df, schema, rid)
    others = pl.encode(df, schema).where(F.col("record_id") != F.lit(rid)).orderBy("record_id").limit(_PAIRS).select("cell", "x").collect()
    edges = matching.cell_edges(df, schema, 1, {r["cell"] for r in others})
    gone = {1: [[(r["cell"], r["x"])] for r in others]}
    # the test rests on the cells' moments alone, whatever the number of distinct values
    return matching.match_pairs(spark, schema, [(rid, cell, x)], det.take_slice(df, schema, det.Grubbs(), x), det.Grubbs(), gone, edges, EPS)


for _name, _rank in (("e14", 200), ("doc13", 30), ("li12", 150)):
    # a pair whose sides are both empty can't occur: the record has a valid context in the table
    _add(
        f"enum_match_{_name}",
        f"{_neighbour_sql(_name, _rank)}, own AS (SELECT ctx FROM valid WHERE pair = -1), each_pair AS (SELECT g.pair, (SELECT count(*) FROM own) AS a, (SELECT count(*) FROM valid v WHERE v.pair = g.pair) AS b, "
        "(SELECT count(*) FROM valid v JOIN own ON own.ctx = v.ctx WHERE v.pair = g.pair) AS both_sides FROM gone g) "
        "SELECT pair::INT AS pair, a = both_sides AND b = both_sides AS exact, round(both_sides / (a + b - both_sides), 9) AS jaccard FROM each_pair WHERE a > 0",
        lambda s, d, n=_name, r=_rank: _neighbours(s, d, n, r).select("pair", "exact", F.round("jaccard", 9).alias("jaccard")),
    )
    _add(
        f"privacy_ratio_{_name}",
        f"{_neighbour_sql(_name, _rank)} SELECT b.pair::INT AS pair, round(max(abs(a.score - ln(a.total) - b.score + ln(b.total))), 6) AS log_ratio FROM law a JOIN law b ON a.pair = -1 AND b.pair >= 0 AND a.ctx = b.ctx GROUP BY b.pair",
        lambda s, d, n=_name, r=_rank: _neighbours(s, d, n, r).where("not isnan(log_ratio)").select("pair", F.round("log_ratio", 6).alias("log_ratio")),
    )


def _compare(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One neighbouring dataset compared as DataFrames: both enumerations, both laws, joined by context."""
    df, schema, rid = top(spark, sf_dir, "doc13")
    other = pl.encode(df, schema).where(F.col("record_id") != F.lit(rid)).orderBy("record_id").first()["record_id"]
    less = df.where(F.expr(schema.record_id) != F.lit(other))
    v1, v2 = (release.valid_contexts(d, schema, rid, det.Grubbs()) for d in (df, less))
    eps1 = mech.allocate("direct", EPS, 0)
    ratio = measures.max_ratio(measures.probability_table(v1, eps1), measures.probability_table(v2, eps1))
    return measures.compare_sets(v1, v2).crossJoin(ratio).select("exact", F.round("jaccard", 9).alias("jaccard"), F.round("max_ratio", 6).alias("max_ratio"), "common")  # one row each


_add(
    "neighbor_compare_doc13",
    f"{_neighbour_sql('doc13', 0)}, own AS (SELECT ctx, e / total AS p FROM law WHERE pair = -1), other AS (SELECT ctx, e / total AS q FROM law WHERE pair = 0) "
    "SELECT bool_and(own.ctx IS NOT NULL AND other.ctx IS NOT NULL) AS exact, round(count(own.ctx) FILTER (other.ctx IS NOT NULL) / count(*), 9) AS jaccard, round(max(greatest(p / q, q / p)), 6) AS max_ratio, count(*) FILTER (own.ctx IS NOT NULL AND other.ctx IS NOT NULL) AS common FROM own FULL JOIN other ON own.ctx = other.ctx",
    _compare,
)

# bounds


def _bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Expected random contexts until n valid ones, and the utility that a direct draw undercuts with probability exp(-tau) at most."""
    df, schema, rid = top(spark, sf_dir, "doc13")
    cell, _ = pl.lookup_record(df, schema, rid)
    valid, best = release.valid_contexts(df, schema, rid, det.Grubbs()).agg(F.count(F.lit(1)), F.max("u")).first()
    free = len(schema.free_bits(cell))
    rows = [(n, measures.expected_trials(valid, free, n), mech.utility_tail_bound(best, valid, 0.1, float(n) / 50)) for n in (25, 50, 100, 200)]
    return spark.createDataFrame(rows, "n int, trials double, bound double").select("n", F.round("trials", 6).alias("trials"), F.round("bound", 6).alias("bound"))


_add(
    "sampling_bounds_doc13",
    f"{grubbs_sql('doc13')} SELECT m::INT AS n, round(m * {1 << (wl.SCHEMAS['doc13'].t - wl.SCHEMAS['doc13'].m)}.0 / count(*), 6) AS trials, round(max(u) - (ln(count(*)) + m / 50) / 0.1, 6) AS bound FROM valid, (VALUES (25), (50), (100), (200)) AS t(m) GROUP BY m",
    _bounds,
)

# seeded trials, written out in SQL

_TRIALS, _STEPS = 4, 5


def _trials_sql(name: str) -> str:
    e1 = mech.allocate("bfs", EPS, _STEPS)
    parts = [_start_sql(name)]
    for t in range(_TRIALS):
        parts += [f"f{t}_0 AS MATERIALIZED (SELECT * FROM start)", f"s{t}_0 AS MATERIALIZED (SELECT * FROM start WHERE false)"]
        for i in range(_STEPS):
            parts += [
                f"p{t}_{i} AS MATERIALIZED ({_best(f'f{t}_{i}', e1, str(i), trial=str(t))})",
                f"s{t}_{i + 1} AS MATERIALIZED (SELECT * FROM s{t}_{i} UNION ALL SELECT * FROM p{t}_{i})",
                f"f{t}_{i + 1} AS MATERIALIZED (SELECT ctx, u FROM (SELECT ctx, u FROM f{t}_{i} UNION SELECT v.ctx, v.u FROM v, p{t}_{i} WHERE bit_count(xor(v.ctx, p{t}_{i}.ctx)) = 1) WHERE ctx NOT IN (SELECT ctx FROM s{t}_{i + 1}))",
            ]
    final = "'final'"
    drawn = " UNION ALL ".join(f"SELECT * FROM ({_best(f's{t}_{_STEPS}', e1, final, trial=str(t))})" for t in range(_TRIALS))
    return ",\n".join(parts) + f" SELECT count(*) AS trials, round(avg(u) / (SELECT max(u) FROM v), 9) AS utility FROM ({drawn})"


def _trials(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    df, schema, rid = top(spark, sf_dir, name)
    search = release.make_search(df, schema, rid, det.Grubbs())
    best = release.best_utility(df, schema, rid, det.Grubbs())
    t = release.run_trials(spark, {str(rid): search}, [("bfs", EPS, _STEPS)], _TRIALS, NOISE.seed, best={str(rid): best})
    return measures.utility_summary(t, []).select("trials", F.round("utility", 9).alias("utility"))


for _name in ("e14", "doc13"):
    _add(f"trials_summary_{_name}", _trials_sql(_name), lambda s, d, n=_name: _trials(s, d, n))


# the graph of valid contexts


def _components(spark: SparkSession, sf_dir: str) -> DataFrame:
    df, schema, rid = top(spark, sf_dir, "li12")
    return measures.graph_components(release.valid_contexts(df, schema, rid, det.LOF()), schema).groupBy("component").agg(F.count(F.lit(1)).alias("contexts"))


_add(
    "valid_graph_components_li12",
    lof_sql("li12").replace("WITH enc", "WITH RECURSIVE enc", 1)
    + ", v AS MATERIALIZED (SELECT ctx FROM valid), reach AS (SELECT ctx, ctx AS goal FROM v UNION SELECT reach.ctx, v.ctx FROM reach JOIN v ON bit_count(xor(reach.goal, v.ctx)) = 1), "
    "least_of AS (SELECT ctx, min(goal) AS component FROM reach GROUP BY ctx) SELECT component, count(*) AS contexts FROM least_of GROUP BY component",
    _components,
)
