"""Queries of the methods on the named datasets, each with independent SQL where SQL can say it."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from math import prod

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxrelease.functions import mechanism as mech
from ctxrelease.operators import detectors as det
from ctxrelease.operators import measures, release
from ctxrelease.plans import cells as pl
from ctxrelease.plans.runtime import bounded_broadcast, cut, shared_dir, table
from ctxrelease.schema import Context
from ctxrelease.sources import sinks
from ctxrelease.sources import workloads as wl

EPS, SAMPLES = 0.2, 5
Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(fn: Query) -> Query:
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return keep


def critical_ctes(sizes: str, alpha: float = 0.05) -> str:
    """CTEs that end in k(n, crit): critical values of the sizes in a relation, for oracles.

    Independent of the library's: the tail of Student's distribution by Simpson's rule over an exponential variable, and
    Newton's rule for its logarithm, written out. DuckDB only supplies lgamma.
    """
    panels, width = 1000, 0.04
    goal = f"ln({alpha} / (2 * n))"
    steps = [
        f"nodes AS MATERIALIZED (SELECT j * {width} AS y, {width} / 3 * exp(-j * {width}) * CASE WHEN j IN (0, {panels}) THEN 1 WHEN j % 2 = 1 THEN 4 ELSE 2 END AS w FROM range({panels + 1}) AS r(j))",
        f"q0 AS MATERIALIZED (SELECT n, (n - 2)::DOUBLE AS v, sqrt(-2 * {goal}) AS t FROM (SELECT DISTINCT n FROM {sizes} WHERE n >= 3))",
    ]
    for i in range(8):
        steps.append(
            f"q{i + 1} AS MATERIALIZED (SELECT n, v, t * exp((lgamma((v + 1) / 2) - lgamma(v / 2) - ln(pi()) / 2 + v / 2 * ln(c) - ln(v) + ln(total) - {goal}) * total / (sqrt(v) * t * sqrt(c))) AS t "
            f"FROM (SELECT n, v, t, v / (v + t * t) AS c, sum(w / sqrt(1 - v / (v + t * t) * exp(-2 * y / v))) AS total FROM q{i}, nodes GROUP BY n, v, t))"
        )
    steps.append("k AS MATERIALIZED (SELECT n, (n - 1) / sqrt(n) * sqrt(t * t / (v + t * t)) AS crit FROM q8)")
    return ",\n".join(steps)


def top(spark: SparkSession, sf_dir: str, name: str):
    df, schema = wl.workload(spark, sf_dir, name)
    rid = wl.top_records(df, schema)[0]
    return df, schema, rid


def base_sql(name: str) -> str:
    """CTEs: the encoded rows, the record with the largest metric, cells, candidates with moments."""
    return f"""
WITH enc AS ({wl.encoded_sql(name)}),
anchor AS (SELECT cell, x FROM enc ORDER BY x DESC, record_id LIMIT 1),
cells AS (SELECT cell, count(*) AS n, sum(x::HUGEINT) AS s, sum(x::HUGEINT * x) AS ss, min(x) AS lo, max(x) AS hi FROM enc GROUP BY cell),
cand AS ({wl.candidates_sql(name)}),
stats AS (SELECT ctx, sum(n)::BIGINT AS n, sum(s)::DOUBLE AS s, sum(ss)::DOUBLE AS ss, min(lo) AS lo, max(hi) AS hi FROM cand JOIN cells ON cell & ctx = cell GROUP BY ctx)"""


def grubbs_sql(name: str) -> str:
    return f"""{base_sql(name)},
{critical_ctes('stats')},
scored AS (SELECT ctx, n, CASE WHEN n >= 3 AND ss - s * (s / n) > 0 THEN abs(x - s / n) / sqrt((ss - s * (s / n)) / (n - 1)) ELSE 0 END AS score FROM stats, anchor),
judged AS (SELECT scored.ctx, scored.n, score, coalesce(score > crit, false) AS is_outlier FROM scored LEFT JOIN k ON k.n = scored.n),
valid AS (SELECT ctx, n AS u FROM judged WHERE is_outlier)"""


def gumbel_sql(*key: str) -> str:
    text = " || '|' || ".join(["'0'", *(f"({k})::VARCHAR" for k in key)])
    return f"(-ln(-ln((('0x' || substr(md5({text}), 1, 13))::BIGINT + 0.5) / {1 << 52})))"


def uniform_sql(*key: str) -> str:
    text = " || '|' || ".join(["'0'", *(f"({k})::VARCHAR" for k in key)])
    return f"((('0x' || substr(md5({text}), 1, 13))::BIGINT + 0.5) / {1 << 52})"


NOISE = mech.SeededNoise(0)

for _name in ("e14", "doc13", "o13", "emb10", "e25", "cv11"):
    query(f"encode_{_name}", wl.encoded_sql(_name))(lambda s, d, n=_name: pl.encode(*wl.workload(s, d, n)))
for _name in ("li12", "li16"):
    query(f"encode_{_name}", f"SELECT cell, x FROM ({wl.encoded_sql(_name)})")(lambda s, d, n=_name: pl.encode(*wl.workload(s, d, n)).select("cell", "x"))
for _name in ("e14", "li12", "doc13", "o13", "li16", "e25", "cv11", "emb10"):
    query(f"cells_{_name}", f"SELECT cell, n, s::BIGINT AS s, ss::DOUBLE AS ss, lo, hi FROM ({wl.cells_sql(_name)})")(
        lambda s, d, n=_name: pl.build_cells(*wl.workload(s, d, n)).select("cell", "n", F.col("s").cast("long"), F.col("ss").cast("double"), "lo", "hi")
    )


def _folded(spark, sf_dir, name):
    df, schema, rid = top(spark, sf_dir, name)
    cell, _ = pl.lookup_record(df, schema, rid)
    return pl.fold_contexts(pl.build_cells(df, schema), schema, cell)


for _name in ("e14", "li12", "doc13", "o13"):
    query(f"context_population_{_name}", f"{base_sql(_name)} SELECT ctx, n FROM stats")(lambda s, d, n=_name: _folded(s, d, n).select("ctx", "n"))


def _population_by_cells(spark, sf_dir, name):
    df, schema, rid = top(spark, sf_dir, name)
    cell, _ = pl.lookup_record(df, schema, rid)
    return pl.context_stats(pl.build_cells(df, schema), pl.candidate_contexts(spark, schema, cell)).select("ctx", "n")


for _name in ("li12",):
    query(f"context_population_by_cells_{_name}", f"{base_sql(_name)} SELECT ctx, n FROM stats")(lambda s, d, n=_name: _population_by_cells(s, d, n))


_START_E14 = Context.of(wl.SCHEMAS["e14"], day=["1", "2", "3"]).mask


@query("context_overlap_e14", f"{base_sql('e14')} SELECT cand.ctx, sum(n)::BIGINT AS u FROM cand JOIN cells ON cell & (cand.ctx & {_START_E14}) = cell GROUP BY cand.ctx")
def _overlap(spark, sf_dir):
    df, schema, rid = top(spark, sf_dir, "e14")
    cell, _ = pl.lookup_record(df, schema, rid)
    cells = pl.build_cells(df, schema)
    cand = pl.candidate_contexts(spark, schema, cell).withColumn("both", F.col("ctx").bitwiseAND(F.lit(_START_E14)))
    sizes = pl.context_stats(cells, cand.select(F.col("both").alias("ctx")).distinct()).select(F.col("ctx").alias("both"), F.col("n").alias("u"))
    return cand.join(sizes, "both").select("ctx", "u")


def _cube_sql(name: str) -> str:
    schema = wl.SCHEMAS[name]
    parts = [f"coalesce(cell & {m}, {m})" if False else f"cell & {m} AS a{i}" for i, m in enumerate(schema.attr_masks)]
    keys = ", ".join(f"a{i}" for i in range(schema.m))
    ctx = " | ".join(f"coalesce(a{i}, {m})" for i, m in enumerate(schema.attr_masks))
    return f"SELECT ({ctx})::BIGINT AS ctx, count(*) AS n FROM (SELECT {', '.join(parts)} FROM ({wl.encoded_sql(name)})) GROUP BY CUBE ({keys})"


@query("context_cube_e14", _cube_sql("e14"))
def _cube(spark, sf_dir):
    df, schema = wl.workload(spark, sf_dir, "e14")
    simple = F.lit(True)
    for m in schema.attr_masks:
        part = F.col("ctx").bitwiseAND(F.lit(m))
        simple = simple & ((part == m) | (F.bit_count(part) == 1))
    return pl.fold_contexts(pl.build_cells(df, schema), schema).where(simple).select("ctx", "n")


@query("neighbors_e14", f"{base_sql('e14')} SELECT cell AS ctx, xor(cell, 1 << b) AS neighbor FROM anchor, range(14) AS r(b)".replace("1 << b", "(1::BIGINT << b::INT)"))
def _neighbors(spark, sf_dir):
    df, schema, rid = top(spark, sf_dir, "e14")
    cell, _ = pl.lookup_record(df, schema, rid)
    return pl.neighbors(spark.createDataFrame([(cell,)], "ctx long"), schema.t)


def _wellformed(spark, sf_dir, name):
    """How many well-formed contexts hold a row of the table."""
    df, schema = wl.workload(spark, sf_dir, name)
    cells = bounded_broadcast(pl.build_cells(df, schema).select("cell"), prod(len(a.domain) for a in schema.attrs), 16)
    every = spark.range(1 << schema.t).select(F.col("id").alias("ctx")).where(pl.wellformed(schema))
    return every.join(cells, F.col("cell").bitwiseAND(F.col("ctx")) == F.col("cell"), "left_semi").agg(F.count(F.lit(1)).alias("contexts"))


for _name, _on in (("inc9", "o9"), ("e14", "e14"), ("li12", "li12")):
    _s = wl.SCHEMAS[_on]
    query(
        f"wellformed_count_{_name}",
        f"WITH enc AS ({wl.encoded_sql(_on)}), cells AS (SELECT DISTINCT cell FROM enc) SELECT count(*) AS contexts FROM range({1 << _s.t}) AS c(ctx) WHERE "
        + " AND ".join(f"ctx & {m} <> 0" for m in _s.attr_masks) + " AND EXISTS (SELECT 1 FROM cells WHERE cell & ctx = cell)",
    )(lambda s, d, n=_on: _wellformed(s, d, n))


def _grubbs(spark, sf_dir, name):
    df, schema, rid = top(spark, sf_dir, name)
    cell, x = pl.lookup_record(df, schema, rid)
    folded = pl.fold_contexts(pl.build_cells(df, schema), schema, cell)
    return det.grubbs_columns(folded, x).select("ctx", "n", "is_outlier", F.round("score", 6).alias("score"))


for _name in ("e14", "doc13", "li12", "o13"):
    query(f"grubbs_verify_{_name}", f"{grubbs_sql(_name)} SELECT ctx, n, is_outlier, round(score, 6) AS score FROM judged")(lambda s, d, n=_name: _grubbs(s, d, n))


def _verified(spark, sf_dir, name, detector):
    df, schema, rid = top(spark, sf_dir, name)
    cell, x = pl.lookup_record(df, schema, rid)
    return det.verify(pl.candidate_contexts(spark, schema, cell), det.take_slice(df, schema, detector, x), detector, x)


def hist_sql(name: str) -> str:
    return f"""{base_sql(name)},
bins AS (SELECT ctx, n, lo, hi, greatest(1, floor(sqrt(n)))::BIGINT AS b FROM stats WHERE n * 0.0025 > 1 AND hi > lo),
own AS (SELECT bins.*, least((x - lo) * b // (hi - lo), b - 1) AS k FROM bins, anchor),
held AS (SELECT ctx, count(*) AS c FROM own JOIN enc ON cell & ctx = cell AND least((enc.x - lo) * b // (hi - lo), b - 1) = k GROUP BY ctx),
judged AS (SELECT stats.ctx, stats.n, coalesce(c < 0.0025 * stats.n, false) AS is_outlier FROM stats LEFT JOIN held ON held.ctx = stats.ctx)"""


for _name in ("e14", "doc13", "li12"):
    query(f"hist_verify_{_name}", f"{hist_sql(_name)} SELECT ctx, n AS population, is_outlier FROM judged")(lambda s, d, n=_name: _verified(s, d, n, det.Histogram()).select("ctx", "population", "is_outlier"))
    query(f"valid_hist_{_name}", f"{hist_sql(_name)} SELECT ctx, n AS u FROM judged WHERE is_outlier")(lambda s, d, n=_name: _verified(s, d, n, det.Histogram()).where("is_outlier").select("ctx", F.col("population").alias("u")))
    query(f"valid_zscore_{_name}", f"{base_sql(_name)} SELECT ctx, n AS u FROM stats, anchor WHERE n >= 2 AND abs(x - s / n) / sqrt((ss - s * (s / n)) / (n - 1)) > 3")(
        lambda s, d, n=_name: _verified(s, d, n, det.ZScore()).where("is_outlier").select("ctx", F.col("population").alias("u"))
    )

_K = 10


def lof_sql(name: str) -> str:
    """Factors of the record in all candidate contexts, from the definition over the 3k+1 nearest distinct values on either side."""
    return f"""{base_sql(name)},
vals AS MATERIALIZED (SELECT cell, x, count(*) AS cnt FROM enc GROUP BY cell, x),
held AS (SELECT cand.ctx, x, sum(cnt) AS cnt FROM cand JOIN vals ON cell & cand.ctx = cell GROUP BY cand.ctx, x),
ranked AS (SELECT held.*, row_number() OVER (PARTITION BY ctx, held.x <= anchor.x ORDER BY abs(held.x - anchor.x)) AS r FROM held, anchor),
pts AS MATERIALIZED (SELECT ctx, x, cnt FROM ranked WHERE r <= {3 * _K + 1}),
dist AS MATERIALIZED (SELECT p.ctx, p.x, q.x AS y, abs(p.x - q.x)::DOUBLE AS d, (q.cnt - (p.x = q.x)::INT)::DOUBLE AS c FROM pts p JOIN pts q ON p.ctx = q.ctx),
cum AS (SELECT *, sum(c) OVER (PARTITION BY ctx, x ORDER BY d RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS total FROM dist),
kd AS MATERIALIZED (SELECT ctx, x, coalesce(min(d) FILTER (total >= {_K}), max(d)) AS kd FROM cum GROUP BY ctx, x),
near AS MATERIALIZED (SELECT dist.ctx, dist.x, dist.y, c, greatest(dist.d, b.kd) AS reach FROM dist JOIN kd a ON a.ctx = dist.ctx AND a.x = dist.x JOIN kd b ON b.ctx = dist.ctx AND b.x = dist.y WHERE dist.d <= a.kd AND c > 0),
lrd AS MATERIALIZED (SELECT ctx, x, CASE WHEN sum(c * reach) > 0 THEN sum(c) / sum(c * reach) ELSE 'inf'::DOUBLE END AS lrd FROM near GROUP BY ctx, x),
lof AS (SELECT near.ctx, any_value(a.lrd) AS own, sum(c * b.lrd) / sum(c) AS others, bool_and(isinf(b.lrd)) AS dense FROM near JOIN anchor ON near.x = anchor.x JOIN lrd a ON a.ctx = near.ctx AND a.x = near.x JOIN lrd b ON b.ctx = near.ctx AND b.x = near.y GROUP BY near.ctx),
judged AS (SELECT stats.ctx, stats.n, CASE WHEN stats.n <= {_K} THEN 0.0 WHEN isinf(own) THEN CASE WHEN dense THEN 1.0 ELSE 0.0 END ELSE others / own END AS score FROM stats LEFT JOIN lof ON lof.ctx = stats.ctx),
valid AS (SELECT ctx, n AS u FROM judged WHERE score > 1.5)"""


for _name in ("e14", "doc13", "li12"):
    query(f"lof_verify_{_name}", f"{lof_sql(_name)} SELECT ctx, n AS population, score > 1.5 AS is_outlier, round(score, 6) AS score FROM judged")(
        lambda s, d, n=_name: _verified(s, d, n, det.LOF(_K)).withColumn("score", F.round("score", 6))
    )
    query(f"valid_lof_{_name}", f"{lof_sql(_name)} SELECT ctx, u FROM valid")(lambda s, d, n=_name: _verified(s, d, n, det.LOF(_K)).where("is_outlier").select("ctx", F.col("population").alias("u")))


def _valid(spark, sf_dir, name, detector=None):
    df, schema, rid = top(spark, sf_dir, name)
    return release.valid_contexts(df, schema, rid, detector or det.Grubbs())


for _name in ("e14", "li12", "doc13", "o13"):
    query(f"valid_grubbs_{_name}", f"{grubbs_sql(_name)} SELECT ctx, u FROM valid")(lambda s, d, n=_name: _valid(s, d, n).select("ctx", "u"))
for _name in ("e14", "li12", "doc13"):
    query(f"max_context_grubbs_{_name}", f"{grubbs_sql(_name)} SELECT ctx, u FROM valid ORDER BY u DESC, ctx DESC LIMIT 1")(lambda s, d, n=_name: release.maximum_context(_valid(s, d, n)))
    query(f"exp_probabilities_{_name}", f"{grubbs_sql(_name)} SELECT ctx, round(exp(0.1 * (u - max(u) OVER ())) / sum(exp(0.1 * (u - (SELECT max(u) FROM valid)))) OVER (), 9) AS p FROM valid")(
        lambda s, d, n=_name: mech.selection_probabilities(_valid(s, d, n), 0.1).select("ctx", F.round("p", 9).alias("p"))
    )


@query("max_context_hist_e14", f"{hist_sql('e14')} SELECT ctx, n AS u FROM judged WHERE is_outlier ORDER BY n DESC, ctx DESC LIMIT 1")
def _max_hist(spark, sf_dir):
    return release.maximum_context(_valid(spark, sf_dir, "e14", det.Histogram()))


@query("exp_draw_seeded_e14", f"{grubbs_sql('e14')} SELECT t::INT AS trial, max_by(ctx, (0.0005 * u + {gumbel_sql('t', 'ctx')}, ctx)) AS ctx FROM valid, range(50) AS r(t) GROUP BY t".replace("(0.0005", "row(0.0005"))
def _draws(spark, sf_dir):
    valid = _valid(spark, sf_dir, "e14").select("ctx", "u")
    many = valid.withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(49))))
    return mech.exp_mechanism(many, 0.0005, NOISE, by=["trial"]).select("trial", "ctx")


@query("direct_release_e14", f"{grubbs_sql('e14')} SELECT max_by(ctx, row(0.1 * u + {gumbel_sql('0', '0', 'ctx')}, ctx)) AS ctx, max_by(u, row(0.1 * u + {gumbel_sql('0', '0', 'ctx')}, ctx)) AS u FROM valid")
def _direct(spark, sf_dir):
    df, schema, rid = top(spark, sf_dir, "e14")
    return release.direct_release(df, schema, rid, det.Grubbs(), EPS, NOISE)


# searches: the seeded noise is the same in SQL, where the steps are written out


def _best(source: str, factor: float, *key: str, trial: str = "0") -> str:
    score = f"row({factor!r} * u + {gumbel_sql(trial, *key, 'ctx')}, ctx)"
    return f"SELECT max_by(ctx, {score}) AS ctx, max_by(u, {score}) AS u FROM {source} HAVING count(*) > 0"


def _start_sql(name: str, valid: Callable[[str], str] = grubbs_sql) -> str:
    return f"{valid(name)}, v AS MATERIALIZED (SELECT ctx, u FROM valid), start AS MATERIALIZED (SELECT ctx, u FROM v ORDER BY bit_count(ctx), ctx LIMIT 1)"


def bfs_sql(name: str, n: int, valid: Callable[[str], str] = grubbs_sql, inclusive: bool = False) -> str:
    e1 = mech.allocate("bfs", EPS, n, inclusive=inclusive)
    n += inclusive
    steps = [_start_sql(name, valid), "f0 AS MATERIALIZED (SELECT * FROM start)", "s0 AS MATERIALIZED (SELECT * FROM start WHERE false)"]
    for i in range(n):
        steps += [
            f"p{i} AS MATERIALIZED ({_best(f'f{i}', e1, str(i))})",
            f"s{i + 1} AS MATERIALIZED (SELECT * FROM s{i} UNION ALL SELECT * FROM p{i})",
            f"f{i + 1} AS MATERIALIZED (SELECT ctx, u FROM (SELECT ctx, u FROM f{i} UNION SELECT v.ctx, v.u FROM v, p{i} WHERE bit_count(xor(v.ctx, p{i}.ctx)) = 1) WHERE ctx NOT IN (SELECT ctx FROM s{i + 1}))",
        ]
    q = f"'final'"
    return ",\n".join(steps) + f" {_best(f's{n}', e1, q)}"


def dfs_sql(name: str, n: int, final: str = "visited") -> str:
    """Without going back, which the datasets here don't need."""
    e1 = mech.allocate("dfs", EPS, n, final)
    steps = [_start_sql(name), "p0 AS MATERIALIZED (SELECT * FROM start)", "s1 AS MATERIALIZED (SELECT * FROM start)"]
    for i in range(1, n):
        steps += [
            f"k{i} AS MATERIALIZED (SELECT v.ctx, v.u FROM v, p{i - 1} p WHERE bit_count(xor(v.ctx, p.ctx)) = 1 AND v.ctx NOT IN (SELECT ctx FROM s{i}))",
            f"p{i} AS MATERIALIZED ({_best(f'k{i}', e1, str(i))})",
            f"s{i + 1} AS MATERIALIZED (SELECT * FROM s{i} UNION ALL SELECT * FROM p{i})",
        ]
    q = "'final'"
    if final == "last":
        return ",\n".join(steps) + f" SELECT ctx, u FROM p{n - 1}"
    return ",\n".join(steps) + f" {_best(f's{n}', e1, q)}"


def walk_sql(name: str, n: int, distinct: bool = False) -> str:
    e1 = mech.allocate("walk", EPS, n)
    steps = [_start_sql(name), "p0 AS MATERIALIZED (SELECT * FROM start)", "s1 AS MATERIALIZED (SELECT * FROM start)"]
    for i in range(1, n):
        order = f"row({uniform_sql('0', str(i), 'v.ctx')}, v.ctx)"
        steps += [
            f"p{i} AS MATERIALIZED (SELECT min_by(v.ctx, {order}) AS ctx, min_by(v.u, {order}) AS u FROM v, p{i - 1} p WHERE bit_count(xor(v.ctx, p.ctx)) = 1 HAVING count(*) > 0)",
            f"s{i + 1} AS MATERIALIZED (SELECT * FROM s{i} UNION ALL SELECT * FROM p{i})",
        ]
    q = "'final'"
    pool = f"(SELECT DISTINCT ctx, u FROM s{n})" if distinct else f"s{n}"
    return ",\n".join(steps) + f" {_best(pool, e1, q)}"


def uniform_release_sql(name: str, n: int, most: int = 256, p: float = 0.5) -> str:
    schema = wl.SCHEMAS[name]
    e1 = mech.allocate("uniform", EPS, n)
    free = f"(SELECT b, row_number() OVER (ORDER BY b) - 1 AS j FROM anchor, range({schema.t}) AS r(b) WHERE (anchor.cell >> b::INT) & 1 = 0)"
    q = "'u'"
    return f"""{_start_sql(name)},
tries AS (SELECT i, (SELECT cell FROM anchor) | coalesce(bit_or(1::BIGINT << b::INT) FILTER ({uniform_sql('0', q, 'i', 'j')} < {p}), 0) AS ctx FROM range({most}) AS t(i), {free} GROUP BY i),
got AS MATERIALIZED (SELECT v.ctx, v.u, min(i) AS i FROM tries JOIN v ON v.ctx = tries.ctx GROUP BY v.ctx, v.u ORDER BY i LIMIT {n})
{_best('got', e1, "'final'")}"""


def _searched(spark, sf_dir, name, method, n, detector=None, **options):
    df, schema, rid = top(spark, sf_dir, name)
    search = release.make_search(df, schema, rid, detector or det.Grubbs())
    o = search.run(method, EPS, n, NOISE, 0, **options)
    return spark.createDataFrame([(o.ctx, int(o.utility))], "ctx long, u long")


for _name in ("e14", "li12", "doc13"):
    query(f"bfs_release_{_name}", bfs_sql(_name, SAMPLES))(lambda s, d, n=_name: _searched(s, d, n, "bfs", SAMPLES))
    query(f"dfs_release_{_name}", dfs_sql(_name, SAMPLES))(lambda s, d, n=_name: _searched(s, d, n, "dfs", SAMPLES))
    query(f"walk_release_{_name}", walk_sql(_name, SAMPLES))(lambda s, d, n=_name: _searched(s, d, n, "walk", SAMPLES))
    query(f"uniform_release_{_name}", uniform_release_sql(_name, SAMPLES))(lambda s, d, n=_name: _searched(s, d, n, "uniform", SAMPLES))
    query(f"lof_bfs_release_{_name}", bfs_sql(_name, 20, lof_sql))(lambda s, d, n=_name: _searched(s, d, n, "bfs", 20, det.LOF()))


def _bfs_lockstep(spark, sf_dir, name):
    df, schema, rid = top(spark, sf_dir, name)
    search = release.make_search(df, schema, rid, det.Grubbs())
    return release.lockstep(df, schema, rid, "bfs", EPS, 3, search.start, 1, NOISE).select("ctx", "u")


for _name in ("li12",):
    query(f"bfs_lockstep_{_name}", bfs_sql(_name, 3))(lambda s, d, n=_name: _bfs_lockstep(s, d, n))


def greedy_sql(name: str, n: int) -> str:
    steps = [_start_sql(name), "f0 AS MATERIALIZED (SELECT * FROM start)", "s0 AS MATERIALIZED (SELECT * FROM start WHERE false)"]
    for i in range(n):
        steps += [
            f"p{i} AS MATERIALIZED (SELECT ctx, u FROM f{i} ORDER BY u DESC, ctx DESC LIMIT 1)",
            f"s{i + 1} AS MATERIALIZED (SELECT * FROM s{i} UNION ALL SELECT * FROM p{i})",
            f"f{i + 1} AS MATERIALIZED (SELECT ctx, u FROM (SELECT ctx, u FROM f{i} UNION SELECT v.ctx, v.u FROM v, p{i} WHERE bit_count(xor(v.ctx, p{i}.ctx)) = 1) WHERE ctx NOT IN (SELECT ctx FROM s{i + 1}))",
        ]
    return ",\n".join(steps) + f" SELECT ctx, u FROM s{n} ORDER BY u DESC, ctx DESC LIMIT 1"


def greedy_dfs_sql(name: str, n: int) -> str:
    """Without going back: the path ends where no unvisited valid neighbour is left."""
    steps = [_start_sql(name), "p0 AS MATERIALIZED (SELECT * FROM start)", "s1 AS MATERIALIZED (SELECT * FROM start)"]
    for i in range(1, n):
        steps += [
            f"p{i} AS MATERIALIZED (SELECT v.ctx, v.u FROM v, p{i - 1} p WHERE bit_count(xor(v.ctx, p.ctx)) = 1 AND v.ctx NOT IN (SELECT ctx FROM s{i}) ORDER BY v.u DESC, v.ctx DESC LIMIT 1)",
            f"s{i + 1} AS MATERIALIZED (SELECT * FROM s{i} UNION ALL SELECT * FROM p{i})",
        ]
    return ",\n".join(steps) + f" SELECT ctx, u FROM s{n} ORDER BY u DESC, ctx DESC LIMIT 1"


for _name in ("li12",):
    query(f"greedy_bfs_{_name}", greedy_sql(_name, SAMPLES))(lambda s, d, n=_name: _searched(s, d, n, "greedy_bfs", SAMPLES))
    query(f"greedy_dfs_{_name}", greedy_dfs_sql(_name, SAMPLES))(lambda s, d, n=_name: _searched(s, d, n, "greedy_dfs", SAMPLES))


for _name in ("e14", "li12", "doc13"):
    query(
        f"locality_{_name}",
        f"""{grubbs_sql(_name)}, v AS MATERIALIZED (SELECT ctx FROM valid),
pairs AS (SELECT a.ctx, xor(a.ctx, 1::BIGINT << b::INT) AS nb FROM v a, range({wl.SCHEMAS[_name].t}) AS r(b), anchor WHERE (anchor.cell >> b::INT) & 1 = 0)
SELECT (SELECT count(*) FROM v) AS valid, round(count(v.ctx) / count(*), 6) AS p_neighbor, round((SELECT count(*) FROM v) / {1 << (wl.SCHEMAS[_name].t - wl.SCHEMAS[_name].m)}, 6) AS p_random FROM pairs LEFT JOIN v ON v.ctx = pairs.nb""",
    )(lambda s, d, n=_name: _locality(s, d, n))


def _locality(spark, sf_dir, name):
    df, schema, rid = top(spark, sf_dir, name)
    cell, _ = pl.lookup_record(df, schema, rid)
    found = measures.locality(_valid(spark, sf_dir, name), schema, cell)
    return found.select("valid", F.round("p_neighbor", 6).alias("p_neighbor"), F.round("p_random", 6).alias("p_random"))


# whole populations


def _flag_sql(name: str) -> str:
    return f"WITH enc AS ({wl.encoded_sql(name)}), st AS (SELECT count(*) AS n, sum(x::HUGEINT)::DOUBLE AS s, sum(x::HUGEINT * x)::DOUBLE AS ss, min(x) AS lo, max(x) AS hi FROM enc)"


@query("flag_all_grubbs_doc13", f"{_flag_sql('doc13')}, {critical_ctes('st')} SELECT record_id, x, abs(x - s / st.n) / sqrt((ss - s * (s / st.n)) / (st.n - 1)) > crit AS is_outlier FROM enc, st JOIN k ON k.n = st.n")
def _flag_grubbs(spark, sf_dir):
    df, schema = wl.workload(spark, sf_dir, "doc13")
    return det.flag_all(df, schema, det.Grubbs(), schema.full)


@query(
    "flag_all_hist_doc13",
    f"{_flag_sql('doc13')}, binned AS (SELECT record_id, x, n, least((x - lo) * floor(sqrt(n))::BIGINT // (hi - lo), floor(sqrt(n))::BIGINT - 1) AS b FROM enc, st) SELECT record_id, x, count(*) OVER (PARTITION BY b) < 0.0025 * n AS is_outlier FROM binned",
)
def _flag_hist(spark, sf_dir):
    df, schema = wl.workload(spark, sf_dir, "doc13")
    return det.flag_all(df, schema, det.Histogram(), schema.full)


@query(
    "flag_all_lof_doc13",
    f"""WITH enc AS ({wl.encoded_sql('doc13')}), pts AS (SELECT row_number() OVER (ORDER BY x, record_id) AS i, record_id, x::DOUBLE AS x, x AS whole FROM enc),
dist AS (SELECT p.i, q.i AS j, abs(p.x - q.x) AS d, row_number() OVER (PARTITION BY p.i ORDER BY abs(p.x - q.x)) AS r FROM pts p JOIN pts q ON p.i <> q.i),
kd AS (SELECT i, max(d) FILTER (r = 10) AS kd FROM dist GROUP BY i),
near AS (SELECT dist.i, dist.j, greatest(dist.d, kj.kd) AS reach FROM dist JOIN kd ki ON ki.i = dist.i JOIN kd kj ON kj.i = dist.j WHERE dist.d <= ki.kd),
lrd AS (SELECT i, CASE WHEN sum(reach) > 0 THEN count(*) / sum(reach) ELSE 'inf'::DOUBLE END AS lrd FROM near GROUP BY i),
lof AS (SELECT near.i, any_value(a.lrd) AS own, avg(b.lrd) AS others, bool_and(isinf(b.lrd)) AS allinf FROM near JOIN lrd a ON a.i = near.i JOIN lrd b ON b.i = near.j GROUP BY near.i)
SELECT record_id, whole AS x, CASE WHEN isinf(own) THEN CASE WHEN allinf THEN 1.0 ELSE 0.0 END ELSE others / own END > 1.5 AS is_outlier FROM lof JOIN pts ON pts.i = lof.i""",
)
def _flag_lof(spark, sf_dir):
    df, schema = wl.workload(spark, sf_dir, "doc13")
    return det.flag_all(df, schema, det.LOF(), schema.full)


def far_values(df: DataFrame, schema, detector: det.Grubbs | None = None) -> tuple[DataFrame, DataFrame]:
    """Statistics of all contexts, and (ctx, cell, x, cnt) of the distinct values that are outliers there.

    Only values beyond the least bound of any context meet contexts; each goes to the contexts that hold its cell by
    joins with the tables of subsets, and meets their bounds by key.
    """
    detector = detector or det.Grubbs()
    stats = cut(pl.fold_contexts(pl.build_cells(df, schema), schema))
    bounds = det.grubbs_bounds(stats, detector.alpha, detector.sides)
    least = bounds.agg(F.min(F.col("mean") + F.col("reach")).alias("above"), F.max(F.col("mean") - F.col("reach")).alias("below"))
    values = pl.build_cell_values(df, schema)
    some = values.join(F.broadcast(least), (F.col("x") > F.col("above")) | (F.col("x") < F.col("below"))).select("cell", "x", "cnt")  # one row
    hits = pl.supersets(some, schema).join(bounded_broadcast(bounds, schema.wellformed_count(), 32), "ctx").where(F.abs(F.col("x") - F.col("mean")) > F.col("reach"))
    return stats, hits.select("ctx", "cell", "x", "cnt")


def reference_file(df: DataFrame, schema, detector: det.Grubbs | None = None) -> DataFrame:
    """(ctx, population, n_outliers): every well-formed context with rows, and how many records it makes outliers."""
    stats, hits = far_values(df, schema, detector)
    counts = hits.groupBy("ctx").agg(F.sum("cnt").alias("hits"))
    return stats.join(counts, "ctx", "left").select("ctx", F.col("n").alias("population"), F.coalesce("hits", F.lit(0)).cast("long").alias("n_outliers"))


def reference_list(df: DataFrame, schema, detector: det.Grubbs | None = None) -> DataFrame:
    """(ctx, record_id): the outliers of every context, a row each, so that no list gathers in one task."""
    _, hits = far_values(df, schema, detector)
    return pl.encode(df, schema).join(hits.select("ctx", "cell", "x"), ["cell", "x"]).select("ctx", "record_id")


def _bounds_sql(name: str) -> str:
    schema = wl.SCHEMAS[name]
    return f"""WITH enc AS ({wl.encoded_sql(name)}), cells AS ({wl.cells_sql(name)}),
stats AS MATERIALIZED (SELECT c.ctx, sum(n)::BIGINT AS n, sum(s)::DOUBLE AS s, sum(ss)::DOUBLE AS ss FROM range({1 << schema.t}) AS c(ctx) JOIN cells ON cell & c.ctx = cell GROUP BY c.ctx),
{critical_ctes('stats')},
bounds AS MATERIALIZED (SELECT stats.*, s / stats.n AS mean, crit * sqrt(greatest((ss - s * (s / stats.n)) / (stats.n - 1), 0)) AS reach FROM stats LEFT JOIN k ON k.n = stats.n),
vals AS (SELECT cell, x, count(*) AS cnt FROM enc GROUP BY cell, x),
far AS MATERIALIZED (SELECT * FROM vals WHERE x > (SELECT min(mean + reach) FROM bounds WHERE reach > 0) OR x < (SELECT max(mean - reach) FROM bounds WHERE reach > 0)),
hits AS (SELECT bounds.ctx, cell, x, cnt FROM bounds JOIN far ON cell & bounds.ctx = cell AND reach > 0 AND abs(x - mean) > reach)"""


for _name in ("li12", "doc13"):
    query(f"reference_file_{_name}", f"{_bounds_sql(_name)} SELECT stats.ctx, any_value(stats.n) AS population, coalesce(sum(cnt), 0)::BIGINT AS n_outliers FROM stats LEFT JOIN hits ON hits.ctx = stats.ctx GROUP BY stats.ctx")(
        lambda s, d, n=_name: reference_file(*wl.workload(s, d, n))
    )
query("reference_list_doc13", f"{_bounds_sql('doc13')} SELECT ctx, record_id FROM enc JOIN hits ON enc.cell = hits.cell AND enc.x = hits.x")(lambda s, d: reference_list(*wl.workload(s, d, "doc13")))


@query("reference_sink_doc13", f"{_bounds_sql('doc13')} SELECT stats.ctx, any_value(stats.n) AS population, coalesce(sum(cnt), 0)::BIGINT AS n_outliers FROM stats LEFT JOIN hits ON hits.ctx = stats.ctx WHERE (SELECT cell FROM enc ORDER BY x DESC, record_id LIMIT 1) & stats.ctx = (SELECT cell FROM enc ORDER BY x DESC, record_id LIMIT 1) GROUP BY stats.ctx")
def _reference_sink(spark, sf_dir):
    """The reference file written, and a record's contexts read back from the folders that may hold them."""
    df, schema, rid = top(spark, sf_dir, "doc13")
    path = f"{shared_dir(spark)}/reference-{uuid.uuid4().hex}"
    sinks.save_reference_file(reference_file(df, schema), schema, path)
    return sinks.read_reference_file(spark, schema, path, pl.lookup_record(df, schema, rid)[0]).select("ctx", "population", "n_outliers")


def hidden(df: DataFrame, schema) -> DataFrame:
    """(record_id, contexts): records that are outliers in some context, but not in the whole table."""
    _, hits = far_values(df, schema)
    flagged = hits.groupBy("cell", "x").agg(F.count(F.lit(1)).alias("contexts"), F.bool_or(F.col("ctx") == schema.full).alias("global_flag")).where("not global_flag")
    return pl.encode(df, schema).join(flagged, ["cell", "x"]).select("record_id", "contexts", "global_flag")


def _hidden_sql(name: str) -> str:
    full = wl.SCHEMAS[name].full
    return f"{_bounds_sql(name)} SELECT record_id, contexts, global_flag FROM enc JOIN (SELECT cell, x, count(*) AS contexts, bool_or(ctx = {full}) AS global_flag FROM hits GROUP BY cell, x) f ON f.cell = enc.cell AND f.x = enc.x WHERE NOT global_flag"


for _name in ("doc13", "li12"):
    query(f"hidden_outliers_{_name}", _hidden_sql(_name))(lambda s, d, n=_name: hidden(*wl.workload(s, d, n)))


@query(
    "hidden_numeric_threshold_li12",
    _hidden_sql("li12").replace("FROM lineitem)", "FROM (SELECT * FROM lineitem WHERE l_quantity < 10))"),
)
def _hidden_threshold(spark, sf_dir):
    """Hidden outliers among records under a numeric threshold: the predicate reaches the scan, contexts see what is left."""
    df, schema = wl.workload(spark, sf_dir, "li12")
    return hidden(df.where("l_quantity < 10"), schema)


@query("flag_all_iterative_doc13")
def _iterative(spark, sf_dir):
    """Grubbs' test repeated without the farthest value, over the whole table; compared with the plain loop in tests."""
    df, schema = wl.workload(spark, sf_dir, "doc13")
    return det.iterative_flags(df, schema, schema.full)


@query(
    "budget_table",
    "SELECT l_suppkey, method, n, draws, 0.2::DOUBLE / draws AS eps1 FROM (SELECT l_suppkey, method, n, CASE WHEN method IN ('direct', 'uniform', 'walk') THEN 2 ELSE 2 * n + 2 END::INT AS draws "
    "FROM (SELECT l_suppkey, count(*)::INT AS n FROM lineitem GROUP BY l_suppkey), (VALUES ('direct'), ('uniform'), ('walk'), ('dfs'), ('bfs')) AS t(method))",
)
def _budget(spark, sf_dir):
    """Budgets of a draw by method, for releases that take as many samples as a supplier has lines."""
    n = F.col("n")
    each = F.explode(F.array(*[F.struct(F.lit(m).alias("method"), (F.lit(0) + mech.draws_charged(m, n)).cast("int").alias("draws"), (F.lit(1.0) * mech.allocate(m, EPS, n)).alias("eps1")) for m in mech.METHODS])).alias("b")
    sizes = table(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).cast("int").alias("n"))
    return sizes.select("l_suppkey", "n", each).select("l_suppkey", "b.method", "n", "b.draws", "b.eps1")


_ASKED = ("101001010", "100001010", "101010001", "111111111")


@query(
    "inc9_contexts",
    f"WITH enc AS ({wl.encoded_sql('o9')}), asked AS (SELECT * FROM (VALUES {', '.join(f'({chr(39)}{b}{chr(39)}, {int(b, 2)}::BIGINT)' for b in _ASKED)}) AS t(bits, ctx)) "
    "SELECT bits, count(cell) AS population FROM asked LEFT JOIN enc ON cell & ctx = cell GROUP BY bits",
)
def _worked_example(spark, sf_dir):
    """The worked example's contexts, asked of a table of orders with as many attributes and values; the ten people are in tests."""
    df, schema = wl.workload(spark, sf_dir, "o9")
    asked = spark.createDataFrame([(b, int(b, 2)) for b in _ASKED], "bits string, ctx long")
    found = pl.context_stats(pl.build_cells(df, schema), asked.select("ctx")).select("ctx", "n")
    return asked.join(found, "ctx", "left").select("bits", F.coalesce("n", F.lit(0)).cast("long").alias("population"))
