"""Exact top-k inner-product search by columnar branch-and-bound.

A first pass scores every query against SEEDS candidates; the k-th best of these is a threshold that no answer of the
query lies under, and it goes with the query to all blocks. Rows are then dealt into candidate blocks and query blocks
of bounded size. A candidate whose norm can't reach the least threshold of a query block isn't sent there. Each pair of
blocks is one small task that holds the candidates in vertical layout (one line of memory per dimension).

A task takes a query's dimensions in the order of their size, so that little of its mass is left early, and adds their
products dimension block by dimension block. After each block the mass that is left of the query and of a candidate
bounds what can still come (the product of the rests' norms); candidates whose bound lies under the threshold go, and
the columns that survive are compacted. Sums are exact integers, bounds carry a margin for rounding, and the kept rows
are the exact best k of each block pair, which a last window merges by query.

Vectors that are null or hold a null or non-finite component take no part, nor does a null vec_id. Shorter vectors count
as padded with zeros. Equal scores go to the smaller id. Rows that repeat a vec_id are candidates each, and as queries
one; extra columns are not read; an empty table gives no rows. The number of block pairs follows queries times
candidates, which is what comparing a growing query set with all rows means; memory in a task doesn't follow either.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ctxrelease.plans.runtime import bounded_broadcast, cut

K = 20
SCALE = 64
QUERY_EVERY = 20
#: Rows in a block, on average.
CANDIDATES, QUERIES = 8192, 8192
#: Candidates of the first pass: the rows with the smallest hashes of their ids.
SEEDS = 4096
#: Dimensions before the first test, and between tests.
FIRST_DIMS, DIM_BLOCK = 16, 8


def integer_vectors(embeddings: DataFrame, scale: int = SCALE) -> DataFrame:
    """Rows (vec_id, v array<long>) of the usable vectors."""
    wide = F.transform("embedding", lambda x: F.floor(F.lit(float(scale)) * x.cast("double")))
    bad = F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return embeddings.select("vec_id", "embedding").where(F.col("embedding").isNotNull() & F.col("vec_id").isNotNull()).where(~bad).select("vec_id", wide.alias("v"))


def best_of_block(q_ids: np.ndarray, q: np.ndarray, tau: np.ndarray, c_ids: np.ndarray, vertical: np.ndarray, k: int, stats: dict | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query ids, candidate ids, scores) of each query's best k in the block, of those that reach its threshold tau.

    c_ids ascend; vertical: dimensions x candidates. stats counts products formed and those of plain comparison.
    """
    dims, n = vertical.shape
    most = float(np.abs(q).max(initial=0)) * float(np.abs(vertical).max(initial=0)) * max(dims, 1)
    exact = np.float32 if most < 2**24 else np.float64 if most < 2**52 else np.int64
    near = np.float32 if exact is np.float32 else np.float64  # bounds; their margins cover its rounding
    margin = 1e-5 if near is np.float32 else 1e-9
    q, vertical = q.astype(exact), np.ascontiguousarray(vertical.astype(exact))
    squares = vertical.astype(near) ** 2
    mass = squares.sum(0)
    spare = near(margin * float(mass.max(initial=0)))
    edges = [0, *range(min(dims, FIRST_DIMS), dims, DIM_BLOCK), dims]
    out_q, out_c, out_s = [], [], []
    formed = 0
    for i in range(len(q)):
        order = np.argsort(-np.abs(q[i]), kind="stable")
        own = q[i][order]
        limit_seen = np.isfinite(tau[i])
        left = np.concatenate([np.cumsum((own.astype(np.float64) ** 2)[::-1])[::-1], [0.0]])
        first, last = np.searchsorted(c_ids, q_ids[i], "left"), np.searchsorted(c_ids, q_ids[i], "right")
        live = np.concatenate([np.arange(first), np.arange(last, n)]) if first < last else None  # None: all
        rest = mass if live is None else mass[live]
        score = np.zeros(n if live is None else len(live), exact)
        for a, e in zip(edges[:-1], edges[1:]):
            some = order[a:e]
            block, square = vertical[some], squares[some]
            if live is not None:
                block, square = block[:, live], square[:, live]
            score = score + own[a:e] @ block
            formed += (e - a) * len(score)
            if e == dims or not limit_seen:
                continue
            rest = rest - square.sum(0)
            can = score + np.sqrt((np.maximum(rest, 0) + spare) * near(left[e] * (1 + margin)))
            stay = np.flatnonzero(can >= tau[i] - margin * (1 + abs(tau[i])))
            if len(stay) < len(score):
                live, score, rest = (stay if live is None else live[stay]), score[stay], rest[stay]
            if not len(score):
                break
        if live is None:
            live = np.arange(n)
        if len(live) > k:
            limit = np.partition(score, len(live) - k)[len(live) - k]
            above, equal = np.flatnonzero(score > limit), np.flatnonzero(score == limit)
            pick = np.concatenate([above, equal[: k - len(above)]])
            live, score = live[pick], score[pick]
        out_q.append(np.full(len(live), q_ids[i]))
        out_c.append(c_ids[live])
        out_s.append(score)
    if stats is not None:
        stats["formed"] = stats.get("formed", 0) + formed
        stats["plain"] = stats.get("plain", 0) + len(q) * n * dims
    none = np.zeros(0, np.int64)
    return tuple(np.concatenate([none, *x]).astype(np.int64) for x in (out_q, out_c, out_s))  # type: ignore[return-value]


def thresholds(queries: DataFrame, seeds: list[tuple[int, list[int]]], k: int) -> DataFrame:
    """Adds tau to (vec_id, v): the k-th best score among the seeds but the query itself, or minus infinity if they are fewer."""
    ids = np.array([r[0] for r in seeds], np.int64)
    dims = max((len(r[1]) for r in seeds), default=0)
    table = _matrix(pd.Series([r[1] for r in seeds], dtype=object), dims)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for at in range(0, len(batch), 256):
                part = batch.iloc[at : at + 256].copy()
                own = part["vec_id"].to_numpy()
                wide = max(dims, int(part["v"].map(len).max()))
                q, c = _matrix(part["v"], wide), np.pad(table, ((0, 0), (0, wide - dims)))
                small = float(np.abs(q).max(initial=0)) * float(np.abs(c).max(initial=0)) * max(wide, 1) < 2**52
                score = (q.astype(np.float64) @ c.T.astype(np.float64)) if small else (q @ c.T).astype(np.float64)
                score[own[:, None] == ids[None, :]] = -np.inf
                part["tau"] = np.partition(score, len(ids) - k, axis=1)[:, len(ids) - k] if len(ids) >= k else -np.inf
                yield part

    return queries.select("vec_id", "v").mapInPandas(run, "vec_id long, v array<long>, tau double")


def _matrix(lists: pd.Series, dims: int) -> np.ndarray:
    out = np.zeros((len(lists), dims), np.int64)
    for i, x in enumerate(lists):
        out[i, : len(x)] = x
    return out


def search(vectors: DataFrame, is_query, k: int = K, candidates: int = CANDIDATES, queries: int = QUERIES, seeds: int = SEEDS) -> DataFrame:
    """Rows (query_id, rank, vec_id, score) from (vec_id, v). `is_query`: a condition on vec_id."""
    total = vectors.select("vec_id").agg(F.count(F.lit(1)), F.count_if(is_query)).first()
    n_c, n_q = max(1, -(-total[0] // candidates)), max(1, -(-total[1] // queries))
    few = [(r[0], r[1]) for r in vectors.orderBy(F.xxhash64("vec_id", F.lit("seed")), "vec_id").limit(seeds).collect()]  # at most `seeds`

    def block(own: str, many: int):
        return F.pmod(F.xxhash64("vec_id", F.lit(own)), F.lit(many)).cast("int").alias(own)

    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")))
    asked = cut(thresholds(vectors.where(is_query).dropDuplicates(["vec_id"]), few, k).select("*", block("q_block", n_q)))
    # the least norm with which a candidate may matter to some query of a block; thresholds under 0 let all pass
    least = asked.groupBy("q_block").agg(F.min(F.when((F.col("tau") <= 0) | (norm == 0), F.lit(0.0)).otherwise(F.col("tau") / norm * (1 - 1e-9))).alias("least"))
    c = vectors.select("vec_id", "v", block("c_block", n_c), norm.alias("norm"))
    c = c.join(bounded_broadcast(least, n_q, 16), F.col("norm") >= F.col("least")).select("vec_id", "v", "c_block", F.col("q_block").alias("q_block"))
    q = asked.withColumn("c_block", F.explode(F.sequence(F.lit(0), F.lit(n_c - 1))))

    def run(key: tuple, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []}).astype("int64")
        right = right.sort_values("vec_id", kind="stable")
        dims = max(left["v"].map(len).max(), right["v"].map(len).max())
        ids, found, score = best_of_block(left["vec_id"].to_numpy(), _matrix(left["v"], dims), left["tau"].to_numpy(), right["vec_id"].to_numpy(), _matrix(right["v"], dims).T, k)
        return pd.DataFrame({"query_id": ids, "vec_id": found, "score": score})

    grouped = q.groupBy("c_block", "q_block").cogroup(c.groupBy("c_block", "q_block"))
    best = grouped.applyInPandas(run, "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op3_exact_topk(spark, sf_dir: str) -> DataFrame:
    vectors = integer_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
    return search(vectors, F.col("vec_id") % QUERY_EVERY == 0)


OP3_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)::BIGINT) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2]))::BIGINT AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 20 = 0
)
SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s
) WHERE rank <= 20
"""
