"""Toxicity by a factorization machine over hashed terms.

A text's terms are its distinct lower-case words and the first bytes of longer words, each hashed to one of
BUCKETS buckets. Besides a weight, every term has a short vector; the products of the vectors of two terms that
occur together add to the score, so that pairs count beyond the sum of their parts. The score is a logistic
function of that sum.

It learns from a bounded sample (SAMPLE_ROWS rows by a hash of doc_id) of labelled rows whose crc32(doc_id) mod 5
isn't 0. Terms are chosen in two ways: by how far their share among toxic rows departs from chance, and by pairs
whose share departs from what the two terms say on their own. A group's name that is as common in clean texts, or
an insult that is harmless alone, comes in by its pairs; such terms start with larger vectors, so that the products
are learned and not left near zero.

Null and empty texts have no terms: their score is the intercept's. Without labels every score is 0. Rows may repeat;
each is scored. A label that is null isn't learned from; several labels of a document count as their largest.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import append_columns, give_back, remembered

BUCKETS = 1 << 24
PREFIXES = (4, 5, 7)
RANK = 4
TERMS = 4096
#: A term is kept if its squared deviation from chance is at least this many times the variance.
DEVIATION = 36.0
SAMPLE_ROWS = 6_000
MIN_ROWS = 3
#: Terms whose pairs are looked at, terms taken in for their pairs, and the spread of the first vectors.
POOL, PAIRED = 3_000, 1_024
SPREAD, PAIR_SPREAD = 0.01, 0.1
EPOCHS = 12
MEMO = 50_000

#: ASCII other than letters parts words; bytes of other characters belong to them.
_PARTS = bytes(b if b >= 128 or chr(b).isalpha() else 32 for b in range(256))


def bucket(term: bytes) -> int:
    return zlib.crc32(term) % BUCKETS


def word_buckets(word: bytes) -> tuple[int, ...]:
    return (bucket(word), *(bucket(b"%d:%b" % (n, word[:n])) for n in PREFIXES if len(word) > n))


class Terms:
    """Distinct buckets of a text; the buckets of a bounded number of words are remembered."""

    def __init__(self, place: dict[int, int] | None = None):
        self.place = place
        self.memo: dict[bytes, tuple[int, ...]] = {}
        self.without: set[bytes] = set()

    def of(self, text: str | None) -> set[int]:
        out: set[int] = set()
        if not text:
            return out
        place = self.place
        for w in set(text.lower().encode().translate(_PARTS).split()) - self.without:
            found = self.memo.get(w)
            if found is None:
                found = word_buckets(w)
                if place is not None:
                    found = tuple(place[b] for b in found if b in place)
                if len(self.memo) + len(self.without) > MEMO:
                    self.memo.clear()
                    self.without.clear()
                if found:
                    self.memo[w] = found
                else:
                    self.without.add(w)
                    continue
            out.update(found)
        return out


def _terms_of(machine: Machine | None) -> Terms:
    """This process's terms for a machine: what they remember serves the tasks that follow."""
    key = machine.buckets.tobytes() if machine else None  # a machine may have no terms
    return remembered(("toxicity", key), lambda: Terms({int(b): k for k, b in enumerate(machine.buckets)} if machine else None))


@dataclass
class Machine:
    buckets: np.ndarray
    intercept: float
    weight: np.ndarray
    factors: np.ndarray  # terms x RANK

    def raw(self, terms: np.ndarray) -> float:
        v = self.factors[terms]
        return float(self.intercept + self.weight[terms].sum() + 0.5 * ((v.sum(0) ** 2).sum() - (v * v).sum()))


def paired_terms(lists: list[np.ndarray], y: np.ndarray, n: np.ndarray, hit: np.ndarray) -> np.ndarray:
    """Places of terms in pairs whose share of toxic rows departs from the sum of the two terms' own log odds, farthest first.

    lists: places of each row's terms. Looks at the POOL terms that most toxic rows hold, leaving out those that half of
    all rows hold.
    """
    rows, positives = len(lists), y.sum()
    fair = np.flatnonzero((hit >= MIN_ROWS) & (2 * n <= rows))
    pool = np.sort(fair[np.argsort(-hit[fair], kind="stable")[:POOL]])
    if len(pool) < 2 or not 0 < positives < rows:
        return np.zeros(0, np.int64)
    place = np.full(len(n), -1)
    place[pool] = np.arange(len(pool))
    held = np.zeros((rows, len(pool)), bool)
    for i, terms in enumerate(lists):
        own = place[terms]
        held[i, own[own >= 0]] = True
    bad_rows = y > 0
    base = np.log((positives + 0.5) / (rows - positives + 0.5))
    odds = (np.log((hit[pool] + 0.5) / (n[pool] - hit[pool] + 0.5)) - base).astype(np.float32)
    best = np.zeros(len(pool), np.float32)
    step = 512
    starts = range(0, len(pool), step)
    for at in starts:
        left = held[:, at : at + step].astype(np.float32)
        for to in starts:
            right = held[:, to : to + step].astype(np.float32)
            both, bad = left.T @ right, left[bad_rows].T @ right[bad_rows]
            share = 1 / (1 + np.exp(-np.clip(odds[at : at + step, None] + odds[None, to : to + step] + np.float32(base), -20, 20)))
            expected = both * share
            far = np.where(both >= MIN_ROWS, (bad - expected) ** 2 / np.maximum(expected * (1 - share), 0.25), 0)
            # a word and its own first bytes are one word: a pair that never parts says nothing, nor does a term with itself
            far[(both == n[pool][at : at + step, None]) | (both == n[pool][None, to : to + step])] = 0
            best[at : at + step] = np.maximum(best[at : at + step], far.max(1))
    order = np.argsort(-best, kind="stable")[:PAIRED]
    return pool[order[best[order] >= DEVIATION]]


def fit(rows: list[np.ndarray], labels: list[int], epochs: int = EPOCHS, seed: int = 5) -> Machine | None:
    """Adaptive gradient descent on the logistic loss with a penalty; rows hold distinct buckets."""
    if not rows:
        return None
    y = np.array(labels, np.float64)
    positives = y.sum()
    base = float(np.log((positives + 0.5) / (len(y) - positives + 0.5)))
    flat = np.concatenate(rows).astype(np.int32)
    owner = np.repeat(np.arange(len(rows), dtype=np.int32), [len(r) for r in rows])
    seen = np.unique(flat)
    at = np.searchsorted(seen, flat).astype(np.int32)
    del flat
    n = np.bincount(at, minlength=len(seen)).astype(np.float64)
    hit = np.bincount(at[(y > 0)[owner]], minlength=len(seen)).astype(np.float64)
    share = positives / len(y)
    far = (hit - n * share) ** 2 / np.maximum(n * share * (1 - share), 1e-9)
    far[n < MIN_ROWS] = -1
    alone = np.argsort(-far, kind="stable")[: TERMS - PAIRED]
    alone = alone[far[alone] >= DEVIATION]
    bounds = np.searchsorted(owner, np.arange(len(rows) + 1))
    pairs = paired_terms([at[bounds[i] : bounds[i + 1]] for i in range(len(rows))], y, n, hit)
    kept = np.union1d(alone, pairs).astype(np.int64)
    where = np.full(len(seen), -1, np.int32)
    where[kept] = np.arange(len(kept))
    new = where[at]
    ok = new >= 0
    bounds = np.searchsorted(owner[ok], np.arange(len(rows) + 1))
    new = new[ok]
    lists = [new[bounds[i] : bounds[i + 1]] for i in range(len(rows))]
    rng = np.random.default_rng(seed)
    odds = np.log((hit[kept] + 0.5) / (n[kept] - hit[kept] + 0.5)) - base
    spread = np.where(np.isin(kept, pairs), PAIR_SPREAD, SPREAD)[:, None]
    m = Machine(seen[kept], base, 0.5 * odds, rng.normal(0, 1, (len(kept), RANK)) * spread)
    g_w, g_v, g_0 = np.full(len(kept), 1.0), np.full((len(kept), RANK), 1.0), 1.0
    penalty = 2e-4
    for epoch in range(epochs):
        for i in rng.permutation(len(lists)):
            t = lists[i]
            v = m.factors[t]
            total = v.sum(0)
            z = m.intercept + m.weight[t].sum() + 0.5 * ((total**2).sum() - (v * v).sum())
            d = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - y[i]
            if abs(d) < 1e-3:
                continue
            g_0 += d * d
            m.intercept -= 0.1 * d / np.sqrt(g_0)
            dw = d + penalty * m.weight[t]
            g_w[t] += dw * dw
            m.weight[t] -= 0.3 * dw / np.sqrt(g_w[t])
            dv = np.clip(d * (total - v), -1, 1) + penalty * v
            g_v[t] += dv * dv
            m.factors[t] -= 0.05 * dv / np.sqrt(g_v[t])
    return m


def score_texts(machine: Machine | None, terms: Terms, texts: list[str | None]) -> list[float]:
    if machine is None:
        return [0.0] * len(texts)
    out = []
    for t in texts:
        z = machine.raw(np.fromiter(sorted(terms.of(t)), np.int64))
        out.append(float(1 / (1 + np.exp(-np.clip(z, -30, 30)))))
    return out


def held_out() -> F.Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0


def training_rows(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS) -> tuple[list[np.ndarray], list[int]]:
    """Bucket lists and labels of the bounded sample."""
    fair = labels.select("doc_id", "toxic").where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out())
    picked = fair.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id", F.lit("sample")), "doc_id").limit(rows)
    sample = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id")  # at most `rows`
    fields = [T.StructField("terms", T.ArrayType(T.IntegerType()))]

    def maker():
        terms = _terms_of(None)
        return lambda texts: [[sorted(terms.of(t)) for t in texts]]

    found = append_columns(sample, "text", fields, maker, ["doc_id", "toxic"], "toxicity").toArrow().sort_by("doc_id")
    lists = found["terms"].combine_chunks()
    values, ends = lists.values.to_numpy(), lists.offsets.to_numpy()
    return [values[a:b] for a, b in zip(ends[:-1], ends[1:])], [int(x != 0) for x in found["toxic"].to_pylist()]


def train(docs: DataFrame, labels: DataFrame) -> Machine | None:
    machine = fit(*training_rows(docs, labels))
    give_back()
    return machine


def score(docs: DataFrame, machine: Machine | None, keep: list[str] | None = None, name: str = "score") -> DataFrame:
    """The columns in `keep` (all, if None) and the score."""

    def maker():
        terms = _terms_of(machine)
        return lambda texts: [score_texts(machine, terms, texts)]

    return append_columns(docs, "text", [T.StructField(name, T.DoubleType())], maker, keep, "toxicity")


def op7_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    machine = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score(docs, machine, ["doc_id"]).select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
