"""Best-fit packing of token sequences by a configuration linear program.

Only the histogram of piece lengths (at most `capacity` numbers) reaches the driver. There the covering program
over configurations (multisets of lengths that fit one sequence) is solved by multiplicative weights: a knapsack
dynamic program prices configurations by the dual values of their lengths, steps along the best ones shrink the
values of what they cover, and the steps average to a fractional cover. It is rounded down; what that leaves is
placed by best fit, first into the room that the chosen configurations leave. Where best fit alone needs fewer
sequences, as it may where nearly every length occurs and all fill up, its packing is returned. All of this
works on counts, so its cost doesn't follow the number of documents. Pieces then find their places by a join of
their rank among pieces of equal length with a table of slots of bounded size.

Null and empty texts are one token (the end mark). Rows may repeat: each is packed. Ranks within a length are
found in salted groups, so that no length gathers in one task.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ctxrelease.plans.runtime import bounded_broadcast, cut

from .bpe import TEXT_SLICE, default_path, encoder
from .common import give_back, text_slices

CAPACITY = 2048
END_ID = 0
#: Pricing rounds, and configurations taken from each; their product bounds the table of slots.
ROUNDS = 48
COLUMNS = 64
RATE = 0.7
#: Share of the scarcest length's demand that one step covers, and how far below the best price a configuration may be.
STEP, NEAR = 0.25, 0.02
#: Salts at least, and pieces of one length and salt on average at most: ranking is spread as the input grows.
SALTS, SALT_ROWS = 64, 100_000

Template = tuple[tuple[int, int], ...]


def price(lengths: np.ndarray, value: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Unbounded knapsack: the best value for each room, and the length placed last (0: none)."""
    best = np.zeros(capacity + 1)
    choice = np.zeros(capacity + 1, np.int64)
    for room in range(1, capacity + 1):
        k = int(np.searchsorted(lengths, room, "right"))
        if k == 0:
            continue
        got = best[room - lengths[:k]] + value[:k]
        at = int(got.argmax())
        if got[at] > best[room - 1]:
            best[room], choice[room] = got[at], lengths[at]
        else:
            best[room] = best[room - 1]
    return best, choice


def _trace(choice: np.ndarray, room: int) -> list[int]:
    out = []
    while room > 0:
        if choice[room]:
            out.append(int(choice[room]))
            room -= int(choice[room])
        else:
            room -= 1
    return out


def _counts(items: list[int]) -> dict[int, int]:
    out: dict[int, int] = {}
    for x in items:
        out[x] = out.get(x, 0) + 1
    return out


def solve(histogram: dict[int, int], capacity: int, rounds: int = ROUNDS, columns: int = COLUMNS, rate: float = RATE, report: dict | None = None) -> list[tuple[Template, int]]:
    """Configurations with the number of sequences that use each; together they hold the histogram exactly.

    `report` gets the bounds, the sequences of the program and of best fit alone, and the share placed by the program.
    """
    left = {k: n for k, n in histogram.items() if n > 0}
    if any(not 0 < k <= capacity for k in left):
        raise ValueError("lengths must be from 1 to the capacity")
    chosen: list[tuple[Template, int]] = []
    if left.get(capacity):
        chosen.append((((capacity, 1),), left.pop(capacity)))
    groups: list[tuple[Template, int]] = []
    # round the fractional cover down, then run what it leaves of each configuration once, where the pieces allow it
    cover, dual = fractional(left, capacity, rounds, columns, rate)
    rest = dict(left)
    for whole in (True, False):
        for config, runs in sorted(cover.items(), key=lambda x: -(x[1] if whole else x[1] % 1)):
            if not whole and runs % 1 < 0.5:
                break
            n = min([int(runs) if whole else 1, *(rest[x] // m for x, m in config)])
            if n > 0:
                groups.append((config, n))
                for x, m in config:
                    rest[x] -= m * n
    rounded, plain = best_fit(rest, groups, capacity), best_fit(left, [], capacity)
    full = sum(n for _, n in chosen)
    ours, alone = (full + sum(n for _, n in x) for x in (rounded, plain))
    if report is not None:
        tokens = sum(x * n for x, n in left.items())
        placed = tokens - sum(x * n for x, n in rest.items())
        report |= {"dual_bound": full + dual, "lower_bound": lower_bound(histogram, capacity), "program": ours, "best_fit": alone, "share_of_program": placed / tokens if tokens else 0.0}
    return chosen + (rounded if ours <= alone else plain)


def fractional(demand: dict[int, int], capacity: int, rounds: int, columns: int, rate: float) -> tuple[dict[Template, float], float]:
    """Configurations with fractions of sequences that cover the demand on average, and a bound from below: multiplicative weights.

    The bound is the best of the rounds' dual values: the demand at a round's prices over the price of its dearest configuration.

    A length's price is its dual value: it starts in proportion to the length and shrinks with the share of the demand
    covered so far. A round prices all configurations at once; those near the best price are run in small steps while
    their price at the current weights stays there. The steps are averaged into one cover.
    """
    lengths = np.array(sorted(k for k, n in demand.items() if n > 0), np.int64)
    if not len(lengths):
        return {}, 0.0
    need = np.array([demand[int(x)] for x in lengths], np.float64)
    place = {int(x): k for k, x in enumerate(lengths)}
    covered = np.zeros(len(lengths))
    cover: dict[Template, float] = {}
    dual = 0.0
    for _ in range(rounds):
        value = lengths / capacity * np.exp(-rate * (covered - covered.min()))
        best, choice = price(lengths, value, capacity)
        worth = value + best[capacity - lengths]
        floor = float(worth.max()) * (1 - NEAR)
        dual = max(dual, float(need @ value) / float(best[capacity]))
        ran = 0
        for k in np.argsort(-worth, kind="stable"):
            if worth[k] < floor or ran == columns:
                break
            first = int(lengths[k])
            # no more of a length than there is of it
            config = {x: min(m, demand[x]) for x, m in _counts([first, *_trace(choice, capacity - first)]).items()}
            at = np.array([place[x] for x in config])
            each = np.array(list(config.values()), np.float64)
            step = STEP * float((need[at] / each).min())
            key = tuple(sorted(config.items(), reverse=True))
            while ran < columns and float(each @ value[at]) >= floor:
                cover[key] = cover.get(key, 0.0) + step
                covered[at] += step * each / need[at]
                value[at] *= np.exp(-rate * step * each / need[at])
                ran += 1
        if not ran:  # what is worth most is scarce: run it as far as there is of it
            k = int(worth.argmax())
            key = ((int(lengths[k]), 1),)
            cover[key] = cover.get(key, 0.0) + STEP * need[k]
            covered[k] += STEP
    tokens = lengths * need
    mean = float(tokens @ covered / tokens.sum())
    return {c: y / mean for c, y in cover.items()}, dual


def best_fit(left: dict[int, int], groups: list[tuple[Template, int]], capacity: int) -> list[tuple[Template, int]]:
    """Places counted lengths, longest first, into the tightest room of counted groups of sequences."""
    rooms: dict[int, list[tuple[Template, int]]] = {}
    for template, n in groups:
        rooms.setdefault(capacity - sum(x * m for x, m in template), []).append((template, n))
    rooms.setdefault(capacity, [])
    for x in sorted(left, reverse=True):
        n = left[x]
        while n > 0:
            room = min((r for r, found in rooms.items() if r >= x and found), default=capacity)
            each = room // x
            if rooms.get(room):
                template, many = rooms[room].pop()
                if not rooms[room] and room != capacity:
                    del rooms[room]
            else:
                template, many = (), -(-n // each)
            full = min(many, n // each)
            rest = many - full
            if full:
                rooms.setdefault(room - each * x, []).append(((*template, (x, each)), full))
                n -= full * each
            if rest and n:
                rooms.setdefault(room - n * x, []).append(((*template, (x, n)), 1))
                n, rest = 0, rest - 1
            if rest and template:
                rooms.setdefault(room, []).append((template, rest))
    return [(t, n) for found in rooms.values() for t, n in found if t]


def lower_bound(histogram: dict[int, int], capacity: int) -> int:
    """No packing has fewer sequences: total tokens, or pieces over half a sequence."""
    return max(-(-sum(k * n for k, n in histogram.items()) // capacity), sum(n for k, n in histogram.items() if 2 * k > capacity))


def slot_table(solution: list[tuple[Template, int]]) -> list[tuple[int, int, int, int, int, int]]:
    """Rows (length, first rank, rank after the last, first sequence, pieces per sequence, offset)."""
    rank: dict[int, int] = {}
    rows, sequence = [], 0
    for template, n in solution:
        offset = 0
        for length, each in template:
            start = rank.get(length, 0)
            rank[length] = start + each * n
            rows.append((length, start, start + each * n, sequence, each, offset))
            offset += length * each
        sequence += n
    return rows


def cut_pieces(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, text_col: str = "text", key: str = "doc_id") -> DataFrame:
    """Rows (key, piece, start, length, ids_crc32) of every whole text's ids, end mark included."""
    path = path or default_path()
    end = np.array([END_ID], "<u4").tobytes()
    key_type = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = encoder(path)
        step = 4 * capacity
        for batch in batches:
            place: list[int] = []
            rows: list[list[int]] = [[], [], [], []]
            for first, _, texts in text_slices(batch.column(1), TEXT_SLICE):
                for k, ids in enumerate(coder.encode([x or "" for x in texts]), first):
                    ids += end
                    for piece, at in enumerate(range(0, len(ids), step)):
                        part = ids[at : at + step]
                        place.append(k)
                        for column, x in zip(rows, (piece, at // 4, len(part) // 4, zlib.crc32(part))):
                            column.append(x)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(place, pa.int64())), pa.array(rows[0], pa.int32()), *(pa.array(r, pa.int64()) for r in rows[1:])], names=[key, "piece", "start", "length", "ids_crc32"])
        give_back()

    return docs.select(key, text_col).mapInArrow(run, f"`{key}` {key_type}, piece int, start long, length long, ids_crc32 long")


def pack(pieces: DataFrame, capacity: int = CAPACITY, key: str = "doc_id") -> DataFrame:
    """Adds sequence_id and offset to rows (key, piece, start, length, ids_crc32). `pieces` must be cheap to read again."""
    spark = pieces.sparkSession
    salts = max(SALTS, -(-pieces.count() // SALT_ROWS))
    salted = pieces.withColumn("salt", F.pmod(F.xxhash64(key, "piece"), F.lit(salts)).cast("int"))
    counts = salted.groupBy("length", "salt").agg(F.count(F.lit(1)).alias("n"))
    histogram = {r[0]: r[1] for r in counts.groupBy("length").agg(F.sum("n")).collect()}  # at most `capacity` rows
    slots = slot_table(solve(histogram, capacity))
    slots_df = spark.createDataFrame(slots or [(0, 0, 0, 0, 1, 0)], "length long, rank_from long, rank_to long, sequence_from long, each long, offset_from long")
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")
    in_salt = Window.partitionBy("length", "salt").orderBy(F.col(key), F.col("piece"))
    ranked = (
        salted.withColumn("nth", F.row_number().over(in_salt).cast("long") - 1)
        .join(bounded_broadcast(base, salts * len(histogram), 24), ["length", "salt"])
        .withColumn("rank", F.col("base") + F.col("nth"))
    )
    p, s = ranked.alias("p"), bounded_broadcast(slots_df, len(slots), 48).alias("s")
    at = F.col("p.rank") - F.col("s.rank_from")
    return p.join(s, (F.col("p.length") == F.col("s.length")) & (F.col("p.rank") >= F.col("s.rank_from")) & (F.col("p.rank") < F.col("s.rank_to"))).select(
        F.col(f"p.{key}"), "p.piece", "p.start", "p.length", "p.ids_crc32",
        (F.col("s.sequence_from") + F.floor(at / F.col("s.each"))).cast("long").alias("sequence_id"),
        (F.col("s.offset_from") + at % F.col("s.each") * F.col("p.length")).cast("long").alias("offset"),
    )


def pack_documents(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """Tokenizes once (the pieces' numbers are checkpointed), then packs."""
    return pack(cut(cut_pieces(docs, path, capacity)), capacity)


def op2_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
