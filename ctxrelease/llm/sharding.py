"""Balanced label propagation of linked documents over shards.

Documents are linked when they share a hub (here: equal texts); a hub stands for all its pairs, so links are never
written out. Labels start from a hash of the row. In each round the counts of hubs per shard are joined back, and
whole hubs want to move to the shard that holds most of them, as far as the quota there has room; a hub whose best
shard is full turns to the best of its shards that has room, or to any that has. Rounds go on until hardly any row
moves (SETTLED of the linked ones), or to MOST_ROUNDS. Hubs larger than a shard are parted first, so that none
overfills one. A last step restores exact balance: every shard keeps its quota of documents, linked ones first, and the
others go to shards with room. Law `rows`: counts of shards differ by one at most.

Null texts have no hub. Empty texts share one. Rows may repeat; each is placed. An empty table gives no rows; extra
columns are not read. Hot hubs are counted in partial aggregates before any shuffle and meet their rows by broadcast,
and ranks are found within hashed groups.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ctxrelease.plans.runtime import bounded_broadcast, cut

from .common import join_hot_apart

SHARDS = 16
MOST_ROUNDS, SETTLED = 12, 0.001
#: Groups in which ranks are found, in a shard: hashes of hubs, times hashes of documents.
BUCKETS, SALTS = 64, 16


def _share(*parts: Column) -> Column:
    """A number from 0 to 1 from a hash."""
    return F.pmod(F.xxhash64(*parts), F.lit(1_000_003)) / F.lit(1_000_003.0)


def quotas(total: int, shards: int) -> list[int]:
    return [total // shards + (s < total % shards) for s in range(shards)]


def propagate(nodes: DataFrame, total: int, shards: int, rounds: int = MOST_ROUNDS, log: list | None = None) -> DataFrame:
    """Adds hub_size and shard to (row_id, hub): rows of a hub gather in one shard as far as quotas allow. log: rows moved by round."""
    room = max(1, total // shards)
    sizes = cut(nodes.where(F.col("hub").isNotNull()).groupBy("hub").agg(F.count(F.lit(1)).alias("hub_size")).where("hub_size > 1"))
    known = join_hot_apart(nodes, sizes, ["hub"], "hub_size", "left").withColumn("hub_size", F.coalesce("hub_size", F.lit(1)))
    parts = F.ceil(F.col("hub_size") / F.lit(room))
    known = known.withColumn("part", F.when(F.col("hub_size") > 1, F.pmod(F.xxhash64("row_id", F.lit("part")), parts)).otherwise(F.lit(-1)).cast("long"))
    known = cut(known.withColumn("shard", F.pmod(F.xxhash64("row_id", F.lit("start")), F.lit(shards)).cast("int")))
    state, alone = known.where("hub_size > 1"), known.where("hub_size = 1")
    for turn in range(rounds):
        held = cut(state.groupBy("hub", "part", "shard").agg(F.count(F.lit(1)).alias("n")))
        loads = {r[0]: r[1] for r in held.groupBy("shard").agg(F.sum("n")).collect()}  # one row per shard
        if not loads:
            break
        # unlinked rows make room for linked ones in the last step, so the quota binds what is linked
        free = [max(0, total // shards - loads.get(s, 0)) for s in range(shards)]
        with_room = [s for s in range(shards) if free[s]]
        is_open = F.element_at(F.array(*[F.lit(bool(x)) for x in free]), F.col("shard") + 1)
        tie = _share(F.col("hub"), F.col("part"), F.col("shard"))
        most = F.max(F.struct("n", tie.alias("tie"), "shard"))
        wanted = held.groupBy("hub", "part").agg(most.alias("best"), F.max(F.when(is_open, F.struct("n", tie.alias("tie"), "shard"))).alias("next"), F.sum("n").alias("members"))
        wanted = wanted.where("best.n < members")  # the others are together
        best_open = F.element_at(F.array(*[F.lit(bool(x)) for x in free]), F.col("best.shard") + 1)
        anywhere = F.element_at(F.array(*[F.lit(s) for s in with_room or [0]]), (F.pmod(F.xxhash64("hub", "part", F.lit(turn)), F.lit(max(1, len(with_room)))) + 1).cast("int"))
        goal = F.when(best_open, F.col("best.shard")).otherwise(F.coalesce(F.col("next.shard"), anywhere))
        there = F.when(best_open, F.col("best.n")).otherwise(F.coalesce(F.col("next.n"), F.lit(0)))
        moves = cut(wanted.select("hub", "part", "members", goal.alias("goal"), (F.col("members") - there).alias("coming")))
        coming = {r[0]: r[1] for r in moves.groupBy("goal").agg(F.sum("coming")).collect()}  # one row per shard
        if not coming or not with_room:
            break
        chance = F.element_at(F.array(*[F.lit(min(1.0, free[s] / max(1, coming.get(s, 0)))) for s in range(shards)]), F.col("goal") + 1)
        go = cut(moves.where(_share(F.col("hub"), F.col("part"), F.lit(turn)) < chance).select("hub", "part", "goal", "members", "coming"))
        moved = go.agg(F.coalesce(F.sum("coming"), F.lit(0))).first()[0]
        state = cut(join_hot_apart(state, go.drop("coming"), ["hub", "part"], "members", "left").withColumn("shard", F.coalesce("goal", "shard")).drop("goal", "members"))
        if log is not None:
            log.append(moved)
        if moved <= SETTLED * sum(loads.values()):
            break
    return state.unionByName(alone)


def balance(state: DataFrame, total: int, shards: int) -> DataFrame:
    """Final shard and slot: each shard keeps its quota, linked rows first; the surplus fills the others."""
    quota = quotas(total, shards)
    loads = {r[0]: r[1] for r in state.groupBy("shard").agg(F.count(F.lit(1))).collect()}  # one row per shard
    # the larger quotas go to the fullest shards
    order = sorted(range(shards), key=lambda s: (-loads.get(s, 0), s))
    quota = {s: q for s, q in zip(order, quota)}
    surplus_from, gaps, start, gap = {}, [], 0, 0
    for s in range(shards):
        surplus_from[s] = start
        start += max(0, loads.get(s, 0) - quota[s])
        if loads.get(s, 0) < quota[s]:
            size = quota[s] - loads.get(s, 0)
            gaps.append((gap, gap + size, s, loads.get(s, 0)))
            gap += size
    grouped = (
        state.withColumn("alone", (F.col("hub_size") == 1).cast("int"))
        .withColumn("bucket", F.when(F.col("hub_size") > 1, F.pmod(F.xxhash64("hub", "part"), F.lit(BUCKETS))).otherwise(F.pmod(F.xxhash64("row_id"), F.lit(BUCKETS))).cast("int"))
        .withColumn("salt", F.pmod(F.xxhash64("row_id", F.lit("salt")), F.lit(SALTS)).cast("int"))
    )
    keys = ["shard", "alone", "bucket", "salt"]
    counts = grouped.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("shard").orderBy("alone", "bucket", "salt").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")
    nth = F.row_number().over(Window.partitionBy(*keys).orderBy("hub", "part", "row_id")) - 1
    ranked = grouped.withColumn("nth", nth).join(bounded_broadcast(base, 2 * shards * BUCKETS * SALTS, 32), keys).withColumn("rank", F.col("base") + F.col("nth"))

    def of_shard(values: dict[int, int]) -> Column:
        return F.element_at(F.array(*[F.lit(int(values[s])).cast("long") for s in range(shards)]), F.col("shard") + 1)

    stays = F.col("rank") < of_shard(quota)
    extra = of_shard(surplus_from) + F.col("rank") - of_shard(quota)
    to_shard, to_slot = F.lit(None).cast("int"), F.lit(None).cast("long")
    for a, b, s, held in gaps:  # at most one per shard
        inside = (F.col("extra") >= a) & (F.col("extra") < b)
        to_shard, to_slot = F.when(inside, F.lit(s)).otherwise(to_shard), F.when(inside, F.col("extra") - a + held).otherwise(to_slot)
    moved = ranked.withColumn("extra", F.when(~stays, extra))
    return moved.withColumn("slot", F.when(stays, F.col("rank")).otherwise(to_slot).cast("long")).withColumn("shard", F.when(stays, F.col("shard")).otherwise(to_shard))


def shard_documents(docs: DataFrame, shards: int = SHARDS, rounds: int = MOST_ROUNDS) -> DataFrame:
    """Rows (doc_id, size, text_crc32, law, shard, slot, grown_shard); texts are read once."""
    raw = F.col("text").cast("binary")
    nodes = cut(
        docs.select(
            F.col("doc_id").alias("row_id"),
            (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"),
            F.crc32(F.coalesce(raw, F.lit(b""))).alias("text_crc32"),
            F.when(F.col("text").isNotNull(), F.unhex(F.md5(raw))).alias("hub"),
        )
    )
    total = nodes.count()
    return balance(propagate(nodes, total, shards, rounds), total, shards).select(
        F.col("row_id").alias("doc_id"), "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard")
    )


def cut_edges(placed: DataFrame, hub: str = "text_crc32") -> DataFrame:
    """Links whose ends lie in different shards, of all links: from counts, without writing pairs out."""
    by_shard = placed.groupBy(hub, "size", "shard").agg(F.count(F.lit(1)).alias("n"))
    by_hub = by_shard.groupBy(hub, "size").agg(F.sum("n").alias("n"), F.sum(F.col("n") * (F.col("n") - 1) / 2).alias("inside"))
    return by_hub.agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).alias("links"), F.sum(F.col("n") * (F.col("n") - 1) / 2 - F.col("inside")).alias("cut"))


def op4_sharding(spark, sf_dir: str) -> DataFrame:
    return shard_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
