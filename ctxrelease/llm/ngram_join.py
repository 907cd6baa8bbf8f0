"""Exact n-gram Jaccard join as a blocked sparse matrix product.

Documents are rows and five-word shingles are columns of an incidence matrix. Its product with its transpose holds
the overlaps; only the part that can reach the threshold is formed, and cells go as soon as sizes rule them out:

* equal sets are one row (class), found by a 128-bit signature of the set;
* columns have one global order, rare ones first by a count sketch over the whole corpus (any order is right, this
  one keeps frequent columns out); by the size bound a row needs only its first |A| - ceil(0.8 |A|) + 1 columns;
* a column held by one class only is dropped;
* first each row is multiplied with the best leader of its columns (the smallest id, then the row with the commonest
  columns), which joins copies in clusters without writing their pairs out; then only columns that still span several
  components are multiplied, and only rows outside a column's largest component against the rest. The overlap that
  the two sizes ask for bounds where in both rows a shared column must lie, so most cells of the product never form;
* overlap counts add up over these columns; the count so far and what the rows hold behind their last shared column
  bound the whole overlap, and pairs below what the sizes ask for are discarded;
* all columns are dealt to blocks by hash, about two columns a block, and every row has its sizes by block. The sum of
  the smaller sizes bounds the overlap without reading a set: most pairs that share only a passage go here;
* the overlaps of the pairs that are left are counted on their full sets.

Links are 100 * intersection >= 80 * union. Null texts and texts without words have an empty set and link with
nothing. Rows with one doc_id are one document; a null doc_id links with nothing; extra columns are not read.

Words and shingles are known by hashes: each byte of a word adds a random number of its place and value, and sums are
mixed. Candidates come from one family of hashes, overlaps of pairs from a second, independent one, and classes need
both. A wrong link needs a collision in one pair's sets: at most |A| |B| / 2^64, 6e-8 for two million words each.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ctxrelease.plans.runtime import bounded_broadcast, cut, release, stored

from .common import claim, give_back, join_hot_apart, slices, text_slices

WORDS = 5
#: The threshold as a fraction.
NUMERATOR, DENOMINATOR = 4, 5
SKETCH_BITS = 16
#: Characters hashed at a time, and in one batch of rows.
HASHED, BATCHED = 1 << 18, 1 << 21

_MIX_A, _MIX_B = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_LOW = np.uint64((1 << (64 - SKETCH_BITS)) - 1)
_SHIFT = np.uint64(64 - SKETCH_BITS)
_rng = np.random.default_rng(20240229)
_PLACES = 64
#: For each of two families: a random number for each byte value at each place of a word, and a factor for each word of a shingle.
_BYTE = _rng.integers(0, 1 << 63, (2, _PLACES * 256), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_WORD = _rng.integers(0, 1 << 63, (2, WORDS), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_FAR = np.uint64(0x9E3779B97F4A7C15)
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True  # fixed values: the white space between words


def mix(h: np.ndarray) -> np.ndarray:
    """A permutation of 64-bit numbers that spreads all bits."""
    h = (h ^ (h >> np.uint64(30))) * _MIX_A
    h = (h ^ (h >> np.uint64(27))) * _MIX_B
    return h ^ (h >> np.uint64(31))


def word_hashes(raw: bytes, family: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of lower-cased text, and where they start."""
    b = np.frombuffer(raw, np.uint8)
    space = _SPACE[b]
    gap = np.concatenate([[True], space, [True]])
    edge = np.flatnonzero(gap[1:] != gap[:-1])
    start, size = edge[0::2], edge[1::2] - edge[0::2]
    if not len(start):
        return np.zeros(0, np.uint64), start
    inside = b[~space]
    first = np.cumsum(size) - size
    place = (np.arange(len(inside)) - np.repeat(first, size)).astype(np.int32)
    value = _BYTE[family][((place & (_PLACES - 1)) << 8) | inside]
    far = np.flatnonzero(place >= _PLACES)
    if len(far):
        value[far] = mix(value[far] + (place[far] >> 6).astype(np.uint64) * _FAR)
    return mix(np.add.reduceat(value, first) + size.astype(np.uint64)), start


def shingles(texts: list[str], family: int = 0) -> list[np.ndarray]:
    """For each text the hashes of its shingles, repeats included; fewer words than a shingle make one."""
    raws = [t.encode().lower() for t in texts]  # on bytes: A to Z only
    h, start = word_hashes(b" ".join(raws), family)
    factor = _WORD[family]
    ends = np.cumsum([len(r) + 1 for r in raws])
    last = np.searchsorted(start, ends)
    first = np.concatenate([[0], last[:-1]])
    n = len(h) - WORDS + 1
    if n > 0:
        full = h[:n] * factor[0]
        for k in range(1, WORDS):
            full += h[k : n + k] * factor[k]
        full = mix(full)
    out = []
    for a, b in zip(first.tolist(), last.tolist()):
        if b - a >= WORDS:
            out.append(full[a : b - WORDS + 1])
        elif b > a:
            out.append(mix((h[a:b] * factor[: b - a]).sum(dtype=np.uint64, keepdims=True) + np.uint64(b - a)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def column_order(docs: DataFrame) -> np.ndarray:
    """The place of each hash bucket (2**SKETCH_BITS of them) by its count over all texts, rare ones first."""
    size = 1 << SKETCH_BITS

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("join")
        total = np.zeros(size, np.int64)
        for batch in batches:
            for _, _, texts in text_slices(batch.column(0), HASHED):
                found = shingles([x or "" for x in texts])
                total += np.bincount((np.concatenate(found) >> _SHIFT).astype(np.int64), minlength=size)
        at = np.flatnonzero(total)
        give_back()
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], names=["bucket", "n"])

    counts = docs.select("text").mapInArrow(count, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n"))
    found = counts.toPandas()  # at most 2**SKETCH_BITS rows
    total = np.zeros(size, np.int64)
    total[found["bucket"].to_numpy()] = found["n"].to_numpy()
    place = np.empty(size, np.uint32)
    place[np.argsort(total, kind="stable")] = np.arange(size, dtype=np.uint32)
    return place


def distinct(h: np.ndarray) -> np.ndarray:
    h = np.sort(h)
    return h[np.concatenate([[True], h[1:] != h[:-1]])] if len(h) else h


def ordered_set(h: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Distinct columns of a text in the global order (a permutation of the hashes)."""
    return distinct((place[(h >> _SHIFT).astype(np.int64)].astype(np.uint64) << _SHIFT) | (h & _LOW))


def block_sizes(h: np.ndarray) -> bytes:
    """How many of the distinct columns fall in each of 2^k blocks, one byte each; none where a byte is too small."""
    bits = max(3, (max(1, len(h) // 2) - 1).bit_length())
    sizes = np.bincount((mix(h) >> np.uint64(64 - bits)).astype(np.int64), minlength=1 << bits)
    return sizes.astype(np.uint8).tobytes() if sizes.max() < 256 else b""


def block_bound(a: bytes, b: bytes) -> int:
    """At least the overlap of two rows, from their sizes by block."""
    if not a or not b:
        return 1 << 62
    x, y = np.frombuffer(a, np.uint8).astype(np.int64), np.frombuffer(b, np.uint8).astype(np.int64)
    few = min(len(x), len(y))
    return int(np.minimum(x.reshape(few, -1).sum(1), y.reshape(few, -1).sum(1)).sum())


def needed_overlap(x, y):
    """The least overlap of linked sets of these sizes, for columns."""
    return F.ceil((x + y) * NUMERATOR / (NUMERATOR + DENOMINATOR))


def prefix_length(n: int) -> int:
    return n - -(-NUMERATOR * n // DENOMINATOR) + 1 if n else 0


def _lists(parts: list[np.ndarray]) -> pa.ListArray:
    offsets = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate([np.zeros(0, np.uint64), *parts]).view(np.int64)))


def _sum(h: np.ndarray) -> int:
    return int(h.sum(dtype=np.uint64).astype(np.int64))


def rows_of(docs: DataFrame, place: np.ndarray) -> DataFrame:
    """(doc_id, n, s1, s2, blocks, columns): set size, signature, sizes by block, and the columns that the size bound asks for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("join")
        for batch in batches:
            for i, j, texts in text_slices(batch.column(1), BATCHED):
                texts = [x or "" for x in texts]
                n, s1, s2, blocks, parts = [], [], [], [], []
                for a, b in slices(texts, HASHED):
                    part = texts[a:b]
                    for h, other in zip(shingles(part), shingles(part, 1)):
                        key = ordered_set(h, place)
                        n.append(len(key))
                        s1.append(_sum(mix(key ^ _MIX_A)))
                        s2.append(_sum(mix(distinct(other) + _MIX_B)))
                        blocks.append(block_sizes(key))
                        parts.append(key[: prefix_length(len(key))].copy())
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(i, j - i).cast(pa.int64()), pa.array(n, pa.int32()), pa.array(s1, pa.int64()), pa.array(s2, pa.int64()), pa.array(blocks, pa.binary()), _lists(parts)],
                    names=["doc_id", "n", "s1", "s2", "blocks", "columns"],
                )
        give_back()

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n int, s1 long, s2 long, blocks binary, columns array<long>")


def full_sets(docs: DataFrame, ids: DataFrame, many: int) -> DataFrame:
    """(rep, cols): whole sets of the documents in `ids` (many rows: broadcast if that is proven small, else shuffled)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("join")
        for batch in batches:
            for i, j, texts in text_slices(batch.column(1), BATCHED):
                texts = [x or "" for x in texts]
                parts = [distinct(h) for a, b in slices(texts, HASHED) for h in shingles(texts[a:b], 1)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i).cast(pa.int64()), _lists(parts)], names=["rep", "cols"])
        give_back()

    wanted = bounded_broadcast(ids, many, 16)
    return docs.select("doc_id", "text").join(wanted.withColumnRenamed("rep", "doc_id"), "doc_id").mapInArrow(run, "rep long, cols array<long>")


def within_blocks(pairs: DataFrame, sizes: DataFrame) -> DataFrame:
    """The pairs (a, b) whose sizes by block allow the overlap that their sizes ask for. sizes: (rep, n, blocks)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            needed, left, right = (batch.column(k).to_pylist() for k in (2, 3, 4))
            yield batch.select([0, 1]).filter(pa.array([block_bound(x, y) >= k for k, x, y in zip(needed, left, right)], pa.bool_()))

    left, right = (sizes.select(F.col("rep").alias(c), F.col("n").alias(f"n_{c}"), F.col("blocks").alias(f"blocks_{c}")) for c in ("a", "b"))
    both = pairs.select("a", "b").join(left, "a").join(right, "b")
    return both.select("a", "b", needed_overlap(F.col("n_a"), F.col("n_b")).alias("needed"), "blocks_a", "blocks_b").mapInArrow(run, "a long, b long")


def links_of(pairs: DataFrame, docs: DataFrame, sizes: DataFrame) -> DataFrame:
    """The pairs (a, b) whose full sets reach the threshold."""
    left = cut(within_blocks(pairs, sizes))
    ids = cut(left.select(F.col("a").alias("rep")).union(left.select("b")).distinct())
    sets = cut(full_sets(docs, ids, ids.count()))
    a, b = sets.select(F.col("rep").alias("a"), F.col("cols").alias("cols_a")), sets.select(F.col("rep").alias("b"), F.col("cols").alias("cols_b"))
    both = left.join(a, "a").join(b, "b")
    common = F.size(F.array_intersect("cols_a", "cols_b"))
    union = F.size("cols_a") + F.size("cols_b") - common
    found = cut(both.where(common * DENOMINATOR >= union * NUMERATOR).select("a", "b").distinct())
    del both, left, a, b, sets, ids
    release(docs.sparkSession)
    return found


def components(edges: DataFrame) -> DataFrame:
    """(node, comp): the smallest node that each node of an undirected graph reaches. Edges are contracted until none is left."""
    edges = cut(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a <> b").distinct())
    state = cut(edges.select(F.col("a").alias("node")).union(edges.select("b")).distinct().withColumn("comp", F.col("node")))
    while not edges.isEmpty():
        both = edges.union(edges.select("b", "a"))
        low = cut(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("low")))
        hop = low.select(F.col("a").alias("at"), F.col("low").alias("next"))
        # two hops at once: each node's goal is itself a node with a goal
        jump = cut(hop.join(hop.select(F.col("at").alias("next"), F.col("next").alias("far")), "next").select("at", "far"))
        state = cut(state.join(jump, state["comp"] == jump["at"], "left").select("node", F.coalesce("far", "comp").alias("comp")))
        to_a, to_b = jump.select(F.col("at").alias("a"), F.col("far").alias("x")), jump.select(F.col("at").alias("b"), F.col("far").alias("y"))
        edges = cut(edges.join(to_a, "a").join(to_b, "b").where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct())
    return state


def _near_sizes(x, y):
    return (x * DENOMINATOR >= y * NUMERATOR) & (y * DENOMINATOR >= x * NUMERATOR)


def best_leaders(led: DataFrame) -> DataFrame:
    """(a, b): each row (a) with the leader (b) of near size that most of its columns name. led: (column, rep, n, leader)."""
    counts = led.where("rep <> leader").groupBy("rep", "n", "leader").agg(F.count(F.lit(1)).alias("c"))
    sizes = led.where("rep = leader").groupBy(F.col("rep").alias("leader")).agg(F.min("n").alias("leader_n"))
    near = counts.join(sizes, "leader").where(_near_sizes(F.col("n"), F.col("leader_n")))
    return near.groupBy(F.col("rep").alias("a")).agg(F.max_by("leader", F.struct("c", -F.col("leader"))).alias("b"))


def spanning(rows: DataFrame, comps: DataFrame) -> DataFrame:
    """(column, rep, n, comp, largest): rows of the columns that span several components, with the largest of each."""
    placed = rows.select("column", "rep", "n", "pos").join(comps.withColumnRenamed("node", "rep"), "rep", "left").withColumn("comp", F.coalesce("comp", "rep"))
    spans = placed.groupBy("column", "comp").agg(F.count(F.lit(1)).alias("k")).groupBy("column").agg(F.count(F.lit(1)).alias("comps"), F.max_by("comp", F.struct("k", "comp")).alias("largest")).where("comps > 1")
    return cut(placed.join(spans.select("column", "largest"), "column"))


def popular_leaders(open_rows: DataFrame) -> DataFrame:
    """(column, rep, n, leader): a column's leader is the row whose columns are held by most rows, for copies their common source."""
    held = open_rows.groupBy("column").agg(F.count(F.lit(1)).alias("m"))
    fame = open_rows.join(held, "column").groupBy("rep").agg((F.sum(F.log1p("m")) / F.max(F.sqrt("n"))).alias("fame"))
    known = cut(open_rows.select("column", "rep", "n").join(fame, "rep"))
    lead = known.groupBy("column").agg(F.max_by("rep", F.struct("fame", -F.col("rep"))).alias("leader"))
    return known.join(lead, "column").select("column", "rep", "n", "leader")


def link_rows(shared: DataFrame, docs: DataFrame, sizes: DataFrame) -> DataFrame:
    """(node, comp) over class representatives that link with others. shared: (column, rep, n, pos, leader), leader the smallest rep."""
    spark = docs.sparkSession
    first = cut(best_leaders(shared))
    found = links_of(first, docs, sizes)
    comps = components(found)
    open_rows = spanning(shared, comps)
    del shared
    release(spark)
    if open_rows.isEmpty():
        return comps
    again = cut(best_leaders(popular_leaders(open_rows)).join(first, ["a", "b"], "left_anti"))
    found = cut(found.union(links_of(again, docs, sizes)))
    comps = components(found)
    tried = cut(first.union(again).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    open_rows = spanning(open_rows, comps)
    release(spark)
    pairs = cut(product(open_rows).join(tried, ["a", "b"], "left_anti"))
    del open_rows
    release(spark)
    if pairs.isEmpty():
        return comps
    return components(found.select("a", "b").union(links_of(pairs, docs, sizes)))


def product(open_rows: DataFrame) -> DataFrame:
    """(a, b): cells of the product between components whose accumulated overlap doesn't rule a link out.

    Each shared column of a pair forms its cell once: rows of two components have one row outside the column's largest
    component, or two, of which the smaller id comes first.
    """
    x = open_rows.where("comp <> largest").select("column", F.col("rep").alias("x"), F.col("n").alias("nx"), F.col("comp").alias("cx"), F.col("pos").alias("px"))
    y = open_rows.select("column", F.col("rep").alias("y"), F.col("n").alias("ny"), F.col("comp").alias("cy"), F.col("pos").alias("py"), (F.col("comp") == F.col("largest")).alias("in_largest"))
    # sizes give the overlap that a link needs; two such rows share a column among the first n - needed + 1 of each
    needed = needed_overlap(F.col("nx"), F.col("ny"))
    early = (F.col("px") + needed <= F.col("nx")) & (F.col("py") + needed <= F.col("ny"))
    apart = (F.col("cx") != F.col("cy")) & (F.col("in_largest") | (F.col("x") < F.col("y")))
    cells = x.join(y, (x["column"] == y["column"]) & apart & early & _near_sizes(F.col("nx"), F.col("ny")))
    # the last shared column here has the highest place in both rows: what lies behind it is all that may still be shared
    behind = F.min(F.least(F.col("nx") - F.col("px"), F.col("ny") - F.col("py")) - 1)
    sums = cells.groupBy(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.count(F.lit(1)).alias("overlap"), behind.alias("behind"), F.first(needed).alias("needed"))
    return sums.where("overlap + behind >= needed").select("a", "b")


def shared_columns(rows: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Sizes and signatures of all documents, their classes, and the columns that several classes hold."""
    spark = rows.sparkSession
    sizes = cut(rows.select("doc_id", "n", "s1", "s2"))
    classes = cut(sizes.where("n > 0 and doc_id is not null").groupBy("s1", "s2", "n").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("members")))
    reps = cut(classes.select(F.col("rep").alias("doc_id")).distinct())
    entries = rows.join(bounded_broadcast(reps, reps.count(), 16), "doc_id").select(F.col("doc_id").alias("rep"), "n", F.posexplode("columns").alias("pos", "column"))
    held = cut(entries.groupBy("column").agg(F.count(F.lit(1)).alias("m"), F.min("rep").alias("leader")).where("m > 1").drop("m"))
    release(spark)
    shared = cut(entries.join(held, "column"))
    return sizes, classes, shared


def near_duplicates(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every row."""
    spark = docs.sparkSession
    rows, forget = stored(rows_of(docs, column_order(docs)))
    sizes, classes, shared = shared_columns(rows)
    release(spark)
    comps = link_rows(shared, docs, rows.select(F.col("doc_id").alias("rep"), "n", "blocks").dropDuplicates(["rep"]))
    del shared
    forget()
    release(spark)
    of_class = cut(classes.join(comps.withColumnRenamed("node", "rep"), "rep", "left").select("s1", "s2", "n", "members", F.coalesce("comp", "rep").alias("comp")))
    same = join_hot_apart(sizes.where("n > 0 and doc_id is not null"), of_class, ["s1", "s2", "n"], "members")
    alone = sizes.where("n = 0 or doc_id is null").withColumn("comp", F.col("doc_id"))
    columns = ("doc_id", F.col("n").cast("long").alias("n_shingles"), F.col("comp").alias("component_id"))
    return same.select(*columns).unionByName(alone.select(*columns))


def op9_ngram_jaccard(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
