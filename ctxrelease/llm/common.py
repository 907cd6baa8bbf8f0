"""Shared pieces of the corpus operators."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ctxrelease.plans import runtime
from ctxrelease.plans.runtime import bounded_broadcast

#: Texts are worked on in slices of about this many characters, so that memory doesn't follow the batch size.
SLICE_CHARS = 1 << 20


def slices(texts: list[str], limit: int = SLICE_CHARS) -> Iterator[tuple[int, int]]:
    """Ranges [i, j) of consecutive texts of about `limit` characters; a longer text has a range of its own."""
    i, size = 0, 0
    for j, text in enumerate(texts):
        if size and size + len(text) > limit:
            yield i, j
            i, size = j, 0
        size += len(text)
    if i < len(texts):
        yield i, len(texts)


#: What one operator keeps in a worker process between tasks; another operator's claim drops it.
_held: dict[tuple, Any] = {}
#: Further caches to empty then, by operator.
_caches: dict[str, list[Callable[[], None]]] = {}


def on_drop(owner: str, clear: Callable[[], None]) -> None:
    _caches.setdefault(owner, []).append(clear)


def claim(owner: str) -> None:
    """Called by every task of an operator: what other operators keep in this process goes, so memories don't add up over stages."""
    others = [k for k in _held if k[0] != owner]
    if others:
        for k in others:
            del _held[k]
        for name, clears in _caches.items():
            if name != owner:
                for clear in clears:
                    clear()
        give_back()


def remembered(key: tuple, make: Callable[[], Any]) -> Any:
    """The process-wide object of a key (operator name first); a process holds one at a time."""
    claim(key[0])
    if key not in _held:
        _held.clear()
        _held[key] = make()
    return _held[key]


def give_back() -> None:
    """Returns freed memory to the system at the end of a task or a training: processes live on beside the next stage's."""
    pa.default_memory_pool().release_unused()
    runtime.give_back()


def fresh(df: DataFrame, name: str) -> str:
    """A column name that `df` doesn't have in any case."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def text_slices(column: pa.Array, limit: int = SLICE_CHARS) -> Iterator[tuple[int, int, list[str | None]]]:
    """(i, j, texts) of consecutive rows of about `limit` bytes: a batch never lies in Python's strings as a whole."""
    sizes = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False)
    i, size = 0, 0
    for j, n in enumerate(sizes.tolist()):
        if size and size + n > limit:
            yield i, j, column.slice(i, j - i).to_pylist()
            i, size = j, 0
        size += n
    if i < len(column):
        yield i, len(column), column.slice(i).to_pylist()


#: Keys of more rows than this meet their rows by broadcast: there are at most rows / HOT_ROWS of them.
HOT_ROWS = 1024


def join_hot_apart(rows: DataFrame, table: DataFrame, keys: list[str], size: str, how: str = "inner") -> DataFrame:
    """Joins rows with a table of one row per key, which says in column `size` how many rows a key has.

    Keys of many rows are broadcast where their count proves them few, so that no task gets all rows of one key.
    """
    hot = table.where(F.col(size) > HOT_ROWS).withColumn("__hot", F.lit(True))
    known = rows.join(bounded_broadcast(hot, hot.count(), 64), keys, "left")
    near = known.where("__hot").drop("__hot")
    rest = known.where("__hot is null").select(*rows.columns).join(table.where(F.col(size) <= HOT_ROWS), keys, how)
    return near.unionByName(rest)


def append_columns(df: DataFrame, text_col: str, fields: list[T.StructField], maker: Callable[[], Callable[[list[str | None]], list[list[Any]]]], keep: list[str] | None = None, owner: str = "") -> DataFrame:
    """One pass over `df`: the columns in `keep` (all, if None) and new ones computed from whole texts.

    `maker` runs once per task and returns a function from a list of texts (None for null) to one list per field.
    An existing column with the name of a new one is replaced. `owner` names the operator whose memories may stay.
    """
    new = {f.name.lower() for f in fields}
    names = [c for c in (df.columns if keep is None else keep) if c.lower() not in new]
    source = df.select(*[df[c] for c in names], df[text_col].alias(fresh(df, "__text")))
    kept = T.StructType([source.schema[c] for c in names])
    schema = T.StructType([*kept.fields, *fields])
    out = to_arrow_schema(T.StructType(fields))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim(owner)
        work = maker()
        for batch in batches:
            for i, j, texts in text_slices(batch.column(len(names)), 4 * SLICE_CHARS):
                part = batch.slice(i, j - i)
                columns = work(texts)
                arrays = [pa.array(c, type=f.type) for c, f in zip(columns, out)]
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in range(len(names))), *arrays], names=[*names, *out.names])
        give_back()

    return source.mapInArrow(run, schema)
