"""Contexts over declared attribute domains.

A context is a bit mask: one bit for each value of each attribute, the first value of the first attribute being the
leftmost printed bit. Domains are declared, never read off the data, since the set of values that occur is private.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Metrics are fixed-point numbers with four places, held as whole ten-thousandths, so that sums are exact.
SCALE = 10_000
WORD_BITS = 63


@dataclass(frozen=True)
class AttributeSpec:
    """An attribute: a SQL expression over the source and its full, ordered domain (compared as strings)."""

    name: str
    expr: str
    domain: tuple[str, ...]

    def __post_init__(self):
        if not self.domain or len(set(self.domain)) != len(self.domain):
            raise ValueError(f"{self.name}: the domain must hold distinct values")


@dataclass(frozen=True)
class ContextSchema:
    name: str
    attrs: tuple[AttributeSpec, ...]
    metric: str
    record_id: str

    @property
    def m(self) -> int:
        return len(self.attrs)

    @cached_property
    def t(self) -> int:
        return sum(len(a.domain) for a in self.attrs)

    @cached_property
    def offsets(self) -> tuple[int, ...]:
        out, at = [], 0
        for a in self.attrs:
            out.append(at)
            at += len(a.domain)
        return tuple(out)

    def bit(self, attr: int, value: int) -> int:
        return 1 << (self.t - 1 - self.offsets[attr] - value)

    @cached_property
    def attr_masks(self) -> tuple[int, ...]:
        return tuple(sum(self.bit(i, j) for j in range(len(a.domain))) for i, a in enumerate(self.attrs))

    @property
    def full(self) -> int:
        return (1 << self.t) - 1

    def wellformed(self, mask: int) -> bool:
        """Every attribute allows some value; other contexts select nothing."""
        return all(mask & a for a in self.attr_masks)

    def wellformed_count(self) -> int:
        out = 1
        for a in self.attrs:
            out *= (1 << len(a.domain)) - 1
        return out

    def free_bits(self, anchor: int) -> list[int]:
        """Bits that a context of the anchored record may flip, from the right."""
        return [1 << k for k in range(self.t) if not anchor >> k & 1]

    @staticmethod
    def infer(df: DataFrame, names: list[str], metric: str, record_id: str, allow_inferred_domain: bool = False) -> ContextSchema:
        """Domains from observed values: a leaky control for tests, refused unless asked for."""
        if not allow_inferred_domain:
            raise ValueError("domains must be declared; observed values depend on private records")
        attrs = []
        for n in names:
            values = sorted(str(r[0]) for r in df.select(n).where(F.col(n).isNotNull()).distinct().limit(10_000).collect())
            attrs.append(AttributeSpec(n, n, tuple(values)))
        return ContextSchema("inferred", tuple(attrs), metric, record_id)


@dataclass(frozen=True)
class Context:
    schema: ContextSchema
    mask: int

    @classmethod
    def from_bits(cls, schema: ContextSchema, bits: str) -> Context:
        if len(bits) != schema.t or set(bits) - {"0", "1"}:
            raise ValueError(f"a context of this schema has {schema.t} bits")
        return cls(schema, int(bits, 2))

    @classmethod
    def of(cls, schema: ContextSchema, **chosen: list[str]) -> Context:
        mask = 0
        for i, a in enumerate(schema.attrs):
            for v in chosen.get(a.name, a.domain):
                mask |= schema.bit(i, a.domain.index(v))
        return cls(schema, mask)

    @property
    def bits(self) -> str:
        return format(self.mask, f"0{self.schema.t}b")

    @property
    def weight(self) -> int:
        return self.mask.bit_count()

    @property
    def is_wellformed(self) -> bool:
        return self.schema.wellformed(self.mask)

    def values(self) -> dict[str, list[str]]:
        s = self.schema
        return {a.name: [v for j, v in enumerate(a.domain) if self.mask & s.bit(i, j)] for i, a in enumerate(s.attrs)}

    def connected(self, other: Context) -> bool:
        return (self.mask ^ other.mask).bit_count() == 1

    def to_sql(self) -> str:
        """The public predicate: an IN list for each attribute that isn't wholly allowed."""
        parts = []
        for a, chosen in zip(self.schema.attrs, self.values().values()):
            if not chosen:
                return "FALSE"
            if len(chosen) < len(a.domain):
                listed = ", ".join("'" + v.replace("'", "''") + "'" for v in chosen)
                parts.append(f"CAST({a.expr} AS STRING) IN ({listed})")
        return " AND ".join(parts) or "TRUE"

    def to_column(self) -> Column:
        """A filter that Spark can push to the scan where attributes are plain columns."""
        out = F.lit(True)
        for a, chosen in zip(self.schema.attrs, self.values().values()):
            out = out & F.expr(a.expr).cast("string").isin(*(v for v in chosen)) if chosen else F.lit(False)
        return out


def wide_words(schema: ContextSchema, mask: int) -> list[int]:
    """A mask of any length as words of WORD_BITS bits, for schemas beyond one BIGINT."""
    return [mask >> k & ((1 << WORD_BITS) - 1) for k in range(0, schema.t, WORD_BITS)]


def wide_contains(cell: Column, ctx: Column) -> Column:
    """Whether a context in words holds a cell in words."""
    return F.forall(F.zip_with(cell, ctx, lambda a, b: a.bitwiseAND(b) == a), lambda x: x)
