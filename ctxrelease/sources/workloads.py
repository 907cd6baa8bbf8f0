"""The named datasets of the experiments, on the given tables; domains are declared here, not read off the data."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxrelease.plans.runtime import table
from ctxrelease.schema import AttributeSpec, ContextSchema


def _numbers(a: int, b: int) -> tuple[str, ...]:
    return tuple(str(k) for k in range(a, b))


EVENT_TYPES = ("click", "error", "purchase", "signup", "view")

SCHEMAS: dict[str, ContextSchema] = {
    s.name: s
    for s in (
        ContextSchema(
            "e14",
            (AttributeSpec("event_type", "event_type", EVENT_TYPES), AttributeSpec("day", "dayofweek(ts) - 1", _numbers(0, 7)), AttributeSpec("half", "cast(hour(ts) >= 12 as int)", ("0", "1"))),
            "value", "event_id",
        ),
        ContextSchema(
            "e25",
            (AttributeSpec("event_type", "event_type", (*EVENT_TYPES, "refund", "share", "logout", "install")), AttributeSpec("part", "cast(floor(hour(ts) / 3) as int)", _numbers(0, 8)), AttributeSpec("bucket", "user_id % 8", _numbers(0, 8))),
            "value", "event_id",
        ),
        ContextSchema(
            "li12",
            (AttributeSpec("flag", "l_returnflag", ("A", "N", "R")), AttributeSpec("status", "l_linestatus", ("F", "O")), AttributeSpec("year", "year(l_shipdate)", _numbers(1995, 2002))),
            "floor(l_extendedprice / l_quantity * 10000 + 0.5) / 10000", "record_id",
        ),
        ContextSchema(
            "li16",
            (AttributeSpec("flag", "l_returnflag", ("A", "N", "R", "X")), AttributeSpec("type", "p_type", ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD")), AttributeSpec("year", "least(year(l_shipdate), 2000)", _numbers(1995, 2001))),
            "round(l_extendedprice / l_quantity / 1000)", "record_id",
        ),
        ContextSchema(
            "doc13",
            (AttributeSpec("lang", "lang", ("de", "en", "es", "fr")), AttributeSpec("source", "cast(regexp_extract(source, '([0-9]+)', 1) as int) % 6", _numbers(0, 6)), AttributeSpec("quality", "coalesce(cast(quality as string), 'none')", ("0", "1", "none"))),
            "n_chars", "doc_id",
        ),
        ContextSchema(
            "o13",
            (AttributeSpec("status", "o_orderstatus", ("F", "O", "P")), AttributeSpec("priority", "substring(o_orderpriority, 1, 1)", _numbers(1, 6)), AttributeSpec("segment", "c_mktsegment", ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"))),
            "o_totalprice", "o_orderkey",
        ),
        ContextSchema(
            "o9",
            (AttributeSpec("status", "o_orderstatus", ("F", "O", "P")), AttributeSpec("priority", "substring(o_orderpriority, 1, 1)", ("1", "2", "3")), AttributeSpec("segment", "c_mktsegment", ("AUTOMOBILE", "BUILDING", "FURNITURE"))),
            "o_totalprice", "o_orderkey",
        ),
        ContextSchema("cv11", (AttributeSpec("role", "role", ("assistant", "system", "user")), AttributeSpec("turn", "turn", _numbers(0, 8))), "char_length(text)", "conv_id * 1000 + turn"),
        ContextSchema("emb10", (AttributeSpec("label", "label", _numbers(0, 10)),), "embedding[0]", "vec_id"),
        ContextSchema(
            "inc9",
            (AttributeSpec("job", "job", ("CEO", "Medical Doctor", "Lawyer")), AttributeSpec("city", "city", ("Montreal", "Ottawa", "Toronto")), AttributeSpec("district", "district", ("Business", "Historic", "Diplomatic"))),
            "salary", "id",
        ),
    )
}
#: Ten people; the attribute values are the worked example's, the salaries are ours.
INCOME = [
    (1, "Medical Doctor", "Montreal", "Business", 210_000), (2, "Lawyer", "Toronto", "Business", 180_000), (3, "CEO", "Ottawa", "Diplomatic", 950_000), (4, "Lawyer", "Toronto", "Business", 175_000),
    (5, "Lawyer", "Ottawa", "Diplomatic", 160_000), (6, "Medical Doctor", "Toronto", "Historic", 205_000), (7, "Lawyer", "Ottawa", "Business", 172_000), (8, "Lawyer", "Ottawa", "Diplomatic", 168_000),
    (9, "CEO", "Montreal", "Historic", 400_000), (10, "Medical Doctor", "Toronto", "Diplomatic", 220_000),
]


def _hashed_rows(df: DataFrame) -> DataFrame:
    """A record id for rows without a key: a hash of all columns, and the ordinal among equal rows."""
    from pyspark.sql import Window

    h = F.xxhash64(*df.columns)
    return df.withColumn("__h", h).withColumn("record_id", F.concat_ws(":", F.col("__h"), F.row_number().over(Window.partitionBy("__h").orderBy(F.lit(1)))))


def _line_id():
    """An id without a shuffle: equal only for rows that agree in all these columns."""
    return F.concat_ws("|", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.unix_micros(F.col("l_shipdate").cast("timestamp")), (F.col("l_extendedprice") * 100).cast("long"))


def load(spark: SparkSession, sf_dir: str, name: str, with_ids: bool = False) -> DataFrame:
    """The source rows of a dataset. `with_ids` gives lineitem rows their hash ids, at the price of a shuffle."""
    if name in ("e14", "e25"):
        return table(spark, sf_dir, "events")
    if name in ("li12", "li16"):
        li = table(spark, sf_dir, "lineitem")
        li = _hashed_rows(li) if with_ids else li.withColumn("record_id", _line_id())
        if name == "li12":
            return li
        part = table(spark, sf_dir, "part").select("p_partkey", "p_type")
        return li.join(part, li["l_partkey"] == part["p_partkey"]).withColumn("p_type", F.regexp_extract("p_type", r"^(\w+)", 1))
    if name == "doc13":
        docs = table(spark, sf_dir, "documents").select("doc_id", "lang", "source", "n_chars")
        return docs.join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", "left")
    if name in ("o13", "o9"):
        orders, customer = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
        return orders.join(customer, orders["o_custkey"] == customer["c_custkey"])
    if name == "cv11":
        return table(spark, sf_dir, "conversations")
    if name == "emb10":
        return table(spark, sf_dir, "embeddings")
    if name == "inc9":
        return spark.createDataFrame(INCOME, "id long, job string, city string, district string, salary long")
    raise KeyError(name)


@dataclass(frozen=True)
class Workload:
    name: str
    load: Callable[[SparkSession, str], DataFrame]
    schema: ContextSchema


def workload(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, ContextSchema]:
    return load(spark, sf_dir, name), SCHEMAS[name]


def top_records(df: DataFrame, schema: ContextSchema, k: int = 1) -> list:
    """Ids of the k largest metrics; ties to the smaller id."""
    from ctxrelease.plans.cells import encode

    return [r[0] for r in encode(df, schema).orderBy(F.desc("x"), "record_id").limit(k).select("record_id").collect()]


# the id is the one of _line_id(), so that ties for the largest metric go to the same record
_LINE_ID_SQL = "concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, epoch_us(l_shipdate::TIMESTAMP), trunc(l_extendedprice * 100)::BIGINT)"

# DuckDB text of each dataset: (from clause, attribute expressions, metric, id), for oracle queries.
SQL = {
    "e14": ("events", ["event_type", "dayofweek(ts)::VARCHAR", "(hour(ts) >= 12)::INT::VARCHAR"], "value", "event_id"),
    "e25": ("events", ["event_type", "(hour(ts) // 3)::VARCHAR", "(user_id % 8)::VARCHAR"], "value", "event_id"),
    "li12": ("lineitem", ["l_returnflag", "l_linestatus", "year(l_shipdate)::VARCHAR"], "floor(l_extendedprice / l_quantity * 10000 + 0.5) / 10000", _LINE_ID_SQL),
    "li16": ("(SELECT * FROM lineitem JOIN part ON l_partkey = p_partkey)", ["l_returnflag", "regexp_extract(p_type, '^(\\w+)', 1)", "least(year(l_shipdate), 2000)::VARCHAR"], "round(l_extendedprice / l_quantity / 1000)", _LINE_ID_SQL),
    "doc13": ("(SELECT d.doc_id, lang, source, n_chars, quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id)", ["lang", "(regexp_extract(source, '([0-9]+)', 1)::INT % 6)::VARCHAR", "coalesce(quality::VARCHAR, 'none')"], "n_chars", "doc_id"),
    "o13": ("(SELECT * FROM orders JOIN customer ON o_custkey = c_custkey)", ["o_orderstatus", "o_orderpriority[1:1]", "c_mktsegment"], "o_totalprice", "o_orderkey"),
    "o9": ("(SELECT * FROM orders JOIN customer ON o_custkey = c_custkey)", ["o_orderstatus", "o_orderpriority[1:1]", "c_mktsegment"], "o_totalprice", "o_orderkey"),
    "cv11": ("conversations", ["role", "turn::VARCHAR"], "length(text)", "conv_id * 1000 + turn"),
    "emb10": ("embeddings", ["label::VARCHAR"], "embedding[1]", "vec_id"),
}

def encoded_sql(name: str) -> str:
    """SQL of encode(): record_id, cell, x."""
    source, exprs, metric, rid = SQL[name]
    schema = SCHEMAS[name]
    bits = []
    for i, (a, e) in enumerate(zip(schema.attrs, exprs)):
        whens = " ".join(f"WHEN '{v}' THEN {schema.bit(i, j)}" for j, v in enumerate(a.domain))
        bits.append(f"(CASE {e} {whens} END)")
    return f"SELECT * FROM (SELECT {rid} AS record_id, ({' | '.join(bits)})::BIGINT AS cell, (({metric})::DECIMAL(18,4) * 10000)::BIGINT AS x FROM {source}) WHERE cell IS NOT NULL AND x IS NOT NULL"


def cells_sql(name: str) -> str:
    return f"SELECT cell, count(*) AS n, sum(x::HUGEINT) AS s, sum(x::HUGEINT * x) AS ss, min(x) AS lo, max(x) AS hi FROM ({encoded_sql(name)}) GROUP BY cell"


def candidates_sql(name: str, anchor: str = "a.cell") -> str:
    """All contexts as masks that hold the anchor row `a` and allow some value of each attribute."""
    schema = SCHEMAS[name]
    return f"SELECT c.ctx FROM range({1 << schema.t}) AS c(ctx), anchor a WHERE c.ctx & {anchor} = {anchor}"
