"""Generic operators that users of the methods need, one query each, with SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ctxrelease.plans.runtime import bounded_broadcast
from ctxrelease.plans.runtime import table as t
from ctxrelease.queries_core import critical_ctes

QUERIES: dict = {}
SQL: dict[str, str] = {}


def checked(df: DataFrame, row_bytes: int = 64) -> DataFrame:
    """A broadcast side after a count of its rows, or a shuffled one where they are too many."""
    return bounded_broadcast(df, df.count(), row_bytes)


def op(name: str, sql: str | None, fn) -> None:
    QUERIES[f"ops_{name}"] = fn
    if sql:
        SQL[f"ops_{name}"] = sql


_SCANS = {
    "region": "r_regionkey, r_name", "nation": "n_nationkey, n_name", "customer": "c_custkey, c_acctbal", "supplier": "s_suppkey, s_acctbal", "part": "p_partkey, p_size",
    "orders": "o_orderkey, o_totalprice", "lineitem": "l_orderkey, l_quantity", "events": "event_id, value", "documents": "doc_id, n_chars", "embeddings": "vec_id, label",
    "pages": "page_id, url", "benchmark": "item_id, text", "labels": "doc_id, toxic", "conversations": "conv_id, turn",
}
for _t, _c in _SCANS.items():
    op(f"scan_{_t}", f"SELECT {_c} FROM {_t}", lambda s, d, n=_t, c=_c: t(s, d, n).select(*c.split(", ")))

op("project_bins", "SELECT event_id, hour(ts)::INT // 3 AS part, (user_id % 8)::BIGINT AS bucket, CASE WHEN value > 100 THEN 'high' ELSE 'low' END AS level FROM events",
   lambda s, d: t(s, d, "events").select("event_id", F.floor(F.hour("ts") / 3).cast("int").alias("part"), F.pmod("user_id", F.lit(8)).alias("bucket"), F.when(F.col("value") > 100, "high").otherwise("low").alias("level")))
op("filter_in_and", "SELECT event_id FROM events WHERE event_type IN ('click', 'view') AND dayofweek(ts) IN (1, 2)",
   lambda s, d: t(s, d, "events").where(F.col("event_type").isin("click", "view") & (F.dayofweek("ts") - 1).isin(1, 2)).select("event_id"))
op("filter_numeric_threshold", "SELECT p_partkey FROM part WHERE p_size < 10 AND p_retailprice BETWEEN 900 AND 1500",
   lambda s, d: t(s, d, "part").where((F.col("p_size") < 10) & F.col("p_retailprice").between(900, 1500)).select("p_partkey"))
op("filter_null_metric", "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE quality IS NOT DISTINCT FROM NULL",
   lambda s, d: t(s, d, "documents").select("doc_id").join(t(s, d, "labels").select("doc_id", "quality"), "doc_id", "left").where(F.col("quality").eqNullSafe(F.lit(None))).select("doc_id"))
op("filter_like_rlike", "SELECT page_id FROM pages WHERE url LIKE 'http%' AND regexp_matches(url, '[0-9]+')",
   lambda s, d: t(s, d, "pages").where(F.col("url").like("http%") & F.col("url").rlike("[0-9]+")).select("page_id"))
op("join_broadcast", "SELECT p_type, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_type",
   lambda s, d: t(s, d, "lineitem").join(checked(t(s, d, "part").select("p_partkey", "p_type")), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_type").agg(F.count(F.lit(1)).alias("n")))
for _h, _n in (("merge", "join_sortmerge"), ("shuffle_hash", "join_shuffle_hash")):
    op(_n, "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus",
       lambda s, d, h=_h: t(s, d, "lineitem").select("l_orderkey").join(t(s, d, "orders").select("o_orderkey", "o_orderstatus").hint(h), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n")))
op("join_star", "SELECT r_name, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name",
   lambda s, d: t(s, d, "orders").join(t(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(t(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count(F.lit(1)).alias("n")))
op("join_left_default", "SELECT d.doc_id, coalesce(quality::VARCHAR, 'none') AS quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id",
   lambda s, d: t(s, d, "documents").select("doc_id").join(t(s, d, "labels").select("doc_id", "quality"), "doc_id", "left").select("doc_id", F.coalesce(F.col("quality").cast("string"), F.lit("none")).alias("quality")))
op("join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)",
   lambda s, d: t(s, d, "customer").join(t(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"))
op("join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)",
   lambda s, d: t(s, d, "customer").join(t(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"))
op("join_full_compare", "SELECT coalesce(a.user_id, b.user_id) AS user_id, a.n AS clicks, b.n AS views FROM (SELECT user_id, count(*) AS n FROM events WHERE event_type = 'click' GROUP BY 1) a FULL JOIN (SELECT user_id, count(*) AS n FROM events WHERE event_type = 'view' GROUP BY 1) b ON a.user_id = b.user_id",
   lambda s, d: t(s, d, "events").where("event_type = 'click'").groupBy("user_id").agg(F.count(F.lit(1)).alias("clicks")).join(t(s, d, "events").where("event_type = 'view'").groupBy("user_id").agg(F.count(F.lit(1)).alias("views")), "user_id", "full").select("user_id", "clicks", "views"))
op("join_range_band", None, lambda s, d: _band(s, d))  # quadratic in SQL; compared with brute force on a fixture


def _band(s: SparkSession, d: str) -> DataFrame:
    """Band join: equal buckets of the band's width (a bucket and its neighbours), then the exact test."""
    o = t(s, d, "orders").select("o_orderkey", (F.col("o_totalprice") / 100).alias("mid"))
    o = o.withColumn("b", F.explode(F.sequence(F.floor((F.col("mid") - 5) / 10), F.floor((F.col("mid") + 5) / 10))))
    c = t(s, d, "customer").select("c_acctbal", F.floor(F.col("c_acctbal") / 10).alias("b"))
    return o.join(c, "b").where(F.col("c_acctbal").between(F.col("mid") - 5, F.col("mid") + 5)).groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("n"))


op("join_asof", "SELECT e.event_id, max(p.ts) AS last_purchase FROM events e LEFT JOIN events p ON p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts GROUP BY e.event_id",
   lambda s, d: t(s, d, "events").select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("ts")), ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)).alias("last_purchase")))
op("cross_grid", "SELECT r_name, s.v AS status FROM region, (VALUES ('F'), ('O'), ('P')) AS s(v)",
   lambda s, d: t(s, d, "region").select("r_name", F.explode(F.array(F.lit("F"), F.lit("O"), F.lit("P"))).alias("status")))
op("agg_moments", "SELECT event_type, count(*) AS n, sum((value::DECIMAL(18,4) * 10000)::BIGINT)::BIGINT AS s, min(value) AS lo, max(value) AS hi FROM events GROUP BY 1",
   lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("value").cast("decimal(18,4)") * 10000).cast("long")).alias("s"), F.min("value").alias("lo"), F.max("value").alias("hi")))
op("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1", lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users")))
op("agg_approx_distinct", None, lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users")))
op("agg_percentile", "SELECT lang, quantile_cont(n_chars, 0.5) AS mid FROM documents GROUP BY 1", lambda s, d: t(s, d, "documents").groupBy("lang").agg(F.percentile("n_chars", F.lit(0.5)).alias("mid")))
op("agg_cube", "SELECT coalesce(event_type, 'all') AS event_type, coalesce(dayofweek(ts)::INT, -1) AS day, count(*) AS n FROM events GROUP BY CUBE (event_type, dayofweek(ts)::INT)",
   lambda s, d: t(s, d, "events").select("event_type", (F.dayofweek("ts") - 1).alias("day")).cube("event_type", "day").agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("event_type", F.lit("all")).alias("event_type"), F.coalesce("day", F.lit(-1)).alias("day"), "n"))
op("agg_rollup", "SELECT coalesce(event_type, 'all') AS event_type, coalesce(dayofweek(ts)::INT, -1) AS day, count(*) AS n FROM events GROUP BY ROLLUP (event_type, dayofweek(ts)::INT)",
   lambda s, d: t(s, d, "events").select("event_type", (F.dayofweek("ts") - 1).alias("day")).rollup("event_type", "day").agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("event_type", F.lit("all")).alias("event_type"), F.coalesce("day", F.lit(-1)).alias("day"), "n"))
op("agg_grouping_sets", "SELECT coalesce(event_type, 'all') AS event_type, coalesce(dayofweek(ts)::INT, -1) AS day, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (dayofweek(ts)::INT))",
   lambda s, d: t(s, d, "events").select("event_type", (F.dayofweek("ts") - 1).alias("day")).groupingSets([[F.col("event_type")], [F.col("day")]], F.col("event_type"), F.col("day")).agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("event_type", F.lit("all")).alias("event_type"), F.coalesce("day", F.lit(-1)).alias("day"), "n"))
op("agg_pivot", "SELECT user_id % 10 AS g, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY 1",
   lambda s, d: t(s, d, "events").withColumn("g", F.col("user_id") % 10).groupBy("g").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).na.fill(0))
op("agg_argmax", "SELECT l_returnflag, max_by(l_orderkey, row(l_extendedprice, l_orderkey)) AS top, min_by(l_orderkey, row(l_extendedprice, l_orderkey)) AS low FROM lineitem GROUP BY 1",
   lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(F.max_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey")).alias("top"), F.min_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey")).alias("low")))
op("agg_collect_sorted", "SELECT lang, array_to_string(list_sort(list(doc_id)), ',') AS ids FROM documents WHERE n_chars > 10000 GROUP BY 1",
   lambda s, d: t(s, d, "documents").where("n_chars > 10000").groupBy("lang").agg(F.array_join(F.sort_array(F.collect_list("doc_id")).cast("array<string>"), ",").alias("ids")))
op("agg_bool", "SELECT event_type, bool_and(value > 0) AS every, bool_or(value > 200) AS some FROM events GROUP BY 1", lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.bool_and(F.col("value") > 0).alias("every"), F.bool_or(F.col("value") > 200).alias("some")))
op("agg_filter_clause", "SELECT event_type, count(*) FILTER (value > 100) AS high, count(*) AS n FROM events GROUP BY 1", lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 100).alias("high"), F.count(F.lit(1)).alias("n")))
op("having", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1 HAVING count(*) > 400", lambda s, d: t(s, d, "lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n")).where("n > 400"))
_W = "PARTITION BY event_type ORDER BY value DESC, event_id"
_w = lambda: Window.partitionBy("event_type").orderBy(F.desc("value"), "event_id")
op("win_rank", f"SELECT event_id, row_number() OVER ({_W})::INT AS rn, dense_rank() OVER (PARTITION BY event_type ORDER BY value DESC)::INT AS dr FROM events QUALIFY rn <= 20",
   lambda s, d: t(s, d, "events").select("event_id", F.row_number().over(_w()).alias("rn"), F.dense_rank().over(Window.partitionBy("event_type").orderBy(F.desc("value"))).alias("dr")).where("rn <= 20"))
op("win_lag_lead", f"SELECT event_id, round(value - lag(value) OVER ({_W}), 6) AS gap, round(lead(value) OVER ({_W}), 6) AS nxt FROM events",
   lambda s, d: t(s, d, "events").select("event_id", F.round(F.col("value") - F.lag("value").over(_w()), 6).alias("gap"), F.round(F.lead("value").over(_w()), 6).alias("nxt")))
op("win_running", f"SELECT event_id, sum(user_id) OVER ({_W} ROWS UNBOUNDED PRECEDING)::BIGINT AS run FROM events", lambda s, d: t(s, d, "events").select("event_id", F.sum("user_id").over(_w().rowsBetween(Window.unboundedPreceding, 0)).alias("run")))
op("win_rangeframe", "SELECT doc_id, count(*) OVER (PARTITION BY lang ORDER BY n_chars RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS near FROM documents",
   lambda s, d: t(s, d, "documents").select("doc_id", F.count(F.lit(1)).over(Window.partitionBy("lang").orderBy("n_chars").rangeBetween(-100, 100)).alias("near")))
op("win_rowframe_k", f"SELECT event_id, sum(user_id) OVER ({_W} ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING)::BIGINT AS around FROM events", lambda s, d: t(s, d, "events").select("event_id", F.sum("user_id").over(_w().rowsBetween(-3, 3)).alias("around")))
op("win_ntile_pct", "SELECT c_custkey, ntile(4) OVER w::INT AS q, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey)".replace("ntile(4) OVER w::INT", "(ntile(4) OVER w)::INT"),
   lambda s, d: (lambda w: t(s, d, "customer").select("c_custkey", F.ntile(4).over(w).alias("q"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd")))(Window.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey")))
op("win_max_shift", "SELECT event_id, round(exp((value - max(value) OVER (PARTITION BY event_type)) / 100), 9) AS e FROM events", lambda s, d: t(s, d, "events").select("event_id", F.round(F.exp((F.col("value") - F.max("value").over(Window.partitionBy("event_type"))) / 100), 9).alias("e")))
op("topk", "SELECT event_id, value FROM events ORDER BY value DESC, event_id LIMIT 25", lambda s, d: t(s, d, "events").orderBy(F.desc("value"), "event_id").limit(25).select("event_id", "value"))
op("limit_offset", "SELECT event_id FROM events ORDER BY value DESC, event_id LIMIT 10 OFFSET 30", lambda s, d: t(s, d, "events").orderBy(F.desc("value"), "event_id").offset(30).limit(10).select("event_id"))
_A, _B = "SELECT user_id FROM events WHERE event_type = 'click'", "SELECT user_id FROM events WHERE event_type = 'error'"
_a = lambda s, d: t(s, d, "events").where("event_type = 'click'").select("user_id")
_b = lambda s, d: t(s, d, "events").where("event_type = 'error'").select("user_id")
op("union", f"{_A} UNION ALL {_B}", lambda s, d: _a(s, d).unionByName(_b(s, d)))
op("intersect", f"{_A} INTERSECT {_B}", lambda s, d: _a(s, d).intersect(_b(s, d)))
op("except", f"{_A} EXCEPT {_B}", lambda s, d: _a(s, d).subtract(_b(s, d)))
op("exceptall", f"{_A} EXCEPT ALL {_B}", lambda s, d: _a(s, d).exceptAll(_b(s, d)))
op("distinct", f"SELECT DISTINCT user_id FROM ({_A})", lambda s, d: _a(s, d).distinct())
op("scalar_bits", "SELECT event_id, bit_count(event_id)::INT AS ones, xor(event_id, 5) AS flipped, event_id & 12 AS kept, lpad(bin(event_id), 20, '0') AS bits FROM events",
   lambda s, d: t(s, d, "events").select("event_id", F.bit_count("event_id").alias("ones"), F.col("event_id").bitwiseXOR(F.lit(5)).alias("flipped"), F.col("event_id").bitwiseAND(F.lit(12)).alias("kept"), F.lpad(F.bin("event_id"), 20, "0").alias("bits")))
op("scalar_math", "SELECT event_id, round(ln(1 + value), 6) AS l, round(sqrt(value), 6) AS r, round(pow(value / 100, 2), 6) AS p, floor(value)::BIGINT AS f, greatest(value, 10.0) AS g FROM events",
   lambda s, d: t(s, d, "events").select("event_id", F.round(F.log1p("value"), 6).alias("l"), F.round(F.sqrt("value"), 6).alias("r"), F.round(F.pow(F.col("value") / 100, 2), 6).alias("p"), F.floor("value").alias("f"), F.greatest("value", F.lit(10.0)).alias("g")))
op("scalar_string", "SELECT page_id, upper(url) AS u, length(html)::INT AS n, split_part(url, '/', 3) AS host, regexp_extract(url, '([0-9]+)', 1) AS num, substr(html, 1, 10) AS head FROM pages",
   lambda s, d: t(s, d, "pages").select("page_id", F.upper("url").alias("u"), F.length("html").alias("n"), F.split_part("url", F.lit("/"), F.lit(3)).alias("host"), F.regexp_extract("url", "([0-9]+)", 1).alias("num"), F.substring("html", 1, 10).alias("head")))
op("scalar_date", "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INT AS days, date_trunc('month', o_orderdate)::TIMESTAMP AS first FROM orders",
   lambda s, d: t(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).alias("days"), F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("first")))
op("scalar_array", "SELECT vec_id, len(embedding)::INT AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm, len(list_filter(embedding, lambda x: x > 0))::INT AS pos FROM embeddings",
   lambda s, d: t(s, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.round(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x), 4).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).alias("pos")))
op("scalar_map", "SELECT o_orderkey, CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 WHEN 'P' THEN 2 END::INT AS code FROM orders",
   lambda s, d: t(s, d, "orders").select("o_orderkey", F.element_at(F.create_map(*[F.lit(x) for x in ("F", 0, "O", 1, "P", 2)]), F.col("o_orderstatus")).alias("code")))
op("scalar_json", "SELECT event_id, json_extract_string(props, '$.k')::INT AS k FROM events", lambda s, d: t(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k")))
op("scalar_hash", "SELECT event_id, md5('0|' || event_id::VARCHAR) AS h, ('0x' || substr(md5('0|' || event_id::VARCHAR), 1, 13))::BIGINT AS u FROM events",
   lambda s, d: t(s, d, "events").select("event_id", F.md5(F.concat(F.lit("0|"), F.col("event_id").cast("string"))).alias("h")).withColumn("u", F.conv(F.substring("h", 1, 13), 16, 10).cast("long")))
op("decimal_sum", "SELECT l_returnflag, sum(l_extendedprice::DECIMAL(18,4))::DOUBLE AS total FROM lineitem GROUP BY 1", lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,4)")).cast("double").alias("total")))
op("explode_posexplode", "SELECT vec_id, (i - 1)::INT AS pos, embedding[i] AS v FROM (SELECT vec_id, embedding, unnest(range(1, len(embedding) + 1)) AS i FROM embeddings)", lambda s, d: t(s, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("pos", "v")))


def _sql(s: SparkSession, d: str, text: str, *names: str) -> DataFrame:
    for n in names:
        t(s, d, n).createOrReplaceTempView(n)
    return s.sql(text)


_SUB = "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders i WHERE i.o_custkey = o.o_custkey)"
op("subquery_scalar", _SUB, lambda s, d: _sql(s, d, _SUB, "orders"))
_EX = "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o_totalprice > 400000)"
op("subquery_exists", _EX, lambda s, d: _sql(s, d, _EX, "orders", "customer"))
_CTE = "WITH per AS (SELECT user_id, count(*) AS n FROM events GROUP BY user_id), best AS (SELECT max(n) AS top FROM per) SELECT user_id, n FROM per, best WHERE n = top"
op("cte_sql", _CTE, lambda s, d: _sql(s, d, _CTE, "events"))
op("sample_hash", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_orderkey % 10 = 3", lambda s, d: t(s, d, "lineitem").where("l_orderkey % 10 = 3").select("l_orderkey", "l_linenumber"))


def _udf_bits(s: SparkSession, d: str) -> DataFrame:
    from ctxrelease.functions.udf import register

    register(s)
    t(s, d, "events").createOrReplaceTempView("events")
    return s.sql("SELECT event_id, ctx_bits(event_id % 64, 6) AS bits FROM events")


op("udf", "SELECT event_id, right('000000' || bin(event_id % 64), 6) AS bits FROM events", _udf_bits)


def _udtf(s: SparkSession, d: str) -> DataFrame:
    from ctxrelease.functions.udf import register

    register(s)
    t(s, d, "events").createOrReplaceTempView("events")
    return s.sql("SELECT event_id, neighbor FROM events, LATERAL context_neighbors(event_id, 5)")


op("udtf", "SELECT event_id, xor(event_id, (1::BIGINT << b::INT)) AS neighbor FROM events, range(5) AS r(b)", _udtf)


def _ctx_sql(s: SparkSession, d: str) -> DataFrame:
    from ctxrelease.functions.udf import register
    from ctxrelease.sources.workloads import SCHEMAS

    schema = SCHEMAS["inc9"]
    register(s, schema)
    t(s, d, "events").createOrReplaceTempView("events")
    return s.sql(f"SELECT event_id, ctx_sql(event_id % {1 << schema.t}) AS predicate FROM events")


def _ctx_sql_oracle() -> str:
    from ctxrelease.sources.workloads import SCHEMAS

    schema = SCHEMAS["inc9"]
    lists, empty = [], []
    for i, a in enumerate(schema.attrs):
        values = " || ".join(f"CASE WHEN ctx & {schema.bit(i, j)} <> 0 THEN ', ''{v}''' ELSE '' END" for j, v in enumerate(a.domain))
        mask = schema.attr_masks[i]
        empty.append(f"ctx & {mask} = 0")
        lists.append(f"CASE WHEN ctx & {mask} = {mask} THEN NULL ELSE 'CAST({a.expr} AS STRING) IN (' || substr({values}, 3) || ')' END")
    return f"SELECT event_id, CASE WHEN {' OR '.join(empty)} THEN 'FALSE' ELSE coalesce(nullif(concat_ws(' AND ', {', '.join(lists)}), ''), 'TRUE') END AS predicate FROM (SELECT event_id, event_id % {1 << schema.t} AS ctx FROM events)"


op("ctx_sql", _ctx_sql_oracle(), _ctx_sql)


def _grouped_udf(s: SparkSession, d: str) -> DataFrame:
    from ctxrelease.functions.udf import studentised_range

    return t(s, d, "orders").groupBy("o_orderpriority").agg(F.round(studentised_range("o_totalprice"), 6).alias("spread"))


op("grouped_udf", "SELECT o_orderpriority, round((max(o_totalprice) - min(o_totalprice)) / stddev_samp(o_totalprice), 6) AS spread FROM orders GROUP BY 1", _grouped_udf)


def _release_contexts(s: SparkSession, d: str) -> DataFrame:
    from ctxrelease.functions.mechanism import SeededNoise
    from ctxrelease.functions.udf import release_contexts
    from ctxrelease.sources.workloads import top_records, workload

    df, schema = workload(s, d, "doc13")
    return release_contexts(df, schema, top_records(df, schema, 3), "grubbs", n=10, noise=SeededNoise(0))


op("release_contexts", None, _release_contexts)


def _mask_theta(s: SparkSession, d: str) -> DataFrame:
    """Contexts against cells by bit containment: the theta join that folding replaces."""
    from ctxrelease.plans import cells as pl
    from ctxrelease.sources.workloads import workload

    df, schema = workload(s, d, "li12")
    cells = pl.build_cells(df, schema)
    contexts = s.range(1 << schema.t).select(F.col("id").alias("ctx"))
    return contexts.join(cells, F.col("cell").bitwiseAND(F.col("ctx")) == F.col("cell")).groupBy("ctx").agg(F.count(F.lit(1)).alias("cells"), F.sum("n").alias("n"))


def _self_flip(s: SparkSession, d: str) -> DataFrame:
    """Pairs of occupied cells' supersets one flip apart, by explode and equal keys."""
    from ctxrelease.plans import cells as pl
    from ctxrelease.sources.workloads import workload

    df, schema = workload(s, d, "li12")
    folded = pl.fold_contexts(pl.build_cells(df, schema), schema).select("ctx", "n")
    flips = pl.neighbors(folded, schema.t)
    return flips.join(folded.select(F.col("ctx").alias("neighbor"), F.col("n").alias("m")), "neighbor").select("ctx", "neighbor", (F.col("m") - F.col("n")).alias("change"))


def _bits_oracles() -> tuple[str, str]:
    from ctxrelease.sources.workloads import SCHEMAS, cells_sql

    schema = SCHEMAS["li12"]
    cells = f"WITH cells AS ({cells_sql('li12')})"
    some = " AND ".join(f"ctx & {m} <> 0" for m in schema.attr_masks)
    theta = f"{cells} SELECT c.ctx, count(*) AS cells, sum(n)::BIGINT AS n FROM range({1 << schema.t}) AS c(ctx) JOIN cells ON cell & c.ctx = cell GROUP BY c.ctx"
    flip = f"{cells}, stats AS (SELECT c.ctx, sum(n)::BIGINT AS n FROM range({1 << schema.t}) AS c(ctx) JOIN cells ON cell & c.ctx = cell WHERE {some} GROUP BY c.ctx) SELECT a.ctx, b.ctx AS neighbor, b.n - a.n AS change FROM stats a JOIN stats b ON bit_count(xor(a.ctx, b.ctx)) = 1"
    return theta, flip


op("join_mask_theta", _bits_oracles()[0], _mask_theta)
op("join_self_flip", _bits_oracles()[1], _self_flip)


def _pandas_udf(s: SparkSession, d: str) -> DataFrame:
    from ctxrelease.functions.udf import grubbs_critical

    sizes = t(s, d, "events").groupBy("user_id").agg(F.count(F.lit(1)).alias("n")).where("n >= 3")
    return sizes.select("user_id", "n", F.round(grubbs_critical("n"), 5).alias("crit"))


op("pandas_udf", f"WITH sizes AS (SELECT user_id, count(*) AS n FROM events GROUP BY user_id HAVING count(*) >= 3), {critical_ctes('sizes')} SELECT user_id, sizes.n, round(crit, 5) AS crit FROM sizes JOIN k ON k.n = sizes.n", _pandas_udf)


def _roundtrip(kind: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        import uuid

        from ctxrelease.plans.runtime import shared_dir

        df = t(s, d, "customer").select("c_custkey", "c_name", "c_mktsegment")
        path = f"{shared_dir(s)}/roundtrip-{uuid.uuid4().hex}"
        df.write.format(kind).option("header", "true").save(path)
        return s.read.schema(df.schema).format(kind).option("header", "true").load(path)

    return run


for _k in ("csv", "json", "orc"):
    op(f"{_k}_roundtrip", "SELECT c_custkey, c_name, c_mktsegment FROM customer", _roundtrip(_k))
