"""The operators around sorted processing: scans, joins, aggregates, windows, functions, streams."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from prefixcode.functions import udfs
from prefixcode.operators import derive
from prefixcode.plans.frame import OFFSET
from prefixcode.sources import scratch, store
from prefixcode.sources.runreader import PrefixRuns
from prefixcode.streaming import events
from prefixcode.workloads import sql as q

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def add(name: str, twin: str | None = None) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if twin:
            SQL[name] = twin
        return f

    return put


def t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def views(spark: SparkSession, d: str, *names: str) -> None:
    for n in names:
        t(spark, d, n).createOrReplaceTempView(n)


def same(name: str, statement: str, *tables: str) -> None:
    """A query that both engines run as the same text."""

    def run(s: SparkSession, d: str) -> DataFrame:
        views(s, d, *tables)
        return s.sql(statement)

    add(name, statement)(run)


# ---------------------------------------------------------------- scans, projections, filters
@add("scan_filter", "SELECT l_orderkey, l_extendedprice FROM lineitem WHERE l_shipdate < TIMESTAMP '1998-01-01' AND l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R')")
def scan_filter(s: SparkSession, d: str) -> DataFrame:
    x = t(s, d, "lineitem")
    return x.where((F.col("l_shipdate") < F.lit("1998-01-01").cast("timestamp_ntz")) & F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R")).select("l_orderkey", "l_extendedprice")


@add("filter_kinds", "SELECT p_partkey FROM part WHERE p_brand LIKE 'Brand#1%' OR regexp_matches(p_type, 'STEEL$') OR nullif(p_size, 7) IS NULL OR NOT (nullif(p_size, 9) IS DISTINCT FROM NULL)")
def filter_kinds(s: SparkSession, d: str) -> DataFrame:
    x = t(s, d, "part")
    return x.where(F.col("p_brand").like("Brand#1%") | F.col("p_type").rlike("STEEL$") | F.nullif("p_size", F.lit(7)).isNull() | F.nullif("p_size", F.lit(9)).eqNullSafe(F.lit(None))).select("p_partkey")


@add("project_basic", "SELECT c_custkey AS id, upper(c_mktsegment) AS segment, round(c_acctbal * 1.1, 2) AS balance, c_acctbal < 0 AS owes FROM customer")
def project_basic(s: SparkSession, d: str) -> DataFrame:
    return t(s, d, "customer").select(F.col("c_custkey").alias("id"), F.upper("c_mktsegment").alias("segment"), F.round(F.col("c_acctbal") * 1.1, 2).alias("balance"), (F.col("c_acctbal") < 0).alias("owes"))


for _format in ("csv", "json", "orc"):

    def _io(s: SparkSession, d: str, kind: str = _format) -> DataFrame:
        x = t(s, d, "nation")
        path = scratch.fresh(s, kind)
        x.write.option("header", True).format(kind).save(path)
        return s.read.schema(x.schema).option("header", True).format(kind).load(path)

    add(f"io_roundtrip_{_format}", "SELECT * FROM nation")(_io)


@add("io_text_lines", "SELECT n_name AS value FROM nation")
def io_text(s: SparkSession, d: str) -> DataFrame:
    path = scratch.fresh(s, "text")
    t(s, d, "nation").select(F.col("n_name").alias("value")).write.text(path)
    return s.read.text(path)


@add("io_partitioned", "SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_orderstatus = 'F' GROUP BY ALL")
def io_partitioned(s: SparkSession, d: str) -> DataFrame:
    path = scratch.fresh(s, "partitioned")
    t(s, d, "orders").write.partitionBy("o_orderstatus").parquet(path)
    return s.read.parquet(path).where("o_orderstatus = 'F'").groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


# ---------------------------------------------------------------- joins
_J = "SELECT {c} FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_totalprice > 300000 GROUP BY o_orderpriority"
for _kind in ("broadcast", "shuffle_hash", "merge"):

    def _hinted(s: SparkSession, d: str, kind: str = _kind) -> DataFrame:
        o = t(s, d, "orders").where("o_totalprice > 300000").select("o_orderkey", "o_orderpriority")
        x = t(s, d, "lineitem").select("l_orderkey", "l_quantity")
        small = o if kind == "broadcast" else o.hint(kind)  # the host checks the size before it broadcasts
        return x.join(small, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))

    add(f"join_{_kind}", _J.format(c="o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS quantity"))(_hinted)

for _how, _text in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):

    def _outer(s: SparkSession, d: str, how: str = _how) -> DataFrame:
        a = t(s, d, "documents").select("doc_id", "lang")
        b = t(s, d, "labels").select(F.col("doc_id").alias("id"), "quality")
        return a.join(b, F.col("doc_id") == F.col("id"), how)

    add(f"join_{_how}", f"SELECT a.doc_id, lang, id, quality FROM documents a {_text} JOIN (SELECT doc_id AS id, quality FROM labels) b ON a.doc_id = b.id")(_outer)

same("join_semi", "SELECT doc_id FROM documents WHERE EXISTS (SELECT 1 FROM labels WHERE labels.doc_id = documents.doc_id)", "documents", "labels")
same("join_anti", "SELECT doc_id FROM documents WHERE NOT EXISTS (SELECT 1 FROM labels WHERE labels.doc_id = documents.doc_id)", "documents", "labels")
same("join_cross", "SELECT r_name, n_name FROM region CROSS JOIN nation", "region", "nation")
same("join_theta", "SELECT a.n_nationkey AS a, count(*) AS n FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey GROUP BY a.n_nationkey", "nation")
same("join_star", "SELECT n_name, o_orderpriority, count(*) AS n FROM customer JOIN orders ON c_custkey = o_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name, o_orderpriority", "customer", "orders", "nation")

# ---------------------------------------------------------------- aggregates
same("agg_stats", "SELECT l_returnflag, min(l_quantity) AS low, max(l_quantity) AS high, round(avg(l_quantity), 6) AS mean, round(stddev_samp(l_quantity), 6) AS dev, round(var_pop(l_quantity), 6) AS var, round(corr(l_quantity, l_extendedprice), 6) AS cor FROM lineitem GROUP BY l_returnflag", "lineitem")
same("agg_filter_clause", "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS f, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY o_orderpriority", "orders")
same("agg_bool_maxby", "SELECT o_orderstatus, bool_and(o_totalprice > 0) AS positive, bool_or(o_totalprice > 400000) AS big, max_by(o_orderkey, o_totalprice) AS top FROM orders GROUP BY o_orderstatus", "orders")
same("agg_having", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey HAVING count(*) > 50", "lineitem")
same("cube_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)", "lineitem")
same("grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())", "orders")


@add("agg_pivot", "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS \"F\", count(*) FILTER (WHERE o_orderstatus = 'O') AS \"O\" FROM orders GROUP BY o_orderpriority")
def agg_pivot(s: SparkSession, d: str) -> DataFrame:
    return t(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).agg(F.count(F.lit(1))).fillna(0)


@add("agg_collect_sorted", "SELECT conv_id, string_agg(role, ',' ORDER BY turn) AS roles FROM conversations GROUP BY conv_id")
def agg_collect(s: SparkSession, d: str) -> DataFrame:
    parts = F.sort_array(F.collect_list(F.struct("turn", "role")))
    return t(s, d, "conversations").groupBy("conv_id").agg(F.concat_ws(",", F.transform(parts, lambda x: x["role"])).alias("roles"))


@add("agg_approximate")
def agg_approximate(s: SparkSession, d: str) -> DataFrame:
    return t(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_extendedprice", 0.5, 1000).alias("median"))


# ---------------------------------------------------------------- windows
same("win_ranking", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_orderdate, o_orderkey)".replace("row_number() OVER w AS rn", "CAST(row_number() OVER w AS BIGINT) AS rn").replace("rank() OVER w AS rk, dense_", "CAST(rank() OVER w AS BIGINT) AS rk, dense_").replace("dense_rank() OVER w AS dr", "CAST(dense_rank() OVER w AS BIGINT) AS dr"), "orders")
same("win_ntile", "SELECT c_custkey, CAST(ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS BIGINT) AS tile FROM customer", "customer")
same("win_lag_lead", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)", "events")
same("win_values", "SELECT event_id, first_value(event_id) OVER w AS first, last_value(event_id) OVER w AS last, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)", "events")
same("win_frames", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS near FROM events", "events")

# ---------------------------------------------------------------- limits, sets
same("limit_offset", "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 20 OFFSET 10", "customer")
same("set_union_all", "SELECT n_name AS name FROM nation UNION ALL SELECT r_name FROM region", "nation", "region")
same("set_except", "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders", "customer", "orders")
same("set_intersect", "SELECT c_custkey AS k FROM customer INTERSECT SELECT o_custkey FROM orders", "customer", "orders")


@add("sample_rows")
def sample_rows(s: SparkSession, d: str) -> DataFrame:
    """The feature is the limit: a tenth of the rows, and more of one stratum."""
    x = t(s, d, "orders")
    return x.sample(0.1, seed=3).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n")).unionAll(x.sampleBy("o_orderstatus", {"F": 0.2}, seed=3).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n")))


# ---------------------------------------------------------------- functions
same("fn_string", "SELECT p_partkey, lower(p_name) AS lo, upper(p_brand) AS up, trim(p_type) AS tr, substr(p_name, 2, 5) AS sub, concat(p_brand, '-', p_type) AS cat, replace(p_type, 'STEEL', 'IRON') AS rep, lpad(CAST(p_size AS STRING), 4, '0') AS pad, CAST(length(p_name) AS BIGINT) AS len, CAST(instr(p_name, 'a') AS BIGINT) AS at, CAST(levenshtein(p_brand, p_type) AS BIGINT) AS dist, reverse(p_brand) AS rev FROM part", "part")
same("fn_math", "SELECT l_orderkey, l_linenumber, l_partkey, round(l_extendedprice, 1) AS r, CAST(floor(l_quantity / 3) AS BIGINT) AS f, CAST(ceil(l_quantity / 3) AS BIGINT) AS c, abs(l_discount - 0.05) AS a, l_partkey % 7 AS m, round(power(l_quantity, 2), 4) AS p, round(sqrt(l_extendedprice), 4) AS s, round(ln(l_extendedprice), 4) AS l, greatest(l_tax, l_discount) AS g, least(l_tax, l_discount) AS le FROM lineitem", "lineitem")


@add("fn_date", "SELECT o_orderkey, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS month, CAST(extract(year FROM o_orderdate) AS INT) AS y, CAST(CAST(o_orderdate + INTERVAL 10 DAY AS DATE) AS VARCHAR) AS later, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INT) AS days, strftime(o_orderdate, '%Y-%m') AS ym FROM orders")
def fn_date(s: SparkSession, d: str) -> DataFrame:
    o = F.col("o_orderdate")
    return t(s, d, "orders").select("o_orderkey", F.date_trunc("month", o).cast("date").cast("string").alias("month"), F.year(o).alias("y"), F.date_add(o.cast("date"), 10).cast("string").alias("later"), F.datediff(o.cast("date"), F.lit("1992-01-01").cast("date")).alias("days"), F.date_format(o, "yyyy-MM").alias("ym"))


@add("fn_array", "SELECT vec_id, CAST(len(embedding) AS INT) AS n, round(CAST(list_max(embedding) AS DOUBLE), 4) AS high, round(CAST(embedding[1] AS DOUBLE), 4) AS first, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS positive, round(list_sum(list_transform(embedding[1:4], lambda x: CAST(x AS DOUBLE))), 4) + 0.0 AS four FROM embeddings")
def fn_array(s: SparkSession, d: str) -> DataFrame:
    e = F.col("embedding")
    four = F.aggregate(F.slice(e, 1, 4), F.lit(0.0), lambda a, x: a + x.cast("double"))
    return t(s, d, "embeddings").select("vec_id", F.size(e).alias("n"), F.round(F.array_max(e).cast("double"), 4).alias("high"), F.round(F.element_at(e, 1).cast("double"), 4).alias("first"), F.size(F.filter(e, lambda x: x > 0)).alias("positive"), (F.round(four, 4) + 0.0).alias("four"))


@add("fn_explode", "SELECT vec_id, CAST(i - 1 AS INT) AS pos, round(CAST(embedding[i] AS DOUBLE), 4) AS v FROM embeddings, range(1, 4) r(i)")
def fn_explode(s: SparkSession, d: str) -> DataFrame:
    return t(s, d, "embeddings").select("vec_id", F.posexplode(F.slice("embedding", 1, 3)).alias("pos", "x")).select("vec_id", "pos", F.round(F.col("x").cast("double"), 4).alias("v"))


@add("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json(s: SparkSession, d: str) -> DataFrame:
    return t(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@add("fn_json_struct", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json_struct(s: SparkSession, d: str) -> DataFrame:
    return t(s, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@add("fn_json_variant", SQL["fn_json"])
def fn_json_variant(s: SparkSession, d: str) -> DataFrame:
    return t(s, d, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "long").alias("k"))


@add("fn_zip_map", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 3) AS length2, label * 2 AS twice FROM embeddings")
def fn_zip_map(s: SparkSession, d: str) -> DataFrame:
    """Two arrays element by element, and a map that is looked up."""
    e = F.transform("embedding", lambda x: x.cast("double"))
    doubled = F.transform_values(F.map_from_arrays(F.array(F.lit("label")), F.array("label")), lambda _, v: v * 2)
    return t(s, d, "embeddings").select("vec_id", F.round(F.aggregate(F.zip_with(e, e, lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x), 3).alias("length2"), F.element_at(doubled, "label").alias("twice"))


_KINDS = f"SELECT CASE WHEN off = 0 THEN 'first' WHEN off >= 2 THEN 'repeat' ELSE 'shared' END AS kind, count(*) AS n, CAST(sum(2 - off) AS BIGINT) AS stored FROM {q.offsets('lineitem', q.KL)} GROUP BY 1"


@add("udf_pandas_arrow", _KINDS)
def udf_pandas_arrow(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(t(s, d, "lineitem").select(*q.KL), q.KL, 1)
    x = of.df.select(udfs.offset_kind(F.col(OFFSET), F.lit(2)).alias("kind"), udfs.stored_cells(F.col(OFFSET), F.lit(2)).alias("cells"))
    return x.groupBy("kind").agg(F.count(F.lit(1)).alias("n"), F.sum("cells").alias("stored"))


@add("bucketed_join", "SELECT o_orderkey, o_custkey, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL")
def bucketed_join(s: SparkSession, d: str) -> DataFrame:
    """Both tables in buckets by the key, sorted: the merge join and the groups above it need no exchange."""
    o = scratch.bucketed(t(s, d, "orders").select("o_orderkey", "o_custkey"), ["o_orderkey"], 8, "orders")
    x = scratch.bucketed(t(s, d, "lineitem").select("l_orderkey"), ["l_orderkey"], 8, "lineitem")
    return o.join(x.hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey", "o_custkey").agg(F.count(F.lit(1)).alias("n"))


@add("run_reader", "SELECT l_orderkey, l_linenumber, count(*) AS n FROM lineitem GROUP BY ALL")
def run_reader(s: SparkSession, d: str) -> DataFrame:
    """A stored run read by the data source of this package, a task for each of its files."""
    path = scratch.fresh(s, "run")
    store.write_sorted(t(s, d, "lineitem").select(*q.KL), q.KL, path, 4)
    s.dataSource.register(PrefixRuns)
    return s.read.format("prefix_runs").option("path", path).load().groupBy(*q.KL).agg(F.count(F.lit(1)).alias("n"))


@add("fn_url", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, CAST(length(regexp_replace(html, '<[^>]*>', '', 'g')) AS BIGINT) AS plain FROM pages")
def fn_url(s: SparkSession, d: str) -> DataFrame:
    return t(s, d, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("long").alias("plain"))


same("fn_hash", "SELECT doc_id, md5(text) AS m FROM documents", "documents")
same("fn_conditional", "SELECT o_orderkey, CASE WHEN o_totalprice > 300000 THEN 'big' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'small' END AS kind, coalesce(nullif(o_orderstatus, 'O'), 'none') AS st, try_cast(substr(o_orderpriority, 1, 1) AS INT) AS p FROM orders", "orders")

# ---------------------------------------------------------------- SQL
same("sql_subqueries", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 0)", "orders", "customer")
same("sql_cte", "WITH x AS (SELECT l_orderkey, sum(l_quantity) AS quantity FROM lineitem GROUP BY l_orderkey), y AS (SELECT quantity, count(*) AS n FROM x GROUP BY quantity) SELECT quantity, n FROM y WHERE n > 1", "lineitem")


@add("sql_codes", f"SELECT l_orderkey, l_linenumber, off AS o, CASE WHEN off >= 2 THEN 0 ELSE l_linenumber END AS v FROM {q.offsets('lineitem', q.KL)} WHERE off > 0")
def sql_codes(s: SparkSession, d: str) -> DataFrame:
    """Codes made and taken apart by SQL functions over a view."""
    udfs.register(s)
    of = derive.attach(t(s, d, "lineitem").select(*q.KL), q.KL, 1)
    of.df.withColumnRenamed(OFFSET, "off").createOrReplaceTempView("__coded")
    return s.sql("SELECT l_orderkey, l_linenumber, prefix_offset(c, 2) AS o, CAST(prefix_value(c) AS INT) AS v FROM (SELECT *, prefix_code(off, CAST(l_linenumber AS BIGINT), 2) AS c FROM __coded) WHERE off > 0")


@add("udaf_truncation", f"SELECT l_returnflag, CAST(sum(off) AS BIGINT) AS cells FROM {q.offsets('lineitem', q.K4)} GROUP BY l_returnflag")
def udaf_truncation(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(t(s, d, "lineitem").select(*q.K4), q.K4, 2)
    return of.df.groupBy("l_returnflag").agg(udfs.truncated_cells(F.col(OFFSET)).alias("cells"))


@add("udtf_expand", "SELECT n_name AS value, CAST(i AS BIGINT) AS pos FROM nation, range(0, 25) r(i) WHERE i < n_regionkey + 1")
def udtf_expand(s: SparkSession, d: str) -> DataFrame:
    udfs.register(s)
    views(s, d, "nation")
    return s.sql("SELECT e.value, e.pos FROM nation, LATERAL expand_run(0, n_regionkey + 1, n_name) e")


# ---------------------------------------------------------------- streams
add("stream_tumbling", "SELECT date_trunc('day', ts) AS win_start, event_type, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY ALL".replace("date_trunc('day', ts)", "CAST(date_trunc('day', ts) AS TIMESTAMP)"))(events.tumbling)
add("stream_sliding", "SELECT CAST(d AS TIMESTAMP) AS win_start, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS d FROM events) GROUP BY 1")(events.sliding)
add(
    "stream_session",
    "WITH x AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR THEN 0 ELSE 1 END AS fresh FROM events), "
    "y AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM x) SELECT user_id, min(ts) AS session_start, count(*) AS n FROM y GROUP BY user_id, g",
)(lambda s, d: events.sessions(s, d))
add("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")(events.distinct_in_watermark)
add("stream_static_join", "SELECT event_id, user_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")(events.with_customers)
add("stream_stream_join", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 6 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")(lambda s, d: events.pairs_in_time(s, d, "click", "purchase"))
add("stream_stateful_groups", "SELECT user_id, count(*) AS n, max(event_id) AS last_event FROM events GROUP BY user_id")(events.stateful_groups)


add("stream_late_rows", "SELECT (SELECT count(*) FROM events WHERE ts >= (SELECT min(ts) FROM events) + INTERVAL 15 DAY) AS in_time, (SELECT count(*) FROM events WHERE ts < (SELECT min(ts) FROM events) + INTERVAL 10 DAY) AS late")(events.late_rows)
add("stream_rate", "SELECT CAST(event_id % 3 AS BIGINT) AS digit, count(*) AS n FROM events GROUP BY 1")(events.rate)


@add("stream_runs", f"SELECT event_type, user_id, ts, off, count(*) AS n FROM {q.offsets('events', q.KE)} GROUP BY ALL")
def stream_runs(s: SparkSession, d: str) -> DataFrame:
    x = events.ingest(s, d, q.KE).merged().withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    return x.groupBy(*q.KE, F.col(OFFSET).alias("off")).agg(F.count(F.lit(1)).alias("n"))


del W
