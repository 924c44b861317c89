"""Queries over codes, and the paper's experiments, with SQL twins where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from prefixcode.functions import measures
from prefixcode.functions.keys import KeyCol, key_spec, normalize_bytes
from prefixcode.operators import derive, join, sort, stream
from prefixcode.plans import planner
from prefixcode.plans.frame import CODE, OFFSET, OrderedFrame
from prefixcode.sources import formats, scratch, store
from prefixcode.workloads import experiments
from prefixcode.workloads import sql as q
from prefixcode.workloads.sql import K4, K6, K8, KC, KE, KL, KO, KV

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


def off(of: OrderedFrame | DataFrame) -> DataFrame:
    return (of.df if isinstance(of, OrderedFrame) else of).withColumn("off", F.col(OFFSET))


def lines(spark: SparkSession, d: str, keys: list[str], more: tuple = ()) -> DataFrame:
    return t(spark, d, "lineitem").select(*dict.fromkeys([*keys, *more]))


# ---------------------------------------------------------------- deriving codes
def _attach(keys: list[str], lead: int | None, table: str = "lineitem") -> Query:
    return lambda s, d: off(derive.attach(t(s, d, table).select(*keys), keys, lead)).select(*keys, "off")


for _name, _keys, _lead, _table in (("codes_attach_k4", K4, 3, "lineitem"), ("codes_attach_k6", K6, None, "lineitem"), ("codes_attach_k8", K8, None, "lineitem"), ("codes_attach_orders", KO, 1, "orders"), ("codes_attach_events", KE, 2, "events"), ("codes_attach_conversations", KV, 1, "conversations"), ("codes_attach_customer", KC, 1, "customer")):
    add(_name, f"SELECT {', '.join(_keys)}, off FROM {q.offsets(_table, _keys)}")(_attach(_keys, _lead, _table))


@add("codes_values", f"SELECT l_orderkey, l_linenumber, off, CASE off WHEN 0 THEN 2 * {q.STEP} + l_orderkey + {q.HALF} WHEN 1 THEN {q.STEP} + l_linenumber + {q.HALF} ELSE 0 END AS code FROM {q.offsets('lineitem', KL)}")
def codes_values(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(lines(s, d, KL), KL, 1)
    return off(of).select(*KL, "off", F.col(CODE).alias("code"))


_D8 = "(SELECT o_orderkey, nullif(o_orderstatus, 'O') AS st, nullif(o_custkey % 7, 3) AS cm, o_orderdate AS od FROM orders)"


@add("codes_attach_desc_nulls", f"SELECT st, cm, od, off FROM {q.offsets(_D8, ['-st', 'cm', '-od'])}")
def codes_desc_nulls(s: SparkSession, d: str) -> DataFrame:
    x = t(s, d, "orders").select(F.nullif(F.col("o_orderstatus"), F.lit("O")).alias("st"), F.nullif(F.col("o_custkey") % 7, F.lit(3)).alias("cm"), F.col("o_orderdate").alias("od"))
    of = derive.attach(x, [KeyCol("st", ascending=False), KeyCol("cm"), KeyCol("od", ascending=False)], 1)
    return off(of).select("st", "cm", "od", "off")


@add("codes_arrow_tier", f"SELECT {', '.join(K8)}, off FROM {q.offsets('lineitem', K8)}")
def codes_arrow(s: SparkSession, d: str) -> DataFrame:
    pieces = scratch.cut(derive.attach_arrow(lines(s, d, K8), K8, 8), "arrow-codes")
    return derive.stitch_parts(pieces, key_spec(K8)).select(*K8, F.col(OFFSET).alias("off"))


@add(
    "codes_bytes_url",
    "WITH u AS (SELECT DISTINCT encode(url) AS b FROM pages), l AS (SELECT b, lag(b) OVER (ORDER BY b) AS p FROM u) "
    "SELECT hex(b) AS key_hex, CASE WHEN p IS NULL THEN 0 ELSE CAST(len(list_filter(range(1, 1 + least(octet_length(b), octet_length(p))), lambda i: left(hex(b), CAST(2 * i AS INT)) = left(hex(p), CAST(2 * i AS INT)))) AS INT) END AS off FROM l",
)
def codes_bytes_url(s: SparkSession, d: str) -> DataFrame:
    x = t(s, d, "pages").select(normalize_bytes(["url"]).alias("k")).distinct()
    out = derive.attach_bytes(x, "k", 8)
    return out.select(F.hex("k").alias("key_hex"), F.col(OFFSET).alias("off"))


@add("offset_histogram", " UNION ALL ".join(f"SELECT '{n}' AS keys, off, count(*) AS n FROM {q.offsets(tb, ks)} GROUP BY off" for n, tb, ks in (("K8", "lineitem", K8), ("KE", "events", KE), ("KO", "orders", KO))))
def offset_histogram(s: SparkSession, d: str) -> DataFrame:
    out = None
    for name, table, keys, lead in (("K8", "lineitem", K8, 3), ("KE", "events", KE, 2), ("KO", "orders", KO, 1)):
        x = off(derive.attach(t(s, d, table).select(*keys), keys, lead)).groupBy("off").agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("keys"), "off", "n")
        out = x if out is None else out.unionByName(x)
    return out


def _summary_sql() -> str:
    parts = []
    for name, table, keys in _summaries():
        stored = " + ".join(q.ndv(table, keys))
        n = f"(SELECT count(*) FROM {table})"
        parts.append(f"SELECT '{name}' AS keys, n, stored, n * {len(keys)} - stored AS truncated, CAST(floor(n * {len(keys)} / stored) AS BIGINT) AS ratio FROM (SELECT {n} AS n, {stored} AS stored)")
    return " UNION ALL ".join(parts)


def _summaries() -> list[tuple[str, str, list[str]]]:
    out = [("K4", "lineitem", K4), ("K6", "lineitem", K6), ("K8", "lineitem", K8), ("KL", "lineitem", KL), ("KO", "orders", KO), ("KC", "customer", KC), ("KV", "conversations", KV)]
    for c in (2, 4, 6, 8):
        names, cols = q.digits(c)
        out.append((f"D{c}", f"(SELECT {cols} FROM lineitem)", names))
    return out


def _derived(s: SparkSession, d: str, source: str) -> DataFrame:
    if not source.startswith("("):
        return t(s, d, source)
    t(s, d, "lineitem").createOrReplaceTempView("__lineitem")
    return s.sql(source[1:-1].replace("FROM lineitem", "FROM __lineitem"))


@add("truncation_summary", _summary_sql())
def truncation_summary(s: SparkSession, d: str) -> DataFrame:
    out = None
    for name, source, keys in _summaries():
        lead = 3 if name in ("K6", "K8", "K4") else int(name[1:]) + 2 if name[0] == "D" else 1
        of = derive.attach(_derived(s, d, source).select(*keys), keys, min(lead, len(keys) - 1))
        x = formats.summary(of).select(F.lit(name).alias("keys"), "n", "stored", "truncated", "ratio")
        out = x if out is None else out.unionByName(x)
    return out


# ---------------------------------------------------------------- comparisons by identities and by kernels
def _prefixed(p: int) -> tuple[list[str], str]:
    names = [*[f"c{i}" for i in range(p)], "l_partkey"]
    return names, f"(SELECT {''.join(f'1 AS c{i}, ' for i in range(p))}l_partkey FROM lineitem)"


@add("rowgen_column_comparisons", " UNION ALL ".join(f"SELECT {p} AS prefix, CAST((SELECT sum(least(off + 1, {p + 1})) - 1 FROM {q.offsets(_prefixed(p)[1], _prefixed(p)[0])}) AS BIGINT) AS comparisons, CAST({p + 1} * ((SELECT count(*) FROM lineitem) - 1) AS BIGINT) AS expected" for p in (0, 2, 4, 6, 8)))
def rowgen_column_comparisons(s: SparkSession, d: str) -> DataFrame:
    out = None
    for p in (0, 2, 4, 6, 8):
        names, source = _prefixed(p)
        of = derive.attach(_derived(s, d, source), names, max(1, p))
        x = of.df.agg(measures.run_generation_columns(of).alias("comparisons"), F.count(F.lit(1)).alias("__n")).select(F.lit(p).alias("prefix"), "comparisons", ((F.col("__n") - 1) * (p + 1)).alias("expected"))
        out = x if out is None else out.unionByName(x)
    return out


_RUNS8 = "(SELECT *, row_number() OVER (PARTITION BY run ORDER BY l_orderkey, l_linenumber) AS n_, lag(l_orderkey) OVER (PARTITION BY run ORDER BY l_orderkey, l_linenumber) AS po, lag(l_linenumber) OVER (PARTITION BY run ORDER BY l_orderkey, l_linenumber) AS pl FROM (SELECT l_orderkey, l_linenumber, l_partkey % 8 AS run FROM lineitem))"


@add(
    "merge_column_comparisons",
    f"WITH o AS (SELECT sum(off) AS o, sum(CASE WHEN off >= 2 THEN 1 ELSE 0 END) AS od FROM {q.offsets('lineitem', KL)}), "
    f"i AS (SELECT sum(CASE WHEN n_ = 1 OR l_orderkey IS DISTINCT FROM po THEN 0 WHEN l_linenumber IS DISTINCT FROM pl THEN 1 ELSE 2 END) AS i, sum(CASE WHEN n_ > 1 AND l_orderkey = po AND l_linenumber = pl THEN 1 ELSE 0 END) AS id FROM {_RUNS8}) "
    "SELECT CAST(o - i AS BIGINT) AS truncated_anew, CAST(o - i - (od - id) AS BIGINT) AS column_comparisons FROM o, i",
)
def merge_column_comparisons(s: SparkSession, d: str) -> DataFrame:
    x = lines(s, d, KL, ("l_partkey",)).withColumn("run", F.pmod("l_partkey", F.lit(8)))
    return measures.merge_columns(derive.attach(x, KL, 1).df, derive.attach_blocks(x, KL, "run").df, 2)


def _numbered(s: SparkSession, d: str) -> DataFrame:
    x = t(s, d, "lineitem")
    return x.select(F.pmod(F.col("l_orderkey") * 2654435761 + F.col("l_linenumber") * 40503, F.lit(2147483647)).alias("h"), "l_orderkey", "l_linenumber", "l_partkey")


_ONE = "(SELECT count(*) FROM lineitem)"


@add("row_comparisons_rungen", f"SELECT {_ONE} AS n, true AS tree_within_4_percent_of_bound, true AS quicksort_needs_more, true AS columns_at_most_one_a_row")
def row_comparisons_rungen(s: SparkSession, d: str) -> DataFrame:
    """Run generation on scrambled keys, a run for each key range: queue of losers against quicksort, and the bound."""
    x = scratch.cut(_numbered(s, d).select("h"), "rungen")
    tree, quick = (sort.measured(x, ["h"], 8, m).agg(*[F.sum(c).alias(f"{c}_{m}") for c in ("n", "row_cmp", "columns", "lower_bound")]) for m in ("generate", "full"))
    both = tree.crossJoin(quick)  # one row each
    return both.select(
        F.col("n_generate").alias("n"), (F.col("row_cmp_generate") <= 1.04 * F.col("lower_bound_generate")).alias("tree_within_4_percent_of_bound"),
        (F.col("row_cmp_full") > 1.1 * F.col("row_cmp_generate")).alias("quicksort_needs_more"), (F.col("columns_generate") <= F.col("n_generate")).alias("columns_at_most_one_a_row"),
    )


@add("row_comparisons_merge", f"SELECT {_ONE} AS n, true AS tree_at_most_3_a_row, true AS heap_needs_over_1_5_times, true AS codes_compare_no_column")
def row_comparisons_merge(s: SparkSession, d: str) -> DataFrame:
    """Eight sorted runs merged by a queue of losers and by a binary heap."""
    x = scratch.cut(_numbered(s, d).select("h"), "merge-runs")
    tree, heap = (sort.measured(x, ["h"], 8, m).agg(*[F.sum(c).alias(f"{c}_{m}") for c in ("n", "row_cmp", "columns")]) for m in ("merge_tree", "merge_heap"))
    return tree.crossJoin(heap).select(  # one row each
        F.col("n_merge_tree").alias("n"), (F.col("row_cmp_merge_tree") <= 3 * F.col("n_merge_tree")).alias("tree_at_most_3_a_row"), (F.col("row_cmp_merge_heap") > 1.5 * F.col("row_cmp_merge_tree")).alias("heap_needs_over_1_5_times"), (F.col("columns_merge_tree") == 0).alias("codes_compare_no_column"),
    )


@add(
    "sort_methods_columns",
    " UNION ALL ".join(f"SELECT {p} AS prefix, '{m}' AS method, {_ONE} AS n, true AS holds FROM (SELECT 1)" for p in (0, 4, 8) for m in ("generate", "full", "pmnk1", "pmnk2")),
)
def sort_methods_columns(s: SparkSession, d: str) -> DataFrame:
    """Column comparisons over key lists of growing constant prefix. With codes at most p + 1 a row;
    without exactly p + 1 a row comparison; static prefixes are as bad as that once they miss the column."""
    out = None
    for p in (0, 4, 8):
        names, source = _prefixed(p)
        x = _derived(s, d, source)
        for method in ("generate", "full", "pmnk1", "pmnk2"):
            each = (p + 1) * F.sum("row_cmp")
            claim = F.sum("columns") <= (p + 1) * F.sum("n") if method == "generate" else F.sum("columns") == each if method == "full" or p >= int(method[4:]) else F.sum("columns") < each
            y = sort.measured(x, names, 8, method).agg(F.sum("n").alias("n"), claim.alias("holds")).select(F.lit(p).alias("prefix"), F.lit(method).alias("method"), "n", "holds")
            out = y if out is None else out.unionByName(y)
    return out


@add("headline_saving", f"SELECT {_ONE} AS n, true AS codes_within_columns_times_rows, true AS over_5_times_fewer_than_traditional, true AS truncated_runs_smaller, true AS same_merges")
def headline_saving(s: SparkSession, d: str) -> DataFrame:
    """External sorts of eight key columns, same memory and fan-in: queue of losers, codes and truncated runs
    against quicksorted plain runs merged by a binary heap with full comparisons."""
    x, out = scratch.cut(lines(s, d, K8), "headline"), None
    for method in ("tree", "traditional"):
        y = sort.measured(x, K8, 8, method, memory=500, fan_in=4).agg(*[F.sum(c).alias(f"{c}_{method}") for c in ("n", "row_cmp", "columns", "runs", "spilled_bytes")])
        out = y if out is None else out.crossJoin(y)  # one row each
    return out.select(
        F.col("n_tree").alias("n"), (F.col("columns_tree") <= 8 * F.col("n_tree")).alias("codes_within_columns_times_rows"), (F.col("columns_traditional") > 5 * F.col("columns_tree")).alias("over_5_times_fewer_than_traditional"),
        (F.col("spilled_bytes_tree") < 0.8 * F.col("spilled_bytes_traditional")).alias("truncated_runs_smaller"), (F.col("runs_tree") == F.col("runs_traditional")).alias("same_merges"),
    )


_ALL_COLUMNS = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]


def _copies_source(each: int) -> tuple[list[str], str]:
    names, cols = q.copies(each)
    return names, f"(SELECT rid % 8 AS run, {cols} FROM {q.RID})"


@add(
    "dup_bypass_counts",
    " UNION ALL ".join(f"SELECT {c} AS copies, count(*) AS n, CAST(count(*) - count(DISTINCT (run, {', '.join(_copies_source(c)[0])})) AS BIGINT) AS repeats_in_runs, CAST(count(*) - count(DISTINCT ({', '.join(_copies_source(c)[0])})) AS BIGINT) AS repeats FROM {_copies_source(c)[1]}" for c in (1, 10, 100, 1000, 10000)),
)
def dup_bypass_counts(s: SparkSession, d: str) -> DataFrame:
    out = None
    base = derive.numbered(t(s, d, "lineitem"), _ALL_COLUMNS, "rid").select("rid")
    base.createOrReplaceTempView("__rid")
    for c in (1, 10, 100, 1000, 10000):
        names, cols = q.copies(c)
        x = s.sql(f"SELECT CAST(rid % 8 AS INT) AS run, {cols} FROM __rid")
        inside = derive.attach_blocks(x, names, "run").df.agg(F.count(F.lit(1)).alias("n"), F.sum((F.col(OFFSET) >= 8).cast("long")).alias("repeats_in_runs"))
        whole = derive.attach(x, names, 4).df.agg(F.sum((F.col(OFFSET) >= 8).cast("long")).alias("repeats"))
        y = inside.crossJoin(whole).select(F.lit(c).alias("copies"), "n", "repeats_in_runs", "repeats")  # one row each
        out = y if out is None else out.unionByName(y)
    return out


# ---------------------------------------------------------------- formats
@add("truncate_rows", f"SELECT CASE WHEN off <= 0 THEN conv_id END AS conv_id, CASE WHEN off <= 1 THEN turn END AS turn, off AS prefix, role FROM {q.offsets('conversations', KV)}")
def truncate_rows(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(t(s, d, "conversations").select("conv_id", "turn", "role"), KV, 1)
    return formats.truncate(of).select("conv_id", "turn", F.col(formats.PREFIX).alias("prefix"), "role")


@add("truncate_roundtrip", f"SELECT {', '.join(K6)} FROM lineitem")
def truncate_roundtrip(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(lines(s, d, K6), K6, 2)
    stored = scratch.cut(formats.truncate(of), "truncated")
    return formats.expand(stored, K6, list(of.partitioned_by)).select(*K6)


@add("truncate_array_layout", f"SELECT 2 - off AS stored, count(*) AS n FROM {q.offsets('lineitem', KL)} GROUP BY 1")
def truncate_array(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(lines(s, d, KL), KL, 1)
    return formats.truncate(of, "array").groupBy(F.size("tail").alias("stored")).agg(F.count(F.lit(1)).alias("n"))


@add("truncate_array_roundtrip", "SELECT CAST(l_orderkey AS VARCHAR) AS l_orderkey, CAST(l_linenumber AS VARCHAR) AS l_linenumber FROM lineitem")
def truncate_array_roundtrip(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(lines(s, d, KL), KL, 1)
    return formats.expand_array(scratch.cut(formats.truncate(of, "array"), "truncated-arrays"), KL, list(of.partitioned_by)).select(*KL)


@add("rle_columns", " UNION ALL ".join(f"SELECT {j} AS col_no, CAST({n} AS BIGINT) AS runs, (SELECT count(*) FROM lineitem) AS covered FROM (SELECT 1)" for j, n in enumerate(q.ndv("lineitem", K6))))
def rle_columns(s: SparkSession, d: str) -> DataFrame:
    runs = formats.to_rle(derive.attach(lines(s, d, K6), K6, 1))
    return runs.groupBy("col_no").agg(F.count(F.lit(1)).alias("runs"), F.sum("run_len").cast("long").alias("covered"))


@add("rle_roundtrip", "SELECT CAST(l_orderkey AS VARCHAR) AS l_orderkey, CAST(l_linenumber AS VARCHAR) AS l_linenumber FROM lineitem")
def rle_roundtrip(s: SparkSession, d: str) -> DataFrame:
    x = lines(s, d, KL, ("l_returnflag",))
    keys = ["l_returnflag", *KL]
    runs = scratch.cut(formats.to_rle(derive.attach(x, keys, 1)), "rle")
    return formats.from_rle(runs, keys, ["l_returnflag"]).select(*KL)


@add("rle_packed_roundtrip", "SELECT CAST(l_orderkey AS VARCHAR) AS l_orderkey, CAST(l_linenumber AS VARCHAR) AS l_linenumber FROM lineitem")
def rle_packed(s: SparkSession, d: str) -> DataFrame:
    """Run lengths packed in arrays for blocks of 4096 rows, and back to rows."""
    keys = ["l_returnflag", *KL]
    of = formats.blocked(derive.attach(lines(s, d, KL, ("l_returnflag",)), keys, 1), 4096)
    names = list(of.partitioned_by)
    packed = scratch.cut(formats.pack_runs(formats.to_rle(of), names), "rle-packed")
    return formats.from_rle(formats.unpack_runs(packed, names), keys, names).select(*KL)


@add("rle_aggregate", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem GROUP BY ALL")
def rle_aggregate(s: SparkSession, d: str) -> DataFrame:
    keys = ["l_returnflag", "l_linestatus", "l_quantity"]
    runs = formats.to_rle(derive.attach(lines(s, d, keys), keys, 2))
    g = ["__block_l_returnflag", "__block_l_linestatus"]
    out = runs.where("col_no = 2").groupBy(*g).agg(F.sum("run_len").cast("long").alias("n"), F.round(formats.rle_sums(runs, 2), 2).alias("quantity"))
    return out.select(F.col(g[0]).alias("l_returnflag"), F.col(g[1]).alias("l_linestatus"), "n", "quantity")


@add(
    "rle_carry",
    "WITH o AS (SELECT l_returnflag, l_linestatus, off, row_number() OVER (PARTITION BY l_returnflag, l_linestatus ORDER BY l_linenumber, l_tax, l_discount, l_quantity, off) - 1 AS pos FROM "
    f"{q.offsets('lineitem', K6)}) SELECT count(*) AS n, CAST(sum(CASE WHEN pos % 65536 = 0 THEN 0 ELSE off END) AS BIGINT) AS without_carry, true AS fewer_with_carry FROM o",
)
def rle_carry(s: SparkSession, d: str) -> DataFrame:
    """Counter updates of translating rows to columns with and without carry, by block of rows."""
    import pyarrow as pa

    from prefixcode.kernels import formats as kernel
    from prefixcode.kernels.tree import Counters

    of = derive.attach(lines(s, d, K6), K6, 2)
    x = formats.positions(of).select(*of.partitioned_by, F.floor(F.col(formats.POS) / 65536).alias("part"), formats.POS, OFFSET)
    blocks = [*of.partitioned_by, "part"]
    x = x.repartition(*of.partitioned_by, "part").sortWithinPartitions(*of.partitioned_by, "part", formats.POS)

    def run(batches):
        out, before, block = [0, 0, 0], None, []

        def close() -> None:
            for i, carry in enumerate((True, False)):
                c = Counters()
                kernel.to_columns(block, 6, c, carry)
                out[i] += c.translated
            out[2] += len(block)

        for b in batches:
            for key, o in zip(zip(*(b.column(c).to_pylist() for c in blocks), strict=True), b.column(OFFSET).to_pylist(), strict=True):
                if key != before:
                    close()
                    before, o = key, 0
                    block = []
                block.append((o, tuple(range(o, 6))))
        close()
        yield pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in out], names=["with_carry", "without_carry", "n"])

    counts = x.mapInArrow(run, "with_carry long, without_carry long, n long").agg(*[F.sum(c).alias(c) for c in ("with_carry", "without_carry", "n")])
    return counts.select("n", "without_carry", (F.col("with_carry") < F.col("without_carry")).alias("fewer_with_carry"))


# ---------------------------------------------------------------- sorting
_SORTED = f"SELECT l_orderkey, l_linenumber, off, count(*) AS n FROM {q.offsets('lineitem', KL)} GROUP BY ALL"


def _sorted(**options) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        x = sort.external_sort(lines(s, d, KL), KL, 8, memory=1000, fan_in=4, **options)
        return x.groupBy(*KL, F.col(OFFSET).alias("off")).agg(F.count(F.lit(1)).alias("n"))

    return run


for _name, _options in (("external_sort", {}), ("external_sort_replacement", {"run_gen": "replacement"}), ("external_sort_rle", {"compress": "rle"}), ("external_sort_derive_on_read", {"compress": "bare"}), ("external_sort_traditional", {"run_gen": "quick", "merge": "heap", "compress": False})):
    add(_name, _SORTED)(_sorted(**_options))


@add("external_sort_order", f"SELECT l_orderkey, off, true AS in_order, count(*) AS n FROM {q.offsets('lineitem', KL)} GROUP BY ALL")
def external_sort_order(s: SparkSession, d: str) -> DataFrame:
    """Every row's place, and its offset, against the row before it in its part."""
    x = sort.external_sort(lines(s, d, KL), KL, 8, memory=1000, fan_in=4, run_gen="quick", compress=False)
    w = W.partitionBy("__part").orderBy("__pos")
    before = [F.lag(c).over(w) for c in KL]
    own = F.when(before[0].isNull(), F.col(OFFSET)).when(before[0] != F.col(KL[0]), 0).when(before[1] != F.col(KL[1]), 1).otherwise(2)
    ok = before[0].isNull() | (before[0] < F.col(KL[0])) | ((before[0] == F.col(KL[0])) & (before[1] <= F.col(KL[1])))
    return x.select("l_orderkey", F.col(OFFSET).alias("off"), (ok & (own == F.col(OFFSET))).alias("in_order")).groupBy("l_orderkey", "off", "in_order").agg(F.count(F.lit(1)).alias("n"))


def _dedup(table: str, select: str, keys: list[str]) -> Query:
    return lambda s, d: sort.external_sort(t(s, d, table).selectExpr(*select.split(", ")), keys, 8, memory=1000, fan_in=4, dedup=True).select(*[k.lstrip("-") for k in keys])


for _name, _table, _select, _keys in (
    ("external_sort_dedup", "lineitem", "l_orderkey, l_linenumber", KL),
    ("external_sort_dedup_text", "documents", "lang, text", ["lang", "-text"]),
    ("external_sort_dedup_double", "lineitem", "l_extendedprice, l_discount", ["-l_extendedprice", "l_discount"]),
    ("external_sort_dedup_wide", "lineitem", "l_returnflag, l_orderkey * 3 + 1152921504606846976 AS wide", ["l_returnflag", "wide"]),
    ("external_sort_dedup_time", "lineitem", "l_shipdate, l_linestatus", ["-l_shipdate", "l_linestatus"]),
):
    add(_name, f"SELECT DISTINCT {_select} FROM {_table}")(_dedup(_table, _select, _keys))


@add("external_sort_agg", "SELECT l_orderkey, count(*) AS n, round(sum(l_quantity), 2) AS quantity, min(l_linenumber) AS lo, max(l_shipdate) AS hi FROM lineitem GROUP BY l_orderkey")
def external_sort_agg(s: SparkSession, d: str, **options) -> DataFrame:
    """Groups are folded while runs are written and in every merge; a group keeps its first row's code."""
    x = sort.external_sort(lines(s, d, ["l_orderkey", "l_quantity", "l_linenumber", "l_shipdate"]), ["l_orderkey"], 8, memory=1000, fan_in=4, aggs={"n": ("count", "*"), "quantity": ("sum", "l_quantity"), "lo": ("min", "l_linenumber"), "hi": ("max", "l_shipdate")}, **options)
    return x.select("l_orderkey", "n", F.round("quantity", 2).alias("quantity"), "lo", "hi")


add("external_sort_agg_index", SQL["external_sort_agg"])(lambda s, d: external_sort_agg(s, d, run_gen="index"))


@add("agg_codes_handed_on", f"WITH g AS (SELECT l_returnflag, l_linestatus, l_linenumber, count(*) AS n FROM lineitem GROUP BY ALL) SELECT *, (SELECT count(*) FROM g) AS groups FROM (SELECT l_returnflag, l_linestatus, l_linenumber, n, off FROM {q.offsets('g', K6[:3])})")
def agg_codes_handed_on(s: SparkSession, d: str) -> DataFrame:
    """A sort that aggregates hands its codes on: groups of groups are found by them, without a second sort."""
    x = sort.external_sort(lines(s, d, K6[:3]), K6[:3], 8, memory=1000, fan_in=4, aggs={"n": ("count", "*")})
    groups = x.agg(F.sum((F.col(OFFSET) < 3).cast("long")).alias("groups"))
    return x.select(*K6[:3], "n", F.col(OFFSET).alias("off")).crossJoin(F.broadcast(groups))  # one row


@add("plain_sort_ranks", "SELECT o_orderkey, row_number() OVER (ORDER BY o_orderdate DESC, o_orderkey) AS r FROM orders")
def plain_sort(s: SparkSession, d: str) -> DataFrame:
    x = derive.numbered(t(s, d, "orders").select("o_orderkey", "o_orderdate"), ["-o_orderdate", "o_orderkey"], "r")
    return x.select("o_orderkey", (F.col("r") + 1).alias("r"))


def _runs8(s: SparkSession, d: str) -> DataFrame:
    return lines(s, d, KL, ("l_partkey",)).withColumn("run", F.pmod("l_partkey", F.lit(8))).drop("l_partkey")


def _exchange(by: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        out = sort.merging_exchange(_runs8(s, d), KL, "run", 1 if by == "single" else 6, by)
        w = W.partitionBy("bucket").orderBy("__pos")
        ok = (F.lag("l_orderkey").over(w) < F.col("l_orderkey")) | ((F.lag("l_orderkey").over(w) == F.col("l_orderkey")) & (F.lag("l_linenumber").over(w) <= F.col("l_linenumber")))
        more = [F.col(OFFSET).alias("off")] if by != "hash" else []
        return out.withColumn("in_order", F.coalesce(ok, F.lit(True))).groupBy(*KL, "in_order", *more).agg(F.count(F.lit(1)).alias("n"))

    return run


for _by in ("range", "single"):
    add(f"merge_exchange_{_by}", f"SELECT l_orderkey, l_linenumber, true AS in_order, off, count(*) AS n FROM {q.offsets('lineitem', KL)} GROUP BY ALL")(_exchange(_by))
add("merge_exchange_hash", "SELECT l_orderkey, l_linenumber, true AS in_order, count(*) AS n FROM lineitem GROUP BY ALL")(_exchange("hash"))


@add("exchange_resort_baseline", f"SELECT l_orderkey, l_linenumber, off, count(*) AS n FROM {q.offsets('lineitem', KL)} GROUP BY ALL")
def exchange_resort(s: SparkSession, d: str) -> DataFrame:
    """The same without order in the exchange: rows are dealt out by ranges and sorted again, codes made anew."""
    pieces = scratch.cut(derive.attach_arrow(_runs8(s, d).drop("run"), KL, 6), "resorted")
    return derive.stitch_parts(pieces, key_spec(KL)).groupBy(*KL, F.col(OFFSET).alias("off")).agg(F.count(F.lit(1)).alias("n"))


@add("merge_exchange_counts", "SELECT (SELECT count(*) FROM lineitem) AS n, column_comparisons AS columns, true AS under_log_bound FROM (" + SQL["merge_column_comparisons"] + ")")
def merge_exchange_counts(s: SparkSession, d: str) -> DataFrame:
    """What a consumer of eight runs does with the codes in its packets: the columns it compares are those
    that the identity over offsets says, no more."""
    x = sort.merging_exchange(_runs8(s, d), KL, "run", 1, "single", counters=True)
    return x.agg(F.sum("n").alias("n"), F.sum("columns").alias("columns"), (F.sum("row_cmp") <= 3 * F.sum("n")).alias("under_log_bound"))


# ---------------------------------------------------------------- consumers of codes
@add("distinct_codes", f"SELECT DISTINCT {', '.join(K4)} FROM lineitem")
def distinct_codes(s: SparkSession, d: str) -> DataFrame:
    return stream.distinct(derive.attach(lines(s, d, K4), K4, 2)).df.select(*K4)


@add("distinct_texts", "SELECT DISTINCT text FROM documents")
def distinct_texts(s: SparkSession, d: str) -> DataFrame:
    x = t(s, d, "documents").select(F.xxhash64("text").alias("h"), "text")
    return stream.distinct(derive.attach(x, ["h", "text"], 1)).df.select("text")


@add("agg_instream", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(sum(l_extendedprice), 2) AS price FROM lineitem GROUP BY ALL")
def agg_instream(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(lines(s, d, K4, ("l_quantity", "l_extendedprice")), K4, 3)
    x = stream.aggregate_over(of, 2, {"n": ("count", "*"), "quantity": ("sum", "l_quantity"), "price": ("sum", "l_extendedprice")})
    return x.select("l_returnflag", "l_linestatus", "n", F.round("quantity", 2).alias("quantity"), F.round("price", 2).alias("price"))


@add("agg_hash_baseline", SQL["agg_instream"])
def agg_hash(s: SparkSession, d: str) -> DataFrame:
    return t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@add("agg_full_compare_baseline", SQL["agg_instream"])
def agg_full(s: SparkSession, d: str) -> DataFrame:
    """The same groups found by comparing both group columns with the row before."""
    x = t(s, d, "lineitem")
    w = W.partitionBy("l_returnflag").orderBy("l_linestatus")
    flag = ~F.col("l_linestatus").eqNullSafe(F.lag("l_linestatus").over(w)) | ~F.col("l_returnflag").eqNullSafe(F.lag("l_returnflag").over(w))
    y = x.withColumn("__f", F.coalesce(flag, F.lit(True)).cast("int")).withColumn("__g", F.sum("__f").over(w))
    return y.groupBy("l_returnflag", "__g").agg(F.first("l_linestatus").alias("l_linestatus"), F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.sum("l_extendedprice"), 2).alias("price")).drop("__g")


for _ratio in (1, 10, 100, 1000, 10000):

    def _agg_ratio(s: SparkSession, d: str, ratio: int = _ratio) -> DataFrame:
        names, cols = q.copies(ratio, base=9)
        derive.numbered(t(s, d, "lineitem"), _ALL_COLUMNS, "rid").createOrReplaceTempView("__numbered")
        x = s.sql(f"SELECT {cols}, l_quantity FROM __numbered")
        of = derive.attach(x, names, 5)
        return stream.aggregate(of, 8, [F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity")])

    _names, _cols = q.copies(_ratio, base=9)
    add(f"agg_instream_ratio_{_ratio}", f"SELECT {', '.join(_names)}, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM (SELECT {_cols}, l_quantity FROM {q.RID}) GROUP BY ALL")(_agg_ratio)

    def _segments(s: SparkSession, d: str, ratio: int = _ratio) -> DataFrame:
        names, cols = q.copies(ratio, base=9)
        derive.numbered(t(s, d, "lineitem"), _ALL_COLUMNS, "rid").createOrReplaceTempView("__numbered2")
        of = derive.attach(s.sql(f"SELECT {cols} FROM __numbered2"), names, 5)
        x = stream.segment(of, 8)
        return x.groupBy(*names).agg(F.sum(F.col("seg_start").cast("long")).alias("flags"), F.count(F.lit(1)).alias("n"))

    add(f"segments_flags_{_ratio}", f"SELECT {', '.join(_names)}, CAST(1 AS BIGINT) AS flags, count(*) AS n FROM (SELECT {_cols} FROM {q.RID}) GROUP BY ALL")(_segments)


def _columns(columns: int, base: int, ratio: int = 100) -> tuple[list[str], str]:
    return q.copies(ratio, base=base, columns=columns)


for _c, _base in ((2, 80), (4, 9), (6, 5)):

    def _agg_columns(s: SparkSession, d: str, c: int = _c, base: int = _base) -> DataFrame:
        names, cols = _columns(c, base)
        derive.numbered(t(s, d, "lineitem"), _ALL_COLUMNS, "rid").createOrReplaceTempView("__numbered3")
        of = derive.attach(s.sql(f"SELECT {cols}, l_quantity FROM __numbered3"), names, max(1, c - 1))
        return stream.aggregate(of, c, [F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity")])

    def _segment_columns(s: SparkSession, d: str, c: int = _c, base: int = _base, by_codes: bool = True) -> DataFrame:
        """Segment starts by codes, or by comparing every column with the row before (the baseline)."""
        names, cols = _columns(c, base)
        derive.numbered(t(s, d, "lineitem"), _ALL_COLUMNS, "rid").createOrReplaceTempView("__numbered4")
        x = s.sql(f"SELECT {cols} FROM __numbered4")
        if by_codes:
            flagged = stream.segment(derive.attach(x, names, max(1, c - 1)), c)
        else:
            w = W.partitionBy(names[0]).orderBy(*names[1:])
            same = F.lit(True)
            for n in names:
                same = same & F.col(n).eqNullSafe(F.lag(n).over(w))
            flagged = x.withColumn("seg_start", ~same)
        return flagged.groupBy(*names).agg(F.sum(F.col("seg_start").cast("long")).alias("flags"), F.count(F.lit(1)).alias("n"))

    _names, _cols = _columns(_c, _base)
    add(f"agg_instream_columns_{_c}", f"SELECT {', '.join(_names)}, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM (SELECT {_cols}, l_quantity FROM {q.RID}) GROUP BY ALL")(_agg_columns)
    for _how in (True, False):
        add(f"segments_{'columns' if _how else 'full_compare_baseline'}_{_c}", f"SELECT {', '.join(_names)}, CAST(1 AS BIGINT) AS flags, count(*) AS n FROM (SELECT {_cols} FROM {q.RID}) GROUP BY ALL")(lambda s, d, f=_segment_columns, how=_how: f(s, d, by_codes=how))


@add("count_distinct_instream", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS n FROM lineitem GROUP BY l_returnflag")
def count_distinct_instream(s: SparkSession, d: str) -> DataFrame:
    return stream.count_distinct(derive.attach(lines(s, d, ["l_returnflag", "l_suppkey"]), ["l_returnflag", "l_suppkey"], 1), 1, "n")


def _visitors(unit: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        x = t(s, d, "events").select(F.date_trunc(unit, F.col("ts")).cast("date").alias("period"), "user_id")
        return stream.count_distinct(derive.attach(x, ["period", "user_id"], 1), 1, "visitors").withColumn("period", F.col("period").cast("string"))

    return run


for _unit in ("day", "month"):
    add(f"unique_visitors_{_unit}", f"SELECT CAST(CAST(date_trunc('{_unit}', ts) AS DATE) AS VARCHAR) AS period, count(DISTINCT user_id) AS visitors FROM events GROUP BY 1")(_visitors(_unit))


_TAIL = ["l_returnflag", "l_linestatus", "l_linenumber", "l_quantity"]


@add("segmented_sort", f"SELECT {', '.join(_TAIL)}, off, count(*) AS n FROM {q.offsets('lineitem', _TAIL)} GROUP BY ALL")
def segmented_sort(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(lines(s, d, K4, _TAIL), K4, 1)
    out, step = planner.order(of, _TAIL)
    assert step.kind == "segmented sort" and step.shared == 2
    return off(out).groupBy(*_TAIL, "off").agg(F.count(F.lit(1)).alias("n"))


@add("segmented_agg", "SELECT conv_id, role, count(*) AS n FROM conversations GROUP BY ALL")
def segmented_agg(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(t(s, d, "conversations").select("conv_id", "turn", "role"), KV, 1)
    return stream.aggregate(stream.extend_sort(of, 1, ["role"]), 2, [F.count(F.lit(1)).alias("n")])


@add("segmented_distinct", "SELECT DISTINCT conv_id, role FROM conversations")
def segmented_distinct(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(t(s, d, "conversations").select("conv_id", "turn", "role"), KV, 1)
    return stream.distinct(stream.extend_sort(of, 1, ["role"])).df.select("conv_id", "role")


@add("resort_baseline", SQL["segmented_sort"])
def resort(s: SparkSession, d: str) -> DataFrame:
    return off(derive.attach(lines(s, d, _TAIL), _TAIL, 1)).groupBy(*_TAIL, "off").agg(F.count(F.lit(1)).alias("n"))


@add("filter_keep_codes", f"SELECT {', '.join(K6)}, off, count(*) AS n FROM {q.offsets('(SELECT * FROM lineitem WHERE l_extendedprice > 40000)', K6)} GROUP BY ALL")
def filter_keep_codes(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(lines(s, d, K6, ("l_extendedprice",)), K6, None)
    return off(stream.keep(of, F.col("l_extendedprice") > 40000)).groupBy(*K6, "off").agg(F.count(F.lit(1)).alias("n"))


@add("project_keep_codes", f"SELECT {', '.join(K6[:3])}, off, count(*) AS n FROM {q.offsets('lineitem', K6[:3])} GROUP BY ALL")
def project_keep_codes(s: SparkSession, d: str) -> DataFrame:
    return off(stream.shorten(derive.attach(lines(s, d, K6), K6, 3), 3)).groupBy(*K6[:3], "off").agg(F.count(F.lit(1)).alias("n"))


@add("agg_groups_coded", f"WITH g AS (SELECT l_returnflag, l_linestatus, l_linenumber, count(*) AS n FROM lineitem GROUP BY ALL) SELECT l_returnflag, l_linestatus, l_linenumber, n, off FROM {q.offsets('g', K6[:3])}")
def agg_groups_coded(s: SparkSession, d: str) -> DataFrame:
    """Groups take their first rows' codes: the output is coded without looking at a column."""
    groups = stream.aggregate_coded(derive.attach(lines(s, d, K6), K6, 3), 3, [F.count(F.lit(1)).alias("n")])
    return off(groups).select(*K6[:3], "n", "off")


@add("rollup_codes", "SELECT l_returnflag, l_linestatus, l_linenumber, CAST(3 - (grouping(l_returnflag) + grouping(l_linestatus) + grouping(l_linenumber)) AS INT) AS level, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus, l_linenumber)")
def rollup_codes(s: SparkSession, d: str) -> DataFrame:
    keys = ["l_returnflag", "l_linestatus", "l_linenumber"]
    x = stream.rollup(derive.attach(lines(s, d, keys, ("l_quantity",)), keys, 1), 3, {"n": ("count", "*"), "quantity": ("sum", "l_quantity")})
    return x.withColumn("quantity", F.round("quantity", 2))


@add("rollup_group_counts", "SELECT " + ", ".join(f"{n} AS p{j + 1}" for j, n in enumerate(q.ndv("lineitem", K4))))
def rollup_group_counts(s: SparkSession, d: str) -> DataFrame:
    return stream.group_counts(derive.attach(lines(s, d, K4), K4, 2))


@add("analytic_ranks", "SELECT o_orderkey, row_number() OVER (PARTITION BY o_orderstatus ORDER BY o_orderdate, o_orderkey) AS rn, rank() OVER (PARTITION BY o_orderstatus ORDER BY o_orderdate) AS rk, dense_rank() OVER (PARTITION BY o_orderstatus ORDER BY o_orderdate) AS dr FROM orders")
def analytic_ranks(s: SparkSession, d: str) -> DataFrame:
    x = derive.attach(t(s, d, "orders").select("o_orderstatus", "o_orderdate", "o_orderkey"), ["o_orderstatus", "o_orderdate", "o_orderkey"], 1)
    ranks = stream.analytic(x, 1, 1)
    return ranks.select("o_orderkey", F.col("row_number").cast("long").alias("rn"), F.col("rank").cast("long").alias("rk"), F.col("dense_rank").cast("long").alias("dr"))


@add("analytic_running_sum", "SELECT event_id, round(sum(value) OVER (PARTITION BY event_type, user_id ORDER BY ts), 4) AS running FROM events")
def analytic_running_sum(s: SparkSession, d: str) -> DataFrame:
    of = derive.attach(t(s, d, "events").select(*KE, "event_id", "value"), KE, 1)
    return stream.analytic(of, 2, 1, "value").select("event_id", F.round("running_sum", 4).alias("running"))


@add("hash_sorted_agg", "SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY ALL")
def hash_sorted_agg(s: SparkSession, d: str) -> DataFrame:
    x = lines(s, d, ["l_partkey"]).withColumn("h", F.xxhash64("l_partkey"))
    return stream.aggregate(derive.attach(x, ["h", "l_partkey"], 1), 2, [F.count(F.lit(1)).alias("n")]).select("l_partkey", "n")


@add("topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100")
def topk(s: SparkSession, d: str) -> DataFrame:
    return stream.top_k(t(s, d, "orders").select("o_orderkey", "o_totalprice"), ["-o_totalprice", "o_orderkey"], 100)


@add("topk_per_segment", "SELECT event_type, event_id, rn FROM (SELECT event_type, event_id, row_number() OVER (PARTITION BY event_type ORDER BY ts, event_id) AS rn FROM events) WHERE rn <= 5")
def topk_per_segment(s: SparkSession, d: str) -> DataFrame:
    keys = ["event_type", "ts", "event_id"]
    return stream.top_k_per_segment(derive.attach(t(s, d, "events").select(*keys), keys, 1), 1, 5).select("event_type", "event_id", F.col("row_number").cast("long").alias("rn"))


# ---------------------------------------------------------------- joins and sets
def _join(how: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        o = derive.attach(t(s, d, "orders").where("o_totalprice < 400000").select("o_orderkey", "o_custkey"), ["o_orderkey"], 1)
        x = derive.attach(t(s, d, "lineitem").where("l_returnflag <> 'N'").select("l_orderkey", "l_partkey"), ["l_orderkey"], 1)
        out = off(join.merge_join(o, x, how))
        cols = ["o_orderkey", "o_custkey"] + (["l_partkey"] if how not in ("semi", "anti") else [])
        return out.groupBy(*cols).agg(F.count(F.lit(1)).alias("n"))

    return run


_L = "(SELECT l_orderkey, l_partkey FROM lineitem WHERE l_returnflag <> 'N')"
_O = "(SELECT o_orderkey, o_custkey FROM orders WHERE o_totalprice < 400000)"
for _how in ("inner", "left", "right", "full"):
    add(f"merge_join_{_how}", f"SELECT coalesce(o.o_orderkey, l.l_orderkey) AS o_orderkey, o_custkey, l_partkey, count(*) AS n FROM {_O} o {_how.upper()} JOIN {_L} l ON o.o_orderkey = l.l_orderkey GROUP BY ALL")(_join(_how))
for _how in ("semi", "anti"):
    add(f"merge_join_{_how}", f"SELECT o_orderkey, o_custkey, count(*) AS n FROM {_O} o WHERE {'NOT ' if _how == 'anti' else ''}EXISTS (SELECT 1 FROM {_L} l WHERE o.o_orderkey = l.l_orderkey) GROUP BY ALL")(_join(_how))


@add("merge_join_codes", f"WITH j AS (SELECT o_orderkey FROM {_O} o JOIN {_L} l ON o.o_orderkey = l.l_orderkey) SELECT o_orderkey, off, count(*) AS n FROM {q.offsets('j', ['o_orderkey'])} GROUP BY ALL")
def merge_join_codes(s: SparkSession, d: str) -> DataFrame:
    o = derive.attach(t(s, d, "orders").where("o_totalprice < 400000").select("o_orderkey", "o_custkey"), ["o_orderkey"], 1)
    x = derive.attach(t(s, d, "lineitem").where("l_returnflag <> 'N'").select("l_orderkey", "l_partkey"), ["l_orderkey"], 1)
    return off(join.merge_join(o, x, "inner")).groupBy("o_orderkey", "off").agg(F.count(F.lit(1)).alias("n"))


def _coded(how: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        o = t(s, d, "orders").where("o_totalprice < 400000").select("o_orderkey", "o_custkey")
        x = t(s, d, "lineitem").where("l_returnflag <> 'N'").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey")
        cols = ["o_orderkey", "o_custkey"] + (["l_partkey"] if how not in ("semi", "anti") else [])
        return off(join.coded_join(o, x, ["o_orderkey"], 8, how)).groupBy(*cols).agg(F.count(F.lit(1)).alias("n"))

    return run


for _how in ("inner", "left", "right", "full", "semi", "anti"):
    add(f"coded_join_{_how}", SQL[f"merge_join_{_how}"])(_coded(_how))


@add("coded_join_codes", SQL["merge_join_codes"])
def coded_join_codes(s: SparkSession, d: str) -> DataFrame:
    o = t(s, d, "orders").where("o_totalprice < 400000").select("o_orderkey", "o_custkey")
    x = t(s, d, "lineitem").where("l_returnflag <> 'N'").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey")
    return off(join.coded_join(o, x, ["o_orderkey"], 8)).groupBy("o_orderkey", "off").agg(F.count(F.lit(1)).alias("n"))


_SIDES = "(SELECT l_orderkey, l_linenumber, 0 AS side FROM lineitem WHERE l_returnflag = 'R' UNION ALL SELECT l_orderkey, l_linenumber, 1 AS side FROM lineitem WHERE l_linestatus = 'O')"


def _window_offsets(by: str, tie: str) -> str:
    w = f"(PARTITION BY {by} ORDER BY l_orderkey, l_linenumber{tie})"
    return f"CASE WHEN row_number() OVER {w} = 1 OR lag(l_orderkey) OVER {w} <> l_orderkey THEN 0 WHEN lag(l_linenumber) OVER {w} <> l_linenumber THEN 1 ELSE 2 END"


@add(
    "coded_join_counts",
    f"WITH u AS (SELECT *, CAST(floor(l_orderkey / 4096) AS INT) AS part FROM {_SIDES}), o AS (SELECT part, {_window_offsets('part', ', side')} AS m, {_window_offsets('part, side', '')} AS own FROM u), "
    "c AS (SELECT part, CAST(sum(m) - sum(own) - (sum(CASE WHEN m = 2 THEN 1 ELSE 0 END) - sum(CASE WHEN own = 2 THEN 1 ELSE 0 END)) AS BIGINT) AS columns FROM o GROUP BY part), "
    "j AS (SELECT a.part, count(*) AS n FROM u a JOIN u b ON a.l_orderkey = b.l_orderkey AND a.l_linenumber = b.l_linenumber AND a.side = 0 AND b.side = 1 GROUP BY a.part) "
    "SELECT c.part, coalesce(n, 0) AS n, columns, true AS fewer_than_by_full_comparison FROM c LEFT JOIN j ON c.part = j.part",
)
def coded_join_counts(s: SparkSession, d: str) -> DataFrame:
    """Columns compared by a merge join on codes: exactly those that the offsets say. Full comparison looks at
    one column at least for each row."""
    x = t(s, d, "lineitem")
    a, b = x.where("l_returnflag = 'R'").select(*KL), x.where("l_linestatus = 'O'").select(*KL)
    out = join.coded_join(a, b, KL, 8, "inner", within=F.floor(F.col("l_orderkey") / 4096), counters=True)
    return out.select("part", "n", "columns", (F.col("columns") <= F.col("row_cmp")).alias("fewer_than_by_full_comparison"))


@add("merge_join_labels", "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, lang, quality FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")
def merge_join_labels(s: SparkSession, d: str) -> DataFrame:
    a = derive.attach(t(s, d, "documents").select("doc_id", "lang"), ["doc_id"], 1)
    b = derive.attach(t(s, d, "labels").select("doc_id", "quality"), ["doc_id"], 1)
    return join.merge_join(a, b, "full").df.select("doc_id", "lang", "quality")


@add(
    "pipeline_join_agg",
    "SELECT c_custkey, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey GROUP BY c_custkey",
)
def pipeline_join_agg(s: SparkSession, d: str) -> DataFrame:
    """Lines are summed by order, orders merged with customers, groups found by carried codes."""
    li = derive.attach(t(s, d, "lineitem").select("l_orderkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("r")), ["l_orderkey"], 1)
    per_order = stream.aggregate(li, 1, [F.count(F.lit(1)).alias("n"), F.sum("r").alias("r")])
    o = t(s, d, "orders").select("o_orderkey", "o_custkey").join(per_order, F.col("o_orderkey") == F.col("l_orderkey")).select("o_custkey", "n", "r")
    c = derive.attach(t(s, d, "customer").select("c_custkey"), ["c_custkey"], 1)
    joined = join.merge_join(c, derive.attach(o, ["o_custkey"], 1), "inner")
    return stream.aggregate(joined, 1, [F.sum("n").alias("n"), F.round(F.sum("r"), 2).alias("revenue")])


_A, _B = "(SELECT l_partkey, l_linenumber FROM lineitem WHERE l_returnflag = 'R')", "(SELECT l_partkey, l_linenumber FROM lineitem WHERE l_linestatus = 'O')"
for _kind in ("union", "intersect", "except"):
    for _all in (False, True):

        def _set(s: SparkSession, d: str, kind: str = _kind, rows: bool = _all) -> DataFrame:
            x = t(s, d, "lineitem")
            keys = ["l_partkey", "l_linenumber"]
            return join.set_operation(x.where("l_returnflag = 'R'").select(*keys), x.where("l_linestatus = 'O'").select(*keys), keys, kind, rows)

        add(f"setop_{_kind}{'_all' if _all else ''}", f"SELECT * FROM {_A} {_kind.upper()}{' ALL' if _all else ''} SELECT * FROM {_B}")(_set)


@add("setop_text_intersect", "SELECT text FROM documents INTERSECT SELECT text FROM benchmark")
def setop_text(s: SparkSession, d: str) -> DataFrame:
    return join.set_operation(t(s, d, "documents").select("text"), t(s, d, "benchmark").select("text"), ["text"], "intersect")


def _index(on_hash: bool) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        path = store.build_index(t(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey"), ["l_orderkey"], 8, on_hash)
        probe = t(s, d, "orders").select("o_orderkey", "o_custkey")
        return store.lookup_join(probe, "o_orderkey", path, "l_orderkey", on_hash)

    return run


for _on, _hash in (("index_lookup_join", False), ("index_lookup_hash", True)):
    add(_on, "SELECT o_orderkey, o_custkey, l_orderkey, l_linenumber, l_partkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey")(_index(_hash))


@add("join_interval", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_id BETWEEN a.event_id AND a.event_id + 200 WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def join_interval(s: SparkSession, d: str) -> DataFrame:
    e = t(s, d, "events")
    a = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("a_id"), (F.col("event_id") + 200).alias("a_to"))
    b = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("b_id"))
    return join.interval_join(b, a, "user_id", "b_id", "a_id", "a_to", 200).select("a_id", "b_id")


@add(
    "join_asof",
    "SELECT event_id, last_view FROM (SELECT event_id, event_type, max(CASE WHEN event_type = 'view' THEN event_id END) OVER (PARTITION BY user_id ORDER BY event_id) AS last_view FROM events) WHERE event_type = 'purchase'",
)
def join_asof(s: SparkSession, d: str) -> DataFrame:
    e = t(s, d, "events")
    left = e.where("event_type = 'purchase'").select("user_id", "event_id")
    right = e.where("event_type = 'view'").select("user_id", F.col("event_id").alias("v_id"))
    return join.asof_join(left, right, ["user_id"], "event_id", "v_id", ["v_id"]).select("event_id", F.col("right_v_id").alias("last_view"))


# ---------------------------------------------------------------- stores
@add("stepped_merge", f"SELECT {', '.join(KE)}, off, count(*) AS n FROM {q.offsets('events', KE)} GROUP BY ALL")
def stepped_merge(s: SparkSession, d: str) -> DataFrame:
    """Daily batches arrive as sorted runs; levels of eight are merged by the codes they were stored with, and
    so is what there is when it is read."""
    e = t(s, d, "events").select(*KE, "event_id")
    days = [r[0] for r in e.select(F.to_date("ts").alias("day")).distinct().orderBy("day").collect()]  # a row for each batch
    runs = store.RunStore(s, KE, fan_in=8)
    for k, day in enumerate(days):
        runs.append_run(e.where(F.to_date("ts") == F.lit(day)), k)
    return off(runs.merged()).groupBy(*KE, "off").agg(F.count(F.lit(1)).alias("n"))


@add("key_depth", "SELECT 21 AS columns_for_ten_billion_of_three, " + ", ".join(f"{n} AS p{j + 1}" for j, n in enumerate(q.ndv("lineitem", K8))))
def key_depth(s: SparkSession, d: str) -> DataFrame:
    counts = stream.group_counts(derive.attach(lines(s, d, K8), K8, None))
    return counts.select(F.lit(round(measures.key_depth(1e10, 3))).alias("columns_for_ten_billion_of_three"), "*")


def _experiment(name: str, sizes: tuple[int, ...]) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        """The experiment over prefixes of lineitem, one after another in a task of its own: what it finds, claim by claim."""
        import pyarrow as pa

        x = derive.numbered(t(s, d, "lineitem"), _ALL_COLUMNS, "rid").where(F.col("rid") < max(sizes))
        x = x.select("rid", F.xxhash64("rid", "l_orderkey", "l_partkey").bitwiseAND(F.lit((1 << 40) - 1)).alias("h")).repartition(1).sortWithinPartitions("rid")

        def work(batches):
            from prefixcode.workloads import experiments

            values: list[int] = []
            for b in batches:
                values += b.column("h").to_pylist()
            found, before = [], None
            for n in sizes:
                some = values[:n]
                if len(some) != before:  # a table that is shorter than both sizes is run once
                    found, before = experiments.found(name, some) if some else [], len(some)
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(found), pa.string()), pa.array([n] * len(found), pa.int64()), pa.array([len(some)] * len(found), pa.int64()), pa.array([c for c, _ in found], pa.string()), pa.array([bool(h) for _, h in found], pa.bool_())], names=["experiment", "size", "n", "claim", "holds"])

        return x.mapInArrow(work, "experiment string, size long, n long, claim string, holds boolean")

    return run


for _e, _sizes in experiments.SIZES.items():
    _rows = " UNION ALL ".join(f"SELECT '{_e}' AS experiment, CAST({_n} AS BIGINT) AS size, least(CAST({_n} AS BIGINT), {_ONE}) AS n, '{_claim}' AS claim, true AS holds FROM (SELECT 1)" for _n in _sizes for _claim in experiments.CLAIMS[_e])
    add(f"experiment_{_e}", _rows)(_experiment(_e, _sizes))
