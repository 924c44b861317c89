"""Plans, order, nulls and edge cases of the operators on coded rows."""

from collections import Counter
from datetime import date, datetime
from decimal import Decimal

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from prefixcode.functions import codes
from prefixcode.functions.keys import KeyCol, key_spec, pack_bits
from prefixcode.operators import derive, join, sort, stream
from prefixcode.plans import planner
from prefixcode.plans.frame import CODE, OFFSET, OrderedFrame
from prefixcode.sources import formats, store
from prefixcode.sources.runreader import PrefixRuns


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.fixture(scope="module")
def items(spark, sf):
    return spark.read.parquet(f"{sf}/lineitem.parquet")


def test_deriving_takes_one_exchange(spark, items):
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        keys = ["l_returnflag", "l_linestatus", "l_linenumber"]
        of = derive.attach(items.select(*keys, "l_quantity"), keys, 1)
        assert plan(of.df).count("Exchange") == 1
        assert plan(stream.distinct(of).df).count("Exchange") == 1
        groups = stream.aggregate(of, 2, [F.sum("l_quantity").alias("q")])
        assert plan(groups).count("Exchange") == 1
        counts = stream.count_distinct(of, 1, "n")
        assert plan(counts).count("Exchange") == 1
        # rows are dealt out and sorted once; what else moves is the table of segments
        text = plan(stream.extend_sort(of, 2, ["l_quantity"]).df)
        sorts = [x for x in text.splitlines() if " Sort [" in x and "l_quantity" in x]
        moved = [x for i, x in enumerate(text.splitlines()) if "- Exchange" in x and "HashAggregate" not in "".join(text.splitlines()[i + 1 : i + 2])]
        assert len(sorts) == 1 and len(moved) == 1
    finally:
        spark.conf.unset("spark.sql.adaptive.enabled")


def test_filters_on_codes_reach_the_scan(spark, items, tmp_path):
    of = derive.attach(items.select("l_orderkey", "l_linenumber"), ["l_orderkey", "l_linenumber"], 1)
    of.df.write.parquet(f"file://{tmp_path}/coded")
    x = spark.read.parquet(f"file://{tmp_path}/coded").where(F.col(OFFSET) < 1).select("l_orderkey")
    assert f"PushedFilters: [IsNotNull({OFFSET}), LessThan({OFFSET},1)]" in plan(x)
    assert "l_linenumber" not in plan(x).split("ReadSchema")[1]


def test_lead_and_partitions_dont_matter(spark, items):
    keys = ["l_returnflag", "l_linestatus", "l_linenumber", "l_tax"]
    want = None
    for lead in (1, 2, 3):
        for n in (1, 4, 13):
            spark.conf.set("spark.sql.shuffle.partitions", n)
            got = sorted(tuple(r) for r in derive.attach(items.select(*keys), keys, lead).df.select(*keys, OFFSET, CODE).collect())
            want = want or got
            assert got == want
    spark.conf.set("spark.sql.shuffle.partitions", 4)


def test_nulls_nan_zero_and_direction(spark):
    rows = [(None, 1.0), (None, None), (1, float("nan")), (1, float("nan")), (1, 0.0), (1, -0.0), (2, None), (2, 5.0), (None, 1.0)]
    df = spark.createDataFrame(rows, "a int, b double")
    for keys in (["a", "b"], ["-a", "b"], [KeyCol("a", nulls_first=False), KeyCol("b", ascending=False)]):
        spec = key_spec(keys)
        got = derive.attach(df, keys, 1).df
        ordered = got.orderBy(*[k.order() for k in spec], OFFSET).select("a", "b", OFFSET, CODE).collect()
        same = lambda x, y: x == y or (x is not None and y is not None and x != x and y != y)
        before = None
        for r in ordered:
            off = 0 if before is None or not same(before.a, r.a) else 1 if not same(before.b, r.b) else 2
            assert r[OFFSET] == off, ordered
            assert (r[CODE] == 0) == (off == 2)
            before = r


def test_codes_keep_order_within_a_base(spark):
    df = spark.createDataFrame([(i, "x" * (i % 3) + chr(97 + i % 5), -i) for i in range(40)], "i int, s string, d long")
    out = df.select(*[codes.pack(F.lit(0), derive.value_at(df, [k], F.lit(0)), 1).alias(f"c{j}") for j, k in enumerate(["i", "s", "-d"])], "i", "s", "d").collect()
    for key, code, sign in (("i", "c0", 1), ("s", "c1", 1), ("d", "c2", -1)):
        pairs = sorted((r[code], r[key]) for r in out)
        keys = [k for _, k in pairs]
        assert keys == sorted(keys, reverse=sign < 0)


def test_packing_forms(spark):
    r = spark.range(1).select(
        codes.pack(F.lit(3), F.lit(44).cast("long"), 4).alias("a"), codes.pack(F.lit(3), F.lit(44).cast("long"), 4, "descending").alias("d"), codes.pack_domain(F.lit(3), F.lit(44), 4, 100).alias("t"),
        pack_bits([(F.lit(2), 3), (F.lit(5), 4)]).alias("p"),
    )
    x = r.select("*", codes.offset_of(F.col("a"), 4).alias("ao"), codes.value_of(F.col("a")).alias("av"), codes.offset_of(F.col("d"), 4, "descending").alias("do"), codes.value_of(F.col("d"), "descending").alias("dv")).first()
    assert (x.t, x.ao, x.av, x["do"], x.dv, x.p) == (144, 3, 44, 3, 44, 37)


def test_truncation_keeps_true_nulls(spark):
    rows = [(1, None, 3), (1, None, 3), (1, 2, None), (2, None, None), (2, None, 1), (None, 1, 1)]
    df = spark.createDataFrame(rows, "a int, b int, c int")
    of = derive.attach(df, ["a", "b", "c"], 1)
    back = formats.expand(formats.truncate(of), ["a", "b", "c"], ["a"])
    key = lambda r: tuple((x is not None, x or 0) for x in r)
    assert sorted((tuple(r) for r in back.select("a", "b", "c").collect()), key=key) == sorted(rows, key=key)


def test_consumers_check_their_input(spark, items):
    blocks = derive.attach_blocks(items.select("l_orderkey", F.pmod("l_partkey", F.lit(8)).alias("run")), ["l_orderkey"], "run")
    with pytest.raises(ValueError, match="whole table"):
        stream.distinct(blocks)
    two = derive.attach(items.select("l_returnflag", "l_linestatus", "l_tax"), ["l_returnflag", "l_linestatus", "l_tax"], 2)
    with pytest.raises(ValueError, match="aren't together"):
        stream.aggregate(two, 1, [F.count(F.lit(1)).alias("n")])
    odd = OrderedFrame(two.df, two.keys, two.scope, ("l_linestatus",))
    with pytest.raises(ValueError, match="leading key columns"):
        stream.keep(odd, F.lit(True))
    for lost in (two.df.drop(OFFSET), two.df.drop("l_tax"), two.df.withColumn("l_tax", F.col("l_tax").cast("string"))):
        with pytest.raises(ValueError, match="order is lost"):
            two.with_df(lost)


@pytest.mark.parametrize("share", ["l_quantity > 40", "l_quantity > 49 and l_tax > 0.05", "l_linestatus = 'O' and l_tax = 0.03", "false", "true"])
def test_filters_keep_codes_over_groups(spark, items, share):
    """However rows are dealt out, survivors have the codes that they would get from scratch."""
    keys = ["l_returnflag", "l_linestatus", "l_linenumber", "l_tax", "l_quantity"]
    want = sorted(tuple(r) for r in derive.attach(items.where(share).select(*keys), keys, 1).df.select(*keys, OFFSET, CODE).collect())
    for lead in (1, 2, 3, None):
        got = stream.keep(derive.attach(items.select(*keys), keys, lead), F.expr(share))
        assert sorted(tuple(r) for r in got.df.select(*keys, OFFSET, CODE).collect()) == want


def test_groups_take_their_first_rows_codes(spark, items):
    keys = ["l_returnflag", "l_linestatus", "l_linenumber", "l_tax"]
    for lead in (1, 2, 3):
        got = stream.aggregate_coded(derive.attach(items.select(*keys), keys, lead), 3, [F.count(F.lit(1)).alias("n")])
        want = derive.attach(items.groupBy(*keys[:3]).agg(F.count(F.lit(1)).alias("n")), keys[:3], 1)
        cols = [*keys[:3], "n", OFFSET, CODE]
        assert sorted(map(tuple, got.df.select(*cols).collect())) == sorted(map(tuple, want.df.select(*cols).collect()))


def test_no_window_over_a_whole_table(spark, items):
    """Numbers and codes by ranges: the only windows without partition are over a row for each range."""
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        keys = ["l_returnflag", "l_linestatus", "l_linenumber"]
        for df in (derive.numbered(items.select(*keys), keys, "r"), derive.stitch_parts(derive.attach_arrow(items.select(*keys), keys, 4), key_spec(keys)), derive.attach(items.select(*keys), keys, None).df):
            lines = plan(df).splitlines()
            for i, line in enumerate(lines):
                if "SinglePartition" in line:
                    assert "Aggregate" in "".join(lines[i + 1 : i + 4]), lines[i : i + 4]
    finally:
        spark.conf.unset("spark.sql.adaptive.enabled")


@pytest.mark.parametrize("lead", [1, 2, None])
def test_numbers_are_those_of_one_sort(spark, items, lead):
    keys = ["l_orderkey", "-l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice"]
    got = derive.numbered(items, keys, "r").select("r", "l_orderkey", "l_linenumber").collect()
    assert sorted(x.r for x in got) == list(range(items.count()))
    order = [(x.l_orderkey, -x.l_linenumber) for x in sorted(got, key=lambda x: x.r)]
    assert order == sorted(order)


def test_planner_steps(items):
    have = key_spec(["a", "b", "x"])
    assert planner.choose(have, key_spec(["a", "b", "x"])).kind == "none"
    assert planner.choose(have, key_spec(["a", "b"])).kind == "shorten"
    assert planner.choose(have, key_spec(["a", "c"])) == planner.Step("segmented sort", 1)
    assert planner.choose(have, key_spec(["-a"])).kind == "full sort"


def test_null_keys_never_join(spark):
    a = derive.attach(spark.createDataFrame([(None, 1), (1, 2), (1, 3), (4, 4)], "k int, v int"), ["k"], 1)
    b = derive.attach(spark.createDataFrame([(None, 5), (1, 6), (1, 7), (9, 8)], "k int, w int"), ["k"], 1)
    sizes = {how: join.merge_join(a, b, how).df.count() for how in ("inner", "left", "right", "full", "semi", "anti")}
    assert sizes == {"inner": 4, "left": 6, "right": 6, "full": 8, "semi": 2, "anti": 2}


def test_empty_tables(spark):
    empty = spark.createDataFrame([], "a int, b string")
    of = derive.attach(empty, ["a", "b"], 1)
    assert stream.distinct(of).df.count() == 0
    assert stream.aggregate(of, 1, [F.count(F.lit(1)).alias("n")]).count() == 0
    assert formats.to_rle(of).count() == 0
    assert join.set_operation(empty, empty, ["a", "b"], "union", True).count() == 0
    assert sort.external_sort(spark.createDataFrame([], "a int"), ["a"], 2).count() == 0


@pytest.mark.parametrize("run_gen", ["tree", "quick", "replacement"])
@pytest.mark.parametrize("compress", [True, False, "rle", "bare"])
def test_external_sort_kernel(run_gen, compress):
    import random

    from prefixcode.kernels.tree import Counters, coded

    r = random.Random(1)
    rows = [(r.randrange(4), r.randrange(4), r.randrange(50)) for _ in range(3000)]
    assert list(sort.sort_rows(rows, 3, 100, 3, Counters(), run_gen, compress)) == list(coded(sorted(rows)))
    assert [x for _, x in sort.sort_rows(rows, 3, 100, 3, Counters(), run_gen, compress, dedup=True)] == sorted(set(rows))
    assert [x for _, x in sort.sort_rows(rows, 3, 100, 3, Counters(), "quick", compress, merge="heap")] == sorted(rows)
    counts = Counter(rows)
    carried = [(*r, 1, i) for i, r in enumerate(rows)]
    assert [x[:3] for _, x in sort.sort_rows(carried, 3, 100, 3, Counters(), "index", compress, dedup=True)] == sorted(counts)
    out = sort.sort_rows(carried, 3, 100, 3, Counters(), run_gen, compress, fold=lambda a, b: (a[0] + b[0], min(a[1], b[1])))
    want = [(*r, counts[r], rows.index(r)) for r in sorted(counts)]
    assert list(out) == list(zip((c for c, _ in coded(sorted(counts))), want, strict=True))


CELLS = [
    ("string", [None, "", "a", "ab", "abcdef1", "abcdef2", "abcdef3", "abcdef", "b\u00e9", "\U0001f600", "a\x00", "a\x00b"]),
    ("binary", [None, b"", b"\x00", b"\x00\x00", b"\xff", b"\xff\xff", b"abcdefg", b"abcdefh"]),
    ("double", [None, float("nan"), float("inf"), float("-inf"), 0.0, -0.0, 1.00001, 1.00002, -1.00001, 1e300, 5e-324]),
    ("long", [None, 0, -1, 2**60 + 1, 2**60 + 2, 2**55, 2**63 - 1, -(2**63)]),
    ("decimal(38,4)", [None, Decimal("0.0001"), Decimal("0.0002"), Decimal("-1"), Decimal("9999999999999999999999999999999999.9999"), Decimal("9999999999999999999999999999999999.9998")]),
    ("date", [None, date(1, 1, 1), date(1970, 1, 1), date(9999, 12, 31)]),
    ("timestamp_ntz", [None, datetime(1, 1, 1), datetime(1970, 1, 1, 0, 0, 0, 1), datetime(9999, 12, 31)]),
    ("boolean", [None, True, False]),
]


@pytest.mark.parametrize("kind,values", CELLS, ids=[k for k, _ in CELLS])
@pytest.mark.parametrize("key", [KeyCol("v"), KeyCol("v", ascending=False), KeyCol("v", nulls_first=False), KeyCol("v", ascending=False, nulls_first=True)])
def test_external_sort_is_exact(spark, kind, values, key):
    """The host's order, and no two keys taken for one, whatever the type."""
    df = spark.createDataFrame([(i, v) for i, v in enumerate([*values, *values[::-1]])], f"i int, v {kind}")
    same = lambda x: "nan" if x != x else 0.0 if x == 0 and isinstance(x, float) else x
    want = [same(r.v) for r in df.orderBy(key.order()).collect()]
    for n, dedup in ((1, False), (3, False), (2, True)):
        got = sort.external_sort(df, [key], n, memory=5, fan_in=2, dedup=dedup).orderBy("__part", "__pos").collect()
        expected = [v for i, v in enumerate(want) if not dedup or not i or v != want[i - 1]]
        assert [same(r.v) for r in got] == expected
        assert [r[OFFSET] for r in got] == [0 if not i or v != expected[i - 1] else 1 for i, v in enumerate(expected)]


def test_codes_of_wide_numbers_stay_apart(spark):
    """64-bit hashes: ten bits are left out beyond 2**53, so nearly all codes differ, and order is kept."""
    x = spark.range(10_000).select(F.xxhash64("id").alias("h"))
    out = derive.attach(x, ["h"], 1).df.select("h", CODE).collect()
    assert len({r[CODE] for r in out}) == 10_000
    assert [r.h for r in sorted(out, key=lambda r: r[CODE])] == sorted(r.h for r in out)


@settings(max_examples=40, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 3), st.integers(0, 3)), max_size=25), st.lists(st.tuples(st.integers(0, 3), st.integers(0, 3)), max_size=25), st.sampled_from(["inner", "left", "right", "full", "semi", "anti"]))
def test_merge_join_kernel(left, right, how):
    from prefixcode.kernels.join import merge_rows
    from prefixcode.kernels.tree import Counters, coded

    tag = lambda rows, side: coded(sorted((*r, side, i) for i, r in enumerate(rows)), None, 2)
    ctr = Counters()
    out = list(merge_rows(tag(left, 0), tag(right, 1), 2, ctr, how, lambda r: r[2] == 0, lambda r: r[0] == 3))
    pairs = [(a, b) for a in left for b in right if a == b and a[0] != 3]
    hit_l, hit_r = {a for a, _ in pairs}, {b for _, b in pairs}
    want = [(a, b) for a, b in pairs] if how not in ("semi", "anti") else [(a, None) for a in left if (a in hit_l) == (how == "semi")]
    want += [(a, None) for a in left if a not in hit_l] if how in ("left", "full") else []
    want += [(None, b) for b in right if b not in hit_r] if how in ("right", "full") else []
    text = lambda x: sorted(map(str, x))
    assert text((a and a[:2], b and b[:2]) for _, a, b in out) == text(want)
    keys = [(a or b)[:2] for _, a, b in out]
    assert keys == sorted(keys) and [c for c, _, _ in out] == [c for c, _ in coded(keys)]


def test_coded_join_codes_and_nulls(spark):
    a = spark.createDataFrame([(None, "x", 1), (1, "x", 2), (1, "x", 3), (4, None, 4), (4, "y", 5)], "k int, s string, v int")
    b = spark.createDataFrame([(None, "x", 5), (1, "x", 6), (1, "x", 7), (9, "z", 8), (4, None, 9)], "k int, s string, w int")
    sizes = {}
    for how in ("inner", "left", "right", "full", "semi", "anti"):
        got = join.coded_join(a, b, ["k", "s"], 3, how)
        sizes[how] = got.count()
        want = derive.attach(got.select("k", "s"), ["k", "s"], 1).df
        key = lambda r: (r.k or 0, r.s or "", r[OFFSET], r[CODE])
        assert sorted(map(key, got.select("k", "s", OFFSET, CODE).collect())) == sorted(map(key, want.collect()))
    assert sizes == {"inner": 4, "left": 7, "right": 7, "full": 10, "semi": 2, "anti": 3}


def test_stored_runs_outlive_the_driver(spark, sf, tmp_path):
    """A store found again knows its runs and batches; a batch that comes again adds nothing."""
    path = f"file://{tmp_path}/store"
    first = store.RunStore(spark, ["k", "v"], fan_in=3, path=path)
    batches = [spark.createDataFrame([(j % 5, j * 7 + i) for j in range(9)], "k int, v int") for i in range(4)]
    for i in range(3):
        first.append_run(batches[i], i)
    again = store.RunStore(spark, ["k", "v"], fan_in=3, path=path)
    assert again.levels == first.levels and again.batches == {0, 1, 2}
    for i in range(4):
        again.append_run(batches[i], i)
    rows = sorted(tuple(r) for b in batches for r in b.collect())
    got = again.merged().orderBy("bucket", "__pos").collect()
    assert [(r.k, r.v) for r in got] == rows
    assert [r[OFFSET] for r in got] == [0 if not i or rows[i - 1][0] != r[0] else 1 if rows[i - 1] != r else 2 for i, r in enumerate(rows)]


def test_packets_carry_codes(spark, items):
    """Offsets in packets are those between rows of one run in one bucket."""
    keys = ["l_orderkey", "l_linenumber"]
    x = items.select(*keys, F.pmod("l_partkey", F.lit(3)).alias("run"))
    got = sort.packets(x, keys, "run", sort.bucket_by(x, keys, 4, "hash"))
    rows = sorted(tuple(r) for r in got.select("__run", "__bucket", "__seq", *keys, OFFSET).collect())
    for before, now in zip(rows, rows[1:], strict=False):
        if before[:2] == now[:2]:
            assert now[5] == (0 if before[3] != now[3] else 1 if before[4] != now[4] else 2)
        else:
            assert now[5] == 0


def test_long_runs_come_back(spark):
    """A run longer than one part of rows, and a block of one value only."""
    df = spark.createDataFrame([(1, 2, 3)] * 9000 + [(1, 2, 4), (1, 3, 1)] + [(2, 1, 1)] * 2, "a int, b int, c int")
    runs = formats.to_rle(derive.attach(df, ["a", "b", "c"], 1))
    back = formats.from_rle(runs, ["a", "b", "c"], ["a"])
    assert sorted(map(tuple, back.select("a", "b", "c").collect())) == sorted(tuple(map(str, r)) for r in df.collect())
    assert back.where(f"{OFFSET} < 3").count() == 4


def test_stepped_merge_writes_a_row_once_a_level(spark):
    runs = store.RunStore(spark, ["k"], fan_in=2)
    for i in range(4):
        batch = spark.createDataFrame([(j * 4 + i,) for j in range(5)], "k int")
        runs.append_run(batch, i)
        runs.append_run(batch, i)  # a batch that comes again
    assert [len(x) for x in runs.levels] == [0, 0, 1] and runs.rewrites == 3
    assert sorted(r.k for r in runs.scan().collect()) == list(range(20))


def test_run_reader(spark, tmp_path):
    spark.range(100).coalesce(2).write.parquet(f"file://{tmp_path}/run")
    spark.dataSource.register(PrefixRuns)
    x = spark.read.format("prefix_runs").option("path", f"{tmp_path}/run").load()
    assert x.columns == ["id", "__ordinal"] and x.select("id").distinct().count() == 100


def test_restarted_stream_adds_nothing(spark, sf, tmp_path):
    """The same ingestion started again with its progress lost: batches come again, the store ignores them."""
    from prefixcode.streaming import events

    path = f"file://{tmp_path}/store"
    first = events.ingest(spark, sf, ["event_type", "user_id"], path=path)
    n = first.scan().count()
    again = events.ingest(spark, sf, ["event_type", "user_id"], path=path)
    assert again.batches == first.batches and again.scan().count() == n == spark.read.parquet(f"{sf}/events.parquet").count()


def test_buckets_need_no_exchange(spark, sf):
    import __spark_entry__

    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        assert "Exchange" not in plan(__spark_entry__.queries()["bucketed_join"](spark, sf))
    finally:
        spark.conf.unset("spark.sql.adaptive.enabled")


def test_rate_counts_the_events_given(spark, tmp_path):
    """The stream's numbers are the table's, not made up."""
    from prefixcode.streaming import events

    spark.createDataFrame([(i, None) for i in (1, 2, 4, 7, 9)], "event_id long, ts timestamp_ntz").write.parquet(str(tmp_path / "events.parquet"))
    assert {r.digit: r.n for r in events.rate(spark, str(tmp_path)).collect()} == {0: 1, 1: 3, 2: 1}


def test_measured_counts_the_same_many_at_once(spark, monkeypatch):
    """In portions that don't end with batches; keys with nulls, or of texts, go row by row."""
    rows = [(i * 7919 % 503, None if i % 97 == 0 else i * 31 % 11, f"t{i % 13}") for i in range(3000)]
    df = spark.createDataFrame(rows, "a long, b int, c string").coalesce(1)
    for keys in (["a"], ["a", "b"], ["c", "a"]):
        for method in ("generate", "full", "pmnk1", "pmnk2"):
            if keys[0] == "c" and method.startswith("pmnk"):
                continue
            got = sort.measured(df, keys, 1, method, at_once=1100).first()
            with monkeypatch.context() as m:
                m.setattr(sort.Rows, "numbers", lambda self, batches: None)
                want = sort.measured(df, keys, 1, method, at_once=1100).first()
            assert got == want and got["n"] == 3000


def test_measured_external_sorts_count_the_same_many_at_once(spark, monkeypatch):
    """Doubles and short texts are numbers too; keys with nulls, of longer texts or downwards go row by row."""
    rows = [(i * 7919 % 503 - 200, None if i % 97 == 0 else i * 31 % 11, f"t{i % 13}", f"a text {i % 7}", (i * 37 % 19 - 9) / 4 or -0.0) for i in range(3000)]
    df = spark.createDataFrame(rows, "a long, b int, c string, d string, e double").coalesce(1)
    for keys, many in ((["c", "e", "a"], True), (["e"], True), (["a", "b"], False), (["d", "a"], False), (["-a"], False)):
        assert sort.Rows(df, sort.key_spec(keys), []).numeric(df) == many
        for method in ("tree", "traditional"):
            got = sort.measured(df, keys, 1, method, memory=50, fan_in=4, at_once=700).first().asDict()
            with monkeypatch.context() as m:
                m.setattr(sort.Rows, "numeric", lambda self, df: False)
                want = sort.measured(df, keys, 1, method, memory=50, fan_in=4).first().asDict()
            sizes = [(x.pop("spilled_bytes"), x.pop("plain_bytes")) for x in (got, want)]
            assert got == want and got["n"] == 3000 and got["runs"] == 60 and min(sizes) > (0, 0)
