"""Merge join, set operations and look-ups over sorted inputs.

``coded_join`` merges both inputs with a queue of losers: the codes they carry decide, and the output's
codes follow from them. ``merge_join`` leaves the merge to the host's sort-merge join and keeps codes
right around it; it splits hot keys over tasks, which a merge in one task can't.
"""

from __future__ import annotations

import tempfile
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from prefixcode.functions.codes import offset_of
from prefixcode.functions.keys import key_spec
from prefixcode.kernels import tree as kernel
from prefixcode.kernels.join import merge_rows
from prefixcode.operators.derive import attach, stitch_parts
from prefixcode.operators.sort import Rows, Spill, _schema, _with_codes, _written
from prefixcode.operators.stream import aggregate, keep
from prefixcode.plans.frame import CODE, OFFSET, OrderedFrame
from prefixcode.sources import scratch
from prefixcode.sources.formats import repeated

_TYPES = {"inner", "left", "right", "full", "semi", "anti"}


def merge_join(left: OrderedFrame, right: OrderedFrame, how: str = "inner") -> OrderedFrame:
    """Join on all key columns of both frames, which must correspond; the output is coded too.

    The host's sort-merge join does the merge. An output key's first row has the greatest code of
    the driving side since the previous output key, its other rows repeat it. Key columns of the
    right side are dropped; in right and full joins the left's are filled from them. Null keys match
    nothing.
    """
    if how not in _TYPES:
        raise ValueError(how)
    if how == "right":
        out = merge_join(right, OrderedFrame(_renamed(left.df, left.names, right.names), right.keys, left.scope, right.partitioned_by), "left")
        return OrderedFrame(_renamed(out.df, right.names, left.names), left.keys, out.scope, left.partitioned_by)
    names, other = left.names, [f"__r_{c}" for c in right.names]
    r = right.df.drop(CODE, OFFSET)
    for c, o in zip(right.names, other, strict=True):
        r = r.withColumnRenamed(c, o)
    on = None
    for c, o in zip(names, other, strict=True):
        term = F.col(c) == F.col(o)
        on = term if on is None else on & term
    if how in ("semi", "anti"):
        there = r.select(*other).distinct().withColumn("__there", F.lit(True))
        flagged = left.df.join(there.hint("merge"), on, "left").drop(*other)
        hit = F.coalesce(F.col("__there"), F.lit(False))
        out = keep(left.with_df(flagged), hit if how == "semi" else ~hit)
        return out.with_df(out.df.drop("__there"))
    if how == "full":
        joined = left.plain().join(r.hint("merge"), on, "full")
        filled = joined.select(*[F.coalesce(F.col(c), F.col(o)).alias(c) for c, o in zip(names, other, strict=True)], *[c for c in joined.columns if c not in names and c not in other])
        return attach(filled, left.keys, 1)
    driving = merge_join(left, right, "semi") if how == "inner" else left
    joined = driving.df.join(r.hint("merge"), on, "inner" if how == "inner" else "left").drop(*other)
    # one row of each key keeps the code, all others repeat the key
    head = F.row_number().over(W.partitionBy(*names).orderBy(F.col(CODE).desc()))
    coded = joined.withColumn(CODE, F.when(head == 1, F.col(CODE)).otherwise(F.lit(0).cast("long")))
    return OrderedFrame(coded.withColumn(OFFSET, offset_of(F.col(CODE), left.k)), left.keys, left.scope, left.partitioned_by)


def _renamed(df: DataFrame, old: list[str], new: list[str]) -> DataFrame:
    for a, b in zip(old, new, strict=True):
        df = df.withColumnRenamed(a, b)
    return df


def coded_join(left: DataFrame, right: DataFrame, keys: list, partitions: int, how: str = "inner", within: Column | None = None, counters: bool = False) -> DataFrame:
    """Join on key columns of the same names and types; both inputs sorted once, merged by codes.

    A task gets a range of keys of both sides (or, with ``within``, a whole-number expression over the
    key columns, all rows of some of its values). The left side's run waits in the task's folder, the
    right side's streams by; a row of each is held, and the left rows of one key. Null keys match
    nothing. Gives __part, __pos, the key columns, the other columns of both, __off and __code, right over
    the whole table; or with counters, a row for each part: rows out, comparisons, columns compared.
    """
    if how not in _TYPES:
        raise ValueError(how)
    spec = key_spec(keys)
    names = [x.name for x in spec]
    own, other = ([c for c in x.columns if c not in names] for x in (left, right))
    both = left.withColumn("__side", F.lit(0)).unionByName(right.withColumn("__side", F.lit(1)), allowMissingColumns=True)
    null = F.lit(False)
    for c in names:
        null = null | F.col(c).isNull()
    both = both.withColumn("__null", null)
    rows = Rows(both, spec, ["__side", "__null", *names, *own, *([] if how in ("semi", "anti") else other)])
    k, lossless = rows.k, rows.lossless
    order = [x.order() for x in spec]
    part = within.cast("int") if within is not None else F.lit(None).cast("int")
    both = both.withColumn("__within", part)
    dealt = both.repartition(partitions, "__within") if within is not None else both.repartitionByRange(partitions, *order)
    dealt = dealt.sortWithinPartitions("__within", "__side", *order).select("__within", *rows.columns)
    fields = rows.fields[2:]
    width, mine = len(names), len(names) + len(own)
    empty_left, empty_right = (None,) * len(own), (None,) * (len(fields) - mine)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        types: list[pa.DataType] = []
        number = TaskContext.get().partitionId()

        def stream() -> Iterator[tuple[object, tuple]]:
            for b in batches:
                types[:] = rows.types(b)[2:]
                yield from zip(b.column("__within").to_pylist(), rows.read(b), strict=True)

        def joined(row: tuple, more: tuple) -> tuple:
            key = row or more
            return (*key[:k], *key[k + 2 : k + 2 + width], *(row[k + 2 + width : k + 2 + mine] if row else empty_left), *(more[k + 2 + mine :] if more else empty_right))

        source = stream()
        item = next(source, None)
        with tempfile.TemporaryDirectory() as folder:
            while item is not None:
                now = item[0]

                def side(which: int, now: object = now) -> Iterator[tuple]:
                    nonlocal item
                    while item is not None and item[0] == now and item[1][k] == which:
                        yield item[1]
                        item = next(source, None)

                ctr = kernel.Counters()
                run_ = Spill(folder, k, "truncate").write(kernel.coded(side(0), None, k))
                out = merge_rows(run_.read(), kernel.coded(side(1), None, k), k, ctr, how, lambda r: r[k] == 0, lambda r: r[k + 1], lossless)
                made = ((c, joined(a, b)) for c, a, b in out)
                if counters:
                    n = sum(1 for _ in made)
                    yield pa.RecordBatch.from_arrays([pa.array([now], pa.int32()), *(pa.array([v], pa.int64()) for v in (n, ctr.rows, ctr.by_code, ctr.columns))], names=["part", "n", "row_cmp", "by_code", "columns"])
                else:
                    yield from _written(made, k, [f.name for f in fields], types, [("__part", number if now is None else now)])

    if counters:
        return dealt.mapInArrow(run, "part int, n long, row_cmp long, by_code long, columns long")
    pieces = dealt.mapInArrow(run, _schema(["__part"], [T.StructField(f.name, f.dataType, True) for f in fields]))
    return _with_codes(stitch_parts(scratch.cut(pieces, "joined"), spec), spec)


def set_operation(left: DataFrame, right: DataFrame, keys: list[str], kind: str, all_rows: bool = False) -> DataFrame:
    """union, intersect or except by one merge: keys of both sides, told apart by a tag, are sorted
    once; codes find the groups, whose counts by side say how many rows leave."""
    both = left.select(*keys, F.lit(0).alias("__side")).unionByName(right.select(*keys, F.lit(1).alias("__side")))
    sides = [F.sum((F.col("__side") == s).cast("long")).alias(f"__n{s}") for s in (0, 1)]
    groups = aggregate(attach(both, keys, 1), len(keys), sides)
    a, b = F.col("__n0"), F.col("__n1")
    if kind == "union":
        n = a + b if all_rows else F.lit(1)
    elif kind == "intersect":
        n = F.least(a, b) if all_rows else F.when((a > 0) & (b > 0), 1).otherwise(0)
    elif kind == "except":
        n = F.greatest(a - b, F.lit(0)) if all_rows else F.when((a > 0) & (b == 0), 1).otherwise(0)
    else:
        raise ValueError(kind)
    out = groups.withColumn("__n", n.cast("long")).where("__n > 0")
    return repeated(out, F.col("__n"), "__i").select(*keys) if all_rows else out.select(*keys)


def interval_join(left: DataFrame, right: DataFrame, equal: str, at: str, lo: str, hi: str, width: int) -> DataFrame:
    """Rows of left whose ``at`` lies in a right row's [lo, hi], within equal ``equal``.

    Whole numbers; both sides are dealt to buckets of ``width``, a right row to each it touches, so
    the join is an equi-join and no bucket pairs with all others.
    """
    l = left.withColumn("__b", F.floor(F.col(at) / width))
    r = right.withColumn("__b", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return l.join(r, [equal, "__b"]).where(F.col(at).between(F.col(lo), F.col(hi))).drop("__b")


def asof_join(left: DataFrame, right: DataFrame, by: list[str], left_at: str, right_at: str, values: list[str]) -> DataFrame:
    """Each left row with the last right row at or before it: one merge of both, tagged, and a look back.

    Ties of right rows in time go to the greatest values.
    """
    l = left.select(*by, F.col(left_at).alias("__at"), F.lit(1).alias("__side"), F.struct(*left.columns).alias("__row"), F.lit(None).cast(right.select(F.struct(*values)).schema[0].dataType).alias("__v"))
    r = right.select(*by, F.col(right_at).alias("__at"), F.lit(0).alias("__side"), F.lit(None).cast(left.select(F.struct(*left.columns)).schema[0].dataType).alias("__row"), F.struct(*values).alias("__v"))
    w = W.partitionBy(*by).orderBy("__at", "__side", "__v").rowsBetween(W.unboundedPreceding, 0)
    out = l.unionByName(r).withColumn("__last", F.last("__v", ignorenulls=True).over(w)).where("__side = 1")
    return out.select("__row.*", *[F.col(f"__last.{v}").alias(f"right_{v}") for v in values])
