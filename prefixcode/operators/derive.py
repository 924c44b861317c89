"""Codes for the rows of a DataFrame in key order."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W
from pyspark.sql import types as T

from prefixcode.functions.codes import pack
from prefixcode.functions.keys import KeyCol, key_spec, kinds, normalize
from prefixcode.plans.frame import CODE, OFFSET, OrderedFrame
from prefixcode.sources import scratch


def first_difference(names: list[str], before: list[Column], start: int = 0) -> Column:
    """Index of the first column that differs from its predecessor, or how many there are."""
    out = None
    for j in range(start, len(names)):
        differs = ~F.col(names[j]).eqNullSafe(before[j])
        out = F.when(differs, F.lit(j)) if out is None else out.when(differs, F.lit(j))
    return out.otherwise(F.lit(len(names))) if out is not None else F.lit(len(names))


def value_at(df: DataFrame, keys: list, offset: Column) -> Column:
    """The normalised value of the key column at ``offset``; only that one is computed."""
    spec = key_spec(keys)
    out = None
    for j, (key, kind) in enumerate(zip(spec, kinds(df, spec), strict=True)):
        n = normalize(key, kind)
        out = F.when(offset == j, n) if out is None else out.when(offset == j, n)
    return out.otherwise(F.lit(0).cast("long"))


#: With less than so many distinct prefixes for each shuffle partition, ``spread`` takes one more column.
SPREAD = 8


def spread(df: DataFrame, keys: list) -> int:
    """The least number of leading key columns whose values deal the rows out well (all but the last, at most),
    from one pass of sketches over the key columns."""
    names = [k.name for k in key_spec(keys)]
    if len(names) < 3:
        return 1
    counts = df.agg(*[F.approx_count_distinct(F.struct(*names[: j + 1])).alias(f"d{j}") for j in range(len(names) - 1)]).first()  # a number for each prefix
    wanted = SPREAD * int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return next((j + 1 for j, n in enumerate(counts) if n >= wanted), len(names) - 1)


def attach(df: DataFrame, keys: list, lead: int | None = 1) -> OrderedFrame:
    """Offset and code of every row relative to its predecessor in key order, over the whole table.

    Rows are grouped by the first ``lead`` key columns, so one exchange by them is all it takes: the
    first row of a group differs from its predecessor within those columns. For lead = 1 that is at
    column 0. With few values in the first column, take a greater lead: the groups' own first rows
    then get their codes from the table of distinct prefixes, by the same method on the first column.
    With None, ``spread`` finds the lead, and the table of prefixes is written and dealt out by half
    as many columns, and so on: no table is sorted in few tasks but those of few rows.
    """
    found = lead is None
    spec = key_spec(keys)
    names = [k.name for k in spec]
    k = len(names)
    if lead is None:
        lead = spread(df, spec)
    if lead >= k:
        lead = max(1, k - 1)
    order = [x.order() for x in spec[lead:]] or [F.lit(0)]
    w = W.partitionBy(*names[:lead]).orderBy(*order)
    before = [F.lag(c).over(w) for c in names]
    position = F.row_number().over(w)
    if k == 1:
        out = df.withColumn(OFFSET, F.when(position == 1, F.lit(0)).otherwise(F.lit(1)))
    else:
        inside = first_difference(names, before, lead)
        if lead == 1:
            out = df.withColumn(OFFSET, F.when(position == 1, F.lit(0)).otherwise(inside))
        else:
            prefixes = df.select(*names[:lead]).distinct()
            heads = attach(scratch.cut(prefixes, "prefixes"), list(spec[:lead]), lead // 2).df if found else attach(prefixes, list(spec[:lead]), 1).df
            heads = heads.select(*[F.col(c).alias(f"__head_{c}") for c in names[:lead]], F.col(OFFSET).alias("__head"))
            same = None
            for c in names[:lead]:
                term = F.col(c).eqNullSafe(F.col(f"__head_{c}"))
                same = term if same is None else same & term
            out = df.withColumn("__position", position).withColumn("__inside", inside)
            out = out.join(heads, same).withColumn(OFFSET, F.when(F.col("__position") == 1, F.col("__head")).otherwise(F.col("__inside")))
            out = out.select(*df.columns, OFFSET)
    coded = out.withColumn(CODE, pack(F.col(OFFSET), value_at(df, keys, F.col(OFFSET)), k))
    return OrderedFrame(coded, spec, scope="global", partitioned_by=tuple(names[:lead]), source=df)


def attach_blocks(df: DataFrame, keys: list, block: str) -> OrderedFrame:
    """Codes within blocks (runs, buckets): the first row of each block has offset 0."""
    spec = key_spec(keys)
    names = [k.name for k in spec]
    w = W.partitionBy(block).orderBy(*[x.order() for x in spec])
    offset = F.when(F.row_number().over(w) == 1, F.lit(0)).otherwise(first_difference(names, [F.lag(c).over(w) for c in names]))
    out = df.withColumn(OFFSET, offset)
    return OrderedFrame(out.withColumn(CODE, pack(F.col(OFFSET), value_at(df, keys, F.col(OFFSET)), len(names))), spec, scope="block", partitioned_by=(block,))


def attach_arrow(df: DataFrame, keys: list, partitions: int) -> DataFrame:
    """The same offsets by one pass over sorted Arrow batches: __part, __pos and __off are added.

    Range partitions of the whole key are sorted in the JVM; a task carries its last row from batch to
    batch. The first row of a part has no predecessor there; ``stitch_parts`` gives it its offset.
    """
    from prefixcode.operators.sort import neighbour_offsets

    spec = key_spec(keys)
    names = [x.name for x in spec]
    ranged = df.repartitionByRange(partitions, *[x.order() for x in spec]).sortWithinPartitions(*[x.order() for x in spec])
    added = [T.StructField("__part", T.IntegerType()), T.StructField("__pos", T.LongType()), T.StructField(OFFSET, T.IntegerType())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        last, part, pos = None, TaskContext.get().partitionId(), 0
        for b in batches:
            if not b.num_rows:
                continue
            offset = neighbour_offsets(b, names, last)
            last = b.slice(b.num_rows - 1, 1)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(np.full(b.num_rows, part, np.int32)), pa.array(np.arange(pos, pos + b.num_rows)), pa.array(offset)], names=[*b.schema.names, *(f.name for f in added)])
            pos += b.num_rows

    return ranged.mapInArrow(run, T.StructType([*(T.StructField(f.name, f.dataType, True) for f in ranged.schema.fields), *added]))


def stitch_parts(pieces: DataFrame, spec: list[KeyCol]) -> DataFrame:
    """Give the parts' first rows (__pos 0) their offsets relative to the last row of an earlier part."""
    names = [x.name for x in spec]
    ends = pieces.groupBy("__part").agg(F.min_by(F.struct(*names), "__pos").alias("__first"), F.max_by(F.struct(*names), "__pos").alias("__last"))
    joined = ends.withColumn("__before", F.lag("__last").over(W.orderBy("__part")))  # a row for each part
    fixed = None
    for j, c in enumerate(names):
        differs = ~F.col(f"__first.{c}").eqNullSafe(F.col(f"__before.{c}"))
        fixed = F.when(F.col("__before").isNull() | differs, F.lit(j)) if fixed is None else fixed.when(differs, F.lit(j))
    table = joined.select("__part", fixed.otherwise(F.lit(len(names))).alias("__fixed"))
    out = pieces.join(F.broadcast(table), "__part")
    return out.withColumn(OFFSET, F.when(F.col("__pos") == 0, F.col("__fixed")).otherwise(F.col(OFFSET))).select(*pieces.columns)


def numbered(df: DataFrame, keys: list, name: str, partitions: int | None = None) -> DataFrame:
    """Rows numbered from 0 in key order over the whole table, by ranges, no task sees them all: the
    numbers of the ranges before come from a table with a row for each."""
    spec = key_spec(keys)
    ranged = df.repartitionByRange(*([partitions] if partitions else []), *[x.order() for x in spec]).sortWithinPartitions(*[x.order() for x in spec])
    local = ranged.withColumn("__id", F.monotonically_increasing_id())
    local = scratch.cut(local.withColumn("__part", F.shiftright("__id", 33)), "numbered")
    before = local.groupBy("__part").agg(F.count(F.lit(1)).alias("__n"))
    base = before.select("__part", F.coalesce(F.sum("__n").over(W.orderBy("__part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("__base"))  # a row for each range
    out = local.join(F.broadcast(base), "__part")
    return out.withColumn(name, F.col("__id").bitwiseAND(F.lit((1 << 33) - 1)) + F.col("__base")).select(*df.columns, name)


def common_prefix(x: str, y: str) -> Column:
    """Number of leading bytes two binary columns share, without Python: by halving."""
    return F.expr(
        f"aggregate(sequence(30, 0, -1), 0, (n, b) -> CASE WHEN n + shiftleft(1, b) <= least(octet_length({x}), octet_length({y}))"
        f" AND substring({x}, 1, n + shiftleft(1, b)) = substring({y}, 1, n + shiftleft(1, b)) THEN n + shiftleft(1, b) ELSE n END)"
    )


def attach_bytes(df: DataFrame, key: str, partitions: int) -> DataFrame:
    """Byte-granular offsets of a binary key (how many leading bytes a row shares with the row before).

    Range partitions of the key are sorted in the JVM, a task carries its last key; the first row of a
    part is compared with the last of the part before, from a table with a row for each part.
    """
    ranged = df.repartitionByRange(partitions, key).sortWithinPartitions(key)
    added = [T.StructField("__part", T.IntegerType()), T.StructField("__pos", T.LongType()), T.StructField(OFFSET, T.IntegerType())]

    def shared(a: bytes, b: bytes) -> int:
        n = min(len(a), len(b))
        if a[:n] == b[:n]:
            return n
        lo, hi = 0, n  # a[:lo] == b[:lo], a[:hi] != b[:hi]
        while hi - lo > 1:
            mid = (lo + hi) // 2
            lo, hi = (mid, hi) if a[lo:mid] == b[lo:mid] else (lo, mid)
        return lo

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        last, part, pos = None, TaskContext.get().partitionId(), 0
        for b in batches:
            off = []
            for v in b.column(key).to_pylist():
                off.append(0 if last is None else shared(last, v))
                last = v
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(np.full(b.num_rows, part, np.int32)), pa.array(np.arange(pos, pos + b.num_rows)), pa.array(off, pa.int32())], names=[*b.schema.names, *(f.name for f in added)])
            pos += b.num_rows

    pieces = scratch.cut(ranged.mapInArrow(run, T.StructType([*(T.StructField(f.name, f.dataType, True) for f in ranged.schema.fields), *added])), "bytes")
    ends = pieces.groupBy("__part").agg(F.min_by(key, "__pos").alias("__first"), F.max_by(key, "__pos").alias("__last"))
    ends = ends.withColumn("__before", F.lag("__last").over(W.orderBy("__part")))  # a row for each part
    table = ends.select("__part", F.when(F.col("__before").isNull(), F.lit(0)).otherwise(common_prefix("__before", "__first")).alias("__fixed"))
    out = pieces.join(F.broadcast(table), "__part")
    return out.withColumn(OFFSET, F.when(F.col("__pos") == 0, F.col("__fixed")).otherwise(F.col(OFFSET))).select(*df.columns, OFFSET)
