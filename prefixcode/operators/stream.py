"""Operators on sorted, coded rows: what they need to know is in the code.

Duplicate removal, segment flags and group counts look at one row at a time. Groups are numbered by
a running sum of flags in the window that the codes came from, so no further exchange or sort is
needed, and no key column is compared.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from prefixcode.functions.codes import offset_of, pack, project
from prefixcode.functions.keys import key_spec
from prefixcode.operators.derive import first_difference, value_at
from prefixcode.plans.frame import CODE, OFFSET, OrderedFrame


def _window(of: OrderedFrame) -> W:
    return W.partitionBy(*of.partitioned_by).orderBy(*[k.order() for k in of.keys if k.name not in of.partitioned_by] or [F.lit(0)])


def running(of: OrderedFrame, flag: Column) -> Column:
    """Running count of a flag in key order, within the frame's partitions.

    The order must tell first rows from their repeats: equal keys go by falling code, the one with the
    group's code first.
    """
    by = [k.order() for k in of.keys if k.name not in of.partitioned_by]
    w = W.partitionBy(*of.partitioned_by).orderBy(*by, F.col(OFFSET)).rowsBetween(W.unboundedPreceding, 0)
    return F.sum(flag.cast("int")).over(w)


def distinct(of: OrderedFrame) -> OrderedFrame:
    """One row for each key: those whose code isn't that of a repeat. A filter, no more."""
    of.need_global("duplicate removal")
    return of.with_df(of.df.where(F.col(OFFSET) < of.k))


def segment(of: OrderedFrame, columns: int) -> DataFrame:
    """seg_start: whether the row opens a segment of equal leading columns; seg: its number in the partition."""
    flag = F.col(OFFSET) < columns
    return of.df.withColumn("seg_start", flag).withColumn("seg", running(of, flag))


def _grouped(of: OrderedFrame, columns: int, aggs: list[Column]) -> DataFrame:
    names = of.names[:columns]
    inside = [c for c in of.partitioned_by if c in names]
    if len(inside) < len(of.partitioned_by):
        raise ValueError(f"rows of a group aren't together: partitioned by {of.partitioned_by}")
    x = of.df.withColumn("__group", running(of, F.col(OFFSET) < columns))
    rest = [c for c in names if c not in inside]
    return x.groupBy(*inside, "__group").agg(*[F.first(c).alias(c) for c in rest], *aggs)


def aggregate(of: OrderedFrame, columns: int, aggs: list[Column]) -> DataFrame:
    """Groups by the leading columns, found by codes."""
    names = of.names[:columns]
    out = _grouped(of, columns, aggs)
    return out.select(*names, *[c for c in out.columns if c not in names and c != "__group"])


def aggregate_coded(of: OrderedFrame, columns: int, aggs: list[Column]) -> OrderedFrame:
    """The same, coded: a group has its first row's code, cut to the group columns. That is the greatest
    code in the group, as all others repeat its columns."""
    of.need_global("codes of groups")
    out = _grouped(of, columns, [*aggs, F.max(CODE).alias(CODE)]).drop("__group")
    out = out.withColumn(CODE, project(F.col(CODE), of.k, columns))
    return OrderedFrame(out.withColumn(OFFSET, offset_of(F.col(CODE), columns)), of.keys[:columns], of.scope, of.partitioned_by)


def aggregate_over(of: OrderedFrame, columns: int, aggs: dict[str, tuple[str, str]]) -> DataFrame:
    """Groups by fewer columns than rows are together by, so that groups of few values don't mean few tasks:
    finer groups are found by codes where their rows are, then those few are folded by the group columns.
    aggs: name -> (sum | count | min | max, column or "*")."""
    fine = max(columns, len(of.partitioned_by))
    first = aggregate(of, fine, [getattr(F, f)(F.lit(1) if c == "*" else F.col(c)).alias(n) for n, (f, c) in aggs.items()])
    if fine == columns:
        return first
    return first.groupBy(*of.names[:columns]).agg(*[(F.sum if f in ("sum", "count") else getattr(F, f))(n).alias(n) for n, (f, _) in aggs.items()])


def count_distinct(of: OrderedFrame, columns: int, name: str) -> DataFrame:
    """count(distinct next key column) for groups by the leading ones: rows that differ up to there."""
    x = of.names[columns]
    new = (F.col(OFFSET) < columns + 1) & F.col(x).isNotNull()
    return of.df.groupBy(*of.names[:columns]).agg(F.sum(new.cast("long")).alias(name))


def group_counts(of: OrderedFrame) -> DataFrame:
    """For every prefix length, how many distinct prefixes there are: counts of offsets, summed up."""
    k = of.k
    counts = [F.sum((F.col(OFFSET) < j).cast("long")).alias(f"p{j}") for j in range(1, k + 1)]
    return of.df.agg(*counts)


def rollup(of: OrderedFrame, columns: int, aggs: dict[str, tuple[str, str]]) -> DataFrame:
    """All levels of ROLLUP from one sorted stream: each level's groups are found by the codes that the
    level below hands on. aggs: name -> (sum | count | min | max, column)."""
    current = aggregate_coded(of, columns, [getattr(F, f)(F.lit(1) if c == "*" else F.col(c)).alias(n) for n, (f, c) in aggs.items()])
    names = of.names[:columns]
    again = [(F.sum if f in ("sum", "count") else getattr(F, f))(n).alias(n) for n, (f, _) in aggs.items()]
    out = None
    for j in range(columns, -1, -1):
        if j < columns:
            current = aggregate_coded(current, j, again) if j >= len(of.partitioned_by) else current.plain().groupBy(*names[:j]).agg(*again)
        rows = current.plain() if isinstance(current, OrderedFrame) else current
        empty = [F.lit(None).cast(of.df.schema[c].dataType).alias(c) for c in names[j:]]
        level = rows.select(*names[:j], *empty, F.lit(j).alias("level"), *aggs)
        out = level if out is None else out.unionByName(level)
    return out


def keep(of: OrderedFrame, condition: Column) -> OrderedFrame:
    """A filter that keeps codes right: a survivor's is the greatest since the last survivor.

    Where rows are together by several leading columns, a group's first survivor also takes up what the
    groups before it lost: the greatest code after their last survivors, from a table with a row for
    each group, in order within the first column. Beyond the first column nothing is taken up, as a
    first row there has offset 0.
    """
    of.need_global("a filter that keeps codes")
    lead = of.names[: len(of.partitioned_by)]
    if list(of.partitioned_by) != lead:
        raise ValueError(f"rows must be together by leading key columns, not by {of.partitioned_by}")
    by = [k.order() for k in of.keys if k.name not in of.partitioned_by]
    order = W.partitionBy(*lead).orderBy(*by, F.col(OFFSET), F.col("__keep").desc())
    x = of.df.withColumn("__keep", F.coalesce(condition, F.lit(False)))
    x = x.withColumn("__g", F.coalesce(F.sum(F.col("__keep").cast("int")).over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    upto = W.partitionBy(*lead, "__g").orderBy(*by, F.col(OFFSET), F.col("__keep").desc()).rowsBetween(W.unboundedPreceding, 0)
    coded = x.withColumn(CODE, F.max(CODE).over(upto)).where("__keep")
    if len(lead) > 1:
        piece = x.groupBy(*lead, "__g").agg(F.max(CODE).alias("__m"), F.max(F.col("__keep").cast("int")).alias("__k"))
        group = piece.groupBy(*lead).agg(F.sum("__k").alias("__any"), F.max(F.struct("__g", F.when(F.col("__k") == 0, F.col("__m")).otherwise(F.lit(0).cast("long")).alias("m"))).alias("__t"))
        along = W.partitionBy(lead[0]).orderBy(*[k.order() for k in of.keys[1 : len(lead)]])
        group = group.withColumn("__run", F.sum((F.col("__any") > 0).cast("int")).over(along.rowsBetween(W.unboundedPreceding, 0)))
        since = W.partitionBy(lead[0], "__run").orderBy(*[k.order() for k in of.keys[1 : len(lead)]]).rowsBetween(W.unboundedPreceding, 0)
        group = group.withColumn("__since", F.max(F.col("__t.m")).over(since)).withColumn("__carry", F.lag("__since").over(along))
        carry = group.select(*[F.col(c).alias(f"__h_{c}") for c in lead], "__carry")
        same = None
        for c in lead:
            term = F.col(c).eqNullSafe(F.col(f"__h_{c}"))
            same = term if same is None else same & term
        coded = coded.join(carry, same).withColumn(CODE, F.when(F.col("__g") == 0, F.greatest(F.col(CODE), F.col("__carry"))).otherwise(F.col(CODE)))
        coded = coded.select(*x.columns)
    out = coded.drop("__keep", "__g")
    return of.with_df(out.withColumn(OFFSET, offset_of(F.col(CODE), of.k)))


def shorten(of: OrderedFrame, columns: int) -> OrderedFrame:
    """Fewer key columns: codes follow without looking at rows."""
    code = project(F.col(CODE), of.k, columns)
    df = of.df.withColumn(CODE, code).withColumn(OFFSET, F.least(F.col(OFFSET), F.lit(columns)))
    return OrderedFrame(df, of.keys[:columns], of.scope, of.partitioned_by)


def extend_sort(of: OrderedFrame, columns: int, tail: list) -> OrderedFrame:
    """Sorted on (A, B, ...), wanted on (A, B, C, D): each segment of equal A, B is sorted alone.

    The segment's first row keeps the code that opened the segment, all others differ within the tail.
    Where the rows before sorting are known, only they are sorted, once, by segments: what opens a
    segment then comes from the coded table of segments, and the present order of rows is never made.
    """
    spec = key_spec(tail)
    head = of.names[:columns]
    keys = [*of.keys[:columns], *spec]
    names = [k.name for k in keys]
    w = W.partitionBy(*head).orderBy(*[k.order() for k in spec])
    inside = first_difference(names, [F.lag(c).over(w) for c in names], columns)
    first = F.row_number().over(w) == 1
    if of.source is not None:
        from prefixcode.operators.derive import attach

        heads = attach(of.source.select(*head).distinct(), of.keys[:columns], 1).df
        heads = heads.select(*[F.col(c).alias(f"__h_{c}") for c in head], F.col(OFFSET).alias("__opens"))
        same = None
        for c in head:
            term = F.col(c).eqNullSafe(F.col(f"__h_{c}"))
            same = term if same is None else same & term
        x = of.source.withColumn("__first", first).withColumn("__inside", inside).join(heads, same)
        x = x.withColumn(OFFSET, F.when(F.col("__first"), F.col("__opens")).otherwise(F.col("__inside")).cast("int"))
        x = x.select(*of.source.columns, OFFSET)
        together = tuple(head)
    else:
        opening = F.max(F.when(F.col(OFFSET) < columns, F.col(CODE))).over(W.partitionBy(*head))
        x = of.df.withColumn("__first", first).withColumn("__inside", inside).withColumn("__opening", opening)
        off = F.when(F.col("__first"), offset_of(F.col("__opening"), of.k)).otherwise(F.col("__inside"))
        x = x.withColumn(OFFSET, off.cast("int")).drop("__first", "__inside", "__opening")
        together = of.partitioned_by
    x = x.withColumn(CODE, pack(F.col(OFFSET), value_at(x, keys, F.col(OFFSET)), len(keys)))
    return OrderedFrame(x, keys, of.scope, together)


def analytic(of: OrderedFrame, partition: int, order: int, total: str | None = None) -> DataFrame:
    """row_number, rank, dense_rank and, for a column, its running sum to the end of the peers.

    A row opens a partition where its offset is below ``partition``, a peer group where it is below
    partition + order. No column is compared for it.
    """
    by = [k.order() for k in of.keys if k.name not in of.partitioned_by]
    w = W.partitionBy(*of.partitioned_by).orderBy(*by, F.col(OFFSET))
    upto = w.rowsBetween(W.unboundedPreceding, 0)
    x = of.df.withColumn("__n", F.row_number().over(w))
    opens, peers = F.col(OFFSET) < partition, F.col(OFFSET) < partition + order
    x = x.withColumn("__p", F.max(F.when(opens, F.col("__n"))).over(upto)).withColumn("__r", F.max(F.when(peers, F.col("__n"))).over(upto)).withColumn("__d", F.sum(peers.cast("int")).over(upto))
    x = x.withColumn("__d0", F.max(F.when(opens, F.col("__d"))).over(upto))
    x = x.withColumn("row_number", F.col("__n") - F.col("__p") + 1).withColumn("rank", F.col("__r") - F.col("__p") + 1).withColumn("dense_rank", F.col("__d") - F.col("__d0") + 1)
    if total:
        run = F.sum(total).over(upto)
        x = x.withColumn("__s", run)
        x = x.withColumn("__s0", F.max(F.when(opens, F.struct("__n", (F.col("__s") - F.col(total)).alias("s")))).over(upto)["s"])
        peer_end = F.max(F.struct("__n", "__s")).over(W.partitionBy(*of.partitioned_by, "__r"))["__s"]
        x = x.withColumn("running_sum", peer_end - F.col("__s0")).drop("__s", "__s0")
    return x.drop("__n", "__p", "__r", "__d", "__d0")


def top_k(df: DataFrame, keys: list, k: int) -> DataFrame:
    return df.orderBy(*[x.order() for x in key_spec(keys)]).limit(k)


def top_k_per_segment(of: OrderedFrame, columns: int, k: int) -> DataFrame:
    """The first k rows of every segment, numbered by flags."""
    return analytic(of, columns, 1).where(F.col("row_number") <= k)
