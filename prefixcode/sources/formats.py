"""Truncated rows and run-length columns as tables, and back, by DataFrame operations alone."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from prefixcode.plans.frame import CODE, OFFSET, OrderedFrame

PREFIX = "__prefix"
POS = "__pos"


def positions(of: OrderedFrame, extra: list[str] | None = None) -> DataFrame:
    """Rows with their place in the block (the frame's partition), from 0."""
    by = [k.order() for k in of.keys if k.name not in of.partitioned_by]
    w = W.partitionBy(*of.partitioned_by).orderBy(*by, F.col(OFFSET), *(extra or []))
    return of.df.withColumn(POS, (F.row_number().over(w) - 1).cast("long"))


def truncate(of: OrderedFrame, layout: str = "nulls") -> DataFrame:
    """The shared leading key columns are left out; __prefix says how many.

    The first column of a block's partition stays as the block's name. layout "array": the kept
    columns as one array of texts; their number tells the prefix.
    """
    x = positions(of)
    block = [F.col(c).alias(f"__block_{c}") for c in of.partitioned_by]
    rest = [c for c in of.plain().columns if c not in of.names]
    kept = [F.when(F.col(OFFSET) <= j, F.col(c)).alias(c) for j, c in enumerate(of.names)]
    if layout == "array":
        tail = F.slice(F.array(*[F.col(c).cast("string") for c in of.names]), F.col(OFFSET) + 1, F.lit(of.k))
        return x.select(*block, POS, F.when(F.col(OFFSET) >= of.k, F.array().cast("array<string>")).otherwise(tail).alias("tail"), *rest)
    return x.select(*block, POS, F.col(OFFSET).alias(PREFIX), *kept, *rest)


def expand(stored: DataFrame, names: list[str], blocks: list[str]) -> DataFrame:
    """Truncated rows -> whole rows: each column's last stored value, true nulls included. A block's
    columns come from its name."""
    w = W.partitionBy(*[f"__block_{c}" for c in blocks]).orderBy(POS).rowsBetween(W.unboundedPreceding, 0)
    last = [F.col(f"__block_{c}").alias(c) if c in blocks else F.last(F.when(F.col(PREFIX) <= j, F.struct(F.col(c).alias("v"))), ignorenulls=True).over(w)["v"].alias(c) for j, c in enumerate(names)]
    rest = [c for c in stored.columns if c not in names and not c.startswith("__")]
    return stored.select(*last, F.col(PREFIX).alias(OFFSET), *rest)


def expand_array(stored: DataFrame, names: list[str], blocks: list[str]) -> DataFrame:
    """Truncated rows of layout "array" -> whole rows, as texts: the tail's length tells the prefix, and a
    column of a row has the last stored value of that column."""
    k = len(names)
    prefix = F.lit(k) - F.size("tail")
    w = W.partitionBy(*[f"__block_{c}" for c in blocks]).orderBy(POS).rowsBetween(W.unboundedPreceding, 0)
    cells = [F.last(F.when(prefix <= j, F.struct(F.get("tail", F.lit(j) - prefix).alias("v"))), ignorenulls=True).over(w)["v"].alias(c) for j, c in enumerate(names)]
    rest = [c for c in stored.columns if c != "tail" and not c.startswith("__")]
    return stored.select(*cells, prefix.alias(OFFSET), *rest)


def to_rle(of: OrderedFrame) -> DataFrame:
    """Runs of every key column: block columns, col_no, run_start, run_len, value (as text).

    A run of column j begins where the offset is at most j; it ends where the next one begins.
    """
    x = positions(of)
    block = [F.col(c).alias(f"__block_{c}") for c in of.partitioned_by]
    size = F.count(F.lit(1)).over(W.partitionBy(*of.partitioned_by))
    cells = F.array(*[F.struct(F.lit(j).alias("col_no"), F.col(c).cast("string").alias("value")) for j, c in enumerate(of.names)])
    starts = x.withColumn("__size", size).where(F.col(OFFSET) < of.k).select(*block, POS, "__size", F.explode(F.slice(cells, F.col(OFFSET) + 1, F.lit(of.k))).alias("c"))
    w = W.partitionBy(*[f"__block_{c}" for c in of.partitioned_by], "c.col_no").orderBy(POS)
    length = F.coalesce(F.lead(POS).over(w), F.col("__size")) - F.col(POS)
    return starts.select(*[f"__block_{c}" for c in of.partitioned_by], F.col("c.col_no").alias("col_no"), F.col(POS).alias("run_start"), length.alias("run_len"), F.col("c.value").alias("value"))


def pack_runs(runs: DataFrame, blocks: list[str]) -> DataFrame:
    """One row for each block and column: its runs as an array of (value, how many rows), in order.

    Blocks should be bounded (see ``blocked``), as a block's runs come together in one array.
    """
    cells = F.sort_array(F.collect_list(F.struct("run_start", "value", "run_len")))
    packed = F.transform(cells, lambda c: F.struct(c["value"].alias("value"), c["run_len"].alias("run_len")))
    return runs.groupBy(*[f"__block_{c}" for c in blocks], "col_no").agg(packed.alias("runs"))


def unpack_runs(packed: DataFrame, blocks: list[str]) -> DataFrame:
    """Back to a row for each run; its start is the sum of the lengths before it in the block."""
    block = [f"__block_{c}" for c in blocks]
    each = packed.select(*block, "col_no", F.posexplode("runs").alias("__i", "r"))
    w = W.partitionBy(*block, "col_no").orderBy("__i").rowsBetween(W.unboundedPreceding, -1)
    return each.select(*block, "col_no", F.coalesce(F.sum("r.run_len").over(w), F.lit(0)).alias("run_start"), F.col("r.run_len").alias("run_len"), F.col("r.value").alias("value"))


def blocked(of: OrderedFrame, rows: int) -> OrderedFrame:
    """Cut the partitions into blocks of so many rows; a block's first row has offset 0 and stands alone."""
    x = positions(of).withColumn("__blockno", F.floor(F.col(POS) / rows))
    first = F.col(POS) % rows == 0
    from prefixcode.functions.codes import pack
    from prefixcode.operators.derive import value_at

    zero = pack(F.lit(0), value_at(x, of.keys, F.lit(0)), of.k)
    x = x.withColumn(CODE, F.when(first, zero).otherwise(F.col(CODE))).withColumn(OFFSET, F.when(first, F.lit(0)).otherwise(F.col(OFFSET))).drop(POS)
    return OrderedFrame(x, of.keys, "block", (*of.partitioned_by, "__blockno"))


_PART = 4096


def repeated(df: DataFrame, times: Column, name: str) -> DataFrame:
    """Each row ``times`` times, numbered from 0; no array is longer than a part, however often."""
    x = df.withColumn("__times", times.cast("long")).where("__times > 0")
    x = x.withColumn("__from", F.explode(F.sequence(F.lit(0).cast("long"), F.col("__times") - 1, F.lit(_PART).cast("long"))))
    x = x.withColumn(name, F.explode(F.sequence(F.col("__from"), F.least(F.col("__from") + (_PART - 1), F.col("__times") - 1))))
    return x.drop("__times", "__from")


def from_rle(runs: DataFrame, names: list[str], blocks: list[str]) -> DataFrame:
    """Runs -> rows (texts) with their offset: the first column whose run begins there, or all.

    The last column's runs say which rows there are; the other columns' runs meet them where they
    begin, and each row takes the last value before it. A row is made once, not once for each column.
    """
    block = [f"__block_{c}" for c in blocks]
    k = len(names)
    last = repeated(runs.where(F.col("col_no") == k - 1), F.col("run_len"), "__i")
    rows = last.select(*block, (F.col("run_start") + F.col("__i")).alias(POS), F.col("value").alias("__last"), (F.col("__i") == 0).alias("__new"))
    cells = [F.max(F.when(F.col("col_no") == j, F.struct(F.col("value").alias("v")))).alias(f"__v{j}") for j in range(k - 1)]
    starts = runs.where(F.col("col_no") < k - 1).groupBy(*block, F.col("run_start").alias("__at")).agg(F.min("col_no").alias("__first"), *cells)
    on = F.col(POS) == F.col("__at")
    for c in block:
        on = on & rows[c].eqNullSafe(starts[c])
    x = rows.join(starts, on, "left").select(*[rows[c] for c in block], POS, "__last", "__new", "__first", *[f"__v{j}" for j in range(k - 1)])
    w = W.partitionBy(*block).orderBy(POS).rowsBetween(W.unboundedPreceding, 0)
    values = [F.last(f"__v{j}", ignorenulls=True).over(w)["v"].alias(c) for j, c in enumerate(names[:-1])]
    first = F.coalesce(F.col("__first"), F.when(F.col("__new"), F.lit(k - 1)).otherwise(F.lit(k)))
    return x.select(*block, POS, *values, F.col("__last").alias(names[-1]), first.cast("int").alias(OFFSET))


def rle_sums(runs: DataFrame, col_no: int, kind: str = "double") -> Column:
    """Sum of a column from its runs: value times length, nothing expanded."""
    return F.sum(F.when(F.col("col_no") == col_no, F.col("value").cast(kind) * F.col("run_len")))


def summary(of: OrderedFrame) -> DataFrame:
    """n, columns, stored cells, truncated cells, ratio (total over stored, rounded down)."""
    k = of.k
    stored = F.sum(F.lit(k) - F.col(OFFSET))
    n = F.count(F.lit(1))
    return of.df.agg(n.alias("n"), stored.cast("long").alias("stored"), (n * k - stored).cast("long").alias("truncated"), F.floor(n * k / stored).cast("long").alias("ratio"))
