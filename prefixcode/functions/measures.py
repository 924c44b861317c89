"""What is measured: counts by identities at scale, bounds, and time."""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from statistics import median

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefixcode.plans.frame import CODE, OFFSET, OrderedFrame


def lower_bound(n: int) -> float:
    """log2(n!): comparisons that any sort of n rows needs."""
    return math.lgamma(n + 1) / math.log(2)


def column_bound(n: int, k: int) -> int:
    """Column comparisons that sorting n rows of k key columns needs at most."""
    return k * max(0, n - 1)


def key_depth(n: float, distinct: float) -> float:
    """How many columns of so many distinct values tell n rows apart."""
    return math.log(n) / math.log(distinct)


def run_generation_columns(of: OrderedFrame) -> Column:
    """Column comparisons of run generation that reads columns when needed: offset + 1, at most K, for
    every row but the very first."""
    k = of.k
    each = F.least(F.col(OFFSET) + 1, F.lit(k))
    # the first row of all would count 1 for its offset 0
    return (F.sum(each) - 1).cast("long")


def merge_columns(output: DataFrame, inputs: DataFrame, k: int) -> DataFrame:
    """Column comparisons of a merge whose inputs know their prefixes: prefixes of the output less
    those of the inputs, less one for each repeat that the merge found."""
    o = output.agg(F.sum(OFFSET).alias("o"), F.sum((F.col(OFFSET) >= k).cast("long")).alias("od"))
    i = inputs.agg(F.sum(OFFSET).alias("i"), F.sum((F.col(OFFSET) >= k).cast("long")).alias("id"))
    return o.crossJoin(i).select((F.col("o") - F.col("i")).cast("long").alias("truncated_anew"), (F.col("o") - F.col("i") - (F.col("od") - F.col("id"))).cast("long").alias("column_comparisons"))


def timed(work: Callable[[], object], repeats: int = 3) -> float:
    """Median microseconds of warm runs."""
    work()
    out = []
    for _ in range(repeats):
        t = time.perf_counter_ns()
        work()
        out.append((time.perf_counter_ns() - t) / 1000)
    return median(out)


__all__ = ["CODE", "column_bound", "key_depth", "lower_bound", "merge_columns", "run_generation_columns", "timed"]
