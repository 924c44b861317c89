"""User-defined functions for SQL: codes, truncation counts, and expanding run lengths."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType

from prefixcode.functions.keys import VALUE_BITS


def register(spark: SparkSession) -> None:
    """prefix_code(offset, value, k), prefix_offset(code, k), prefix_value(code) in plain SQL; and
    truncated_cells, a grouped aggregate, and expand_run, a table function."""
    v = VALUE_BITS
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION prefix_code(o INT, x BIGINT, k INT) RETURNS BIGINT RETURN CASE WHEN o >= k THEN 0L ELSE shiftleft(CAST(k - o AS BIGINT), {v}) | x END")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION prefix_offset(c BIGINT, k INT) RETURNS INT RETURN k - CAST(shiftrightunsigned(c, {v}) AS INT)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION prefix_value(c BIGINT) RETURNS BIGINT RETURN c & {(1 << v) - 1}L")
    spark.udf.register("truncated_cells", truncated_cells)
    spark.udtf.register("expand_run", ExpandRun)


@F.pandas_udf(LongType())
def truncated_cells(offset: pd.Series) -> int:
    return int(offset.sum())


@F.pandas_udf(StringType())
def offset_kind(offset: pd.Series, k: pd.Series) -> pd.Series:
    """first, shared or repeat: what an offset says of its row. A scalar function on pandas columns."""
    return pd.Series("shared", index=offset.index).mask(offset == 0, "first").mask(offset >= k, "repeat")


@F.arrow_udf(LongType())
def stored_cells(offset: pa.Array, k: pa.Array) -> pa.Array:
    """Cells that truncation keeps of a row. The same on Arrow columns."""
    return pc.cast(pc.subtract(k, offset), pa.int64())


@F.udtf(returnType=StructType([StructField("pos", LongType()), StructField("value", StringType())]))
class ExpandRun:
    def eval(self, start: int, length: int, value: str) -> Iterator[tuple[int, str]]:
        for i in range(length or 0):
            yield start + i, value
