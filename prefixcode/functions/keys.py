"""Sort keys and their normalisation to order-preserving whole numbers.

A key column's value becomes a number between 1 and 2**56 - 2, so that ascending numbers mean the
wanted order; NULL takes 0 or 2**56 - 1. Only the one column that a code needs is ever normalised.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

VALUE_BITS = 56
VALUE_MAX = (1 << VALUE_BITS) - 1
_HALF = 1 << 54
_SCALE = 10_000  # steps of a floating value told apart


@dataclass(frozen=True)
class KeyCol:
    name: str
    ascending: bool = True
    nulls_first: bool | None = None  # None: first if ascending, as Spark's default

    @property
    def first_null(self) -> bool:
        return self.ascending if self.nulls_first is None else self.nulls_first

    def order(self) -> Column:
        c = F.col(self.name)
        if self.ascending:
            return c.asc_nulls_first() if self.first_null else c.asc_nulls_last()
        return c.desc_nulls_first() if self.first_null else c.desc_nulls_last()


KeyLike = "str | KeyCol"


def key_spec(keys: list) -> list[KeyCol]:
    """Names, names with a leading minus for descending, or KeyCols."""
    return [k if isinstance(k, KeyCol) else KeyCol(k[1:], ascending=False) if k.startswith("-") else KeyCol(k) for k in keys]


def lossless(kind: T.DataType) -> bool:
    """Whether equal numbers prove equal values, for all values of the type.

    Bigints and timestamps within 2**53 of zero are exact, beyond that 1,024 neighbours share a number.
    """
    return isinstance(kind, (T.BooleanType, T.ByteType, T.ShortType, T.IntegerType, T.DateType))


def _wide(x: Column) -> Column:
    """Any bigint in 55 bits: itself within 2**53 of zero, beyond that without its last ten bits."""
    far = F.lit(1 << 53)
    return F.when(x >= far, far + F.shiftright(x - far, 10)).when(x < -far, -far + F.shiftright(x + far, 10)).otherwise(x)


def _number(c: Column, kind: T.DataType) -> Column:
    if isinstance(kind, T.BooleanType):
        return c.cast("int").cast("long")
    if isinstance(kind, T.LongType):
        return _wide(c)
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType)):
        return c.cast("long")
    if isinstance(kind, T.DateType):
        return F.unix_date(c).cast("long")
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return _wide(F.unix_micros(c.cast("timestamp")))
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        x = c.cast("double")
        most = float(_HALF - 1)
        return F.when(F.isnan(x), F.lit(_HALF - 1)).otherwise(F.greatest(F.lit(-most), F.least(F.lit(most), F.floor(F.greatest(F.lit(-9e13), F.least(F.lit(9e13), x)) * _SCALE).cast("double"))).cast("long"))
    if isinstance(kind, T.DecimalType):
        return F.greatest(F.lit(1 - _HALF), F.least(F.lit(_HALF - 1), F.floor(c.cast("double") * _SCALE).cast("long")))
    if isinstance(kind, (T.StringType, T.BinaryType)):
        first = F.rpad(F.hex(F.substring(c.cast("binary"), 1, 6)), 12, "0")
        return F.conv(first, 16, 10).cast("long") - F.lit(_HALF)
    if isinstance(kind, T.ArrayType):
        return F.when(F.size(c) == 0, F.lit(1 - _HALF)).otherwise(F.coalesce(_number(F.get(c, F.lit(0)), kind.elementType), F.lit(1 - _HALF)))
    raise TypeError(f"{kind.simpleString()} can't be a key")


def normalize(key: KeyCol, kind: T.DataType) -> Column:
    """The number of a key column, direction and NULL considered."""
    c = F.col(key.name)
    n = _number(c, kind)
    inside = n + F.lit(_HALF)
    if isinstance(kind, (T.StringType, T.BinaryType)):
        inside = n + F.lit(_HALF + 1)
    if not key.ascending:
        inside = F.lit(VALUE_MAX) - inside
    null = F.lit(0 if key.first_null else VALUE_MAX).cast("long")
    return F.when(c.isNull(), null).otherwise(inside)


def kinds(df: DataFrame, keys: list[KeyCol]) -> list[T.DataType]:
    return [df.schema[k.name].dataType for k in keys]


def normalize_bytes(columns: list[str]) -> Column:
    """One binary key for byte-granular codes: texts with an end mark that sorts before any byte."""
    return F.concat(*[x for c in columns for x in (F.coalesce(F.col(c).cast("binary"), F.lit(b"")), F.lit(b"\x00"))]) if len(columns) > 1 else F.coalesce(F.col(columns[0]).cast("binary"), F.lit(b""))


def pack_bits(columns: list[tuple[Column, int]]) -> Column:
    """Several columns of few values in one bigint, so that one integer sorts them all.

    columns: (whole number from 0, bits); at most 63 bits together.
    """
    if sum(b for _, b in columns) > 63:
        raise ValueError("more than 63 bits")
    out = F.lit(0).cast("long")
    for c, bits in columns:
        out = F.shiftleft(out, bits).bitwiseOR(c.cast("long"))
    return out
