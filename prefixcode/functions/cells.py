"""Exact key cells for the kernels: one for each key value, in the wanted order.

Whole numbers, dates, timestamps and doubles become one number of at most 66 bits that stands for the
value exactly. Texts, bytes and decimals become (number, value): the number never falls as the value
rises, the value decides where numbers are equal; it is empty where the number says all, as for texts of
up to six bytes. So equal cells mean equal keys, whatever the type.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from prefixcode.functions.keys import KeyCol, kinds

_SIGN = 1 << 63
_LAST = (1 << 64) + 1  # a null after all 64-bit numbers
_FIRST_BYTES = 6
_TEXT_LAST = (1 << 8 * _FIRST_BYTES + 3) + 2


def cell_column(key: KeyCol, kind: T.DataType) -> Column:
    """The key column as the type that a cell is made from."""
    c = F.col(key.name)
    if isinstance(kind, (T.BooleanType, T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        return c.cast("long")
    if isinstance(kind, T.DateType):
        return F.unix_date(c).cast("long")
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return F.unix_micros(c.cast("timestamp"))
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        return c.cast("double")
    if isinstance(kind, T.DecimalType):
        return c
    if isinstance(kind, (T.StringType, T.BinaryType)):
        return c.cast("binary")
    raise TypeError(f"{kind.simpleString()} can't be a key here")


def exact(kind: T.DataType) -> bool:
    """Whether a cell of this type is a plain number."""
    return not isinstance(kind, (T.DecimalType, T.StringType, T.BinaryType))


def _number(v: int, ascending: bool) -> int:
    return v + _SIGN + 1 if ascending else _SIGN - v


def maker(key: KeyCol, kind: T.DataType) -> Callable[[pa.Array], list]:
    """Arrow column of ``cell_column`` -> cells."""
    up, first = key.ascending, key.first_null
    if exact(kind):
        null = 0 if first else _LAST
        if isinstance(kind, (T.DoubleType, T.FloatType)):

            def doubles(a: pa.Array) -> list:
                x = np.array(a.to_numpy(zero_copy_only=False), dtype=np.float64) + 0.0
                x[np.isnan(x)] = np.nan  # one NaN, above infinity
                bits = x.view(np.int64)
                bits = bits ^ ((bits >> 63) & np.int64(0x7FFFFFFFFFFFFFFF))
                valid = a.is_valid().to_pylist()
                return [_number(v, up) if ok else null for v, ok in zip(bits.tolist(), valid, strict=True)]

            return doubles
        return lambda a: [null if v is None else _number(v, up) for v in a.to_pylist()]
    if isinstance(kind, T.DecimalType):
        empty = (0, 0) if first else (_LAST, 0)
        edge = _SIGN - 1

        def decimals(a: pa.Array) -> list:
            out = []
            for v in a.to_pylist():
                if v is None:
                    out.append(empty)
                    continue
                sign, digits, exponent = v.as_tuple()
                n = int("".join(map(str, digits))) * 10 ** (exponent + kind.scale) * (-1 if sign else 1)
                out.append((_number(max(-edge, min(edge, n)), up), n if up else -n))
            return out

        return decimals
    empty = (0, b"" if up else ()) if first else (_TEXT_LAST, b"" if up else ())

    def texts(a: pa.Array) -> list:
        out = []
        for v in a.to_pylist():
            if v is None:
                out.append(empty)
                continue
            n = (int.from_bytes(v[:_FIRST_BYTES].ljust(_FIRST_BYTES, b"\0"), "big") << 3 | min(len(v), 7)) + 1
            if len(v) <= _FIRST_BYTES:
                out.append((n, b"") if up else (_TEXT_LAST - n, ()))
            else:
                out.append((n, v) if up else (_TEXT_LAST - n, (*(-b for b in v), 1)))
        return out

    return texts


def cells_of(df: DataFrame, spec: list[KeyCol]) -> tuple[list[Column], list[Callable[[pa.Array], list]], bool]:
    """(columns to select, makers, whether all cells are plain numbers)."""
    types = kinds(df, spec)
    return [cell_column(k, t) for k, t in zip(spec, types, strict=True)], [maker(k, t) for k, t in zip(spec, types, strict=True)], all(map(exact, types))
