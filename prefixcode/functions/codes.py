"""Prefix codes: where a row's key first differs from an earlier row's, and with which value.

Ascending form: (K - offset) in 7 bits, then 56 bits of value. The smaller of two codes relative to
the same row belongs to the smaller key; a repeated key has code 0. The algebra:

* chain(code(b|a), code(c|b)) = code(c|a) is the greater of the two, for a <= b <= c;
* a kept row's code after dropped ones is the greatest since the last kept one;
* for fewer key columns, codes at or past the new end become 0, others lose the missing columns.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from prefixcode.functions.keys import VALUE_BITS, VALUE_MAX

MAX_COLUMNS = 127


def pack(offset: Column, value: Column, k: int, form: str = "ascending") -> Column:
    """A code. In the descending form the greater code belongs to the smaller key."""
    if k > MAX_COLUMNS:
        raise ValueError("at most 127 key columns")
    if form == "ascending":
        return F.when(offset >= k, F.lit(0).cast("long")).otherwise(F.shiftleft((F.lit(k) - offset).cast("long"), VALUE_BITS).bitwiseOR(value))
    return F.when(offset >= k, F.shiftleft(F.lit(k).cast("long"), VALUE_BITS)).otherwise(F.shiftleft(offset.cast("long"), VALUE_BITS).bitwiseOR(F.lit(VALUE_MAX) - value))


def offset_of(code: Column, k: int, form: str = "ascending") -> Column:
    high = F.shiftrightunsigned(code, VALUE_BITS).cast("int")
    return F.lit(k) - high if form == "ascending" else high


def value_of(code: Column, form: str = "ascending") -> Column:
    low = code.bitwiseAND(F.lit(VALUE_MAX))
    return low if form == "ascending" else F.lit(VALUE_MAX) - low


def pack_domain(offset: Column, value: Column, k: int, domain: int) -> Column:
    """The decimal form for small domains: (K - offset) * domain + value."""
    return (F.lit(k) - offset) * domain + value


def chain(first: Column, second: Column) -> Column:
    return F.greatest(first, second)


def project(code: Column, k: int, shorter: int) -> Column:
    """The code for the first ``shorter`` of k key columns."""
    offset = offset_of(code, k)
    return F.when(offset >= shorter, F.lit(0).cast("long")).otherwise(code - F.shiftleft(F.lit(k - shorter).cast("long"), VALUE_BITS))


# twins on arrays and plain numbers
def pack_array(offset: np.ndarray, value: np.ndarray, k: int) -> np.ndarray:
    return np.where(offset >= k, 0, ((k - offset).astype(np.int64) << VALUE_BITS) | value)


def offset_array(code: np.ndarray, k: int) -> np.ndarray:
    return k - (code >> VALUE_BITS)


def pack_one(offset: int, value: int, k: int) -> int:
    return 0 if offset >= k else (k - offset) << VALUE_BITS | value


def of_pair(low: tuple, high: tuple) -> int:
    """The code of ``high`` relative to ``low``; whole numbers, low <= high."""
    for i, (a, b) in enumerate(zip(low, high, strict=True)):
        if a != b:
            return pack_one(i, b, len(high))
    return 0


BYTE_VALUE_BITS = 9


def pack_bytes(offset: int, value: int, longest: int) -> int:
    """Byte-granular: (longest - offset), then the byte + 1, or 0 past the end of the key."""
    return (longest - offset) << BYTE_VALUE_BITS | value
