"""Order-preserving key encodings and digits.

Every sort key becomes a signed 64-bit *order key*: values sort as their keys
do, and its unsigned form (sign bit flipped) is the big-endian string of the
key's first eight bytes, whose base-2^bits digits the radix methods read.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

MIN_LONG = -(1 << 63)
KEY_BYTES = 8


def digit(key: Column, position: int, bits: int = 8) -> Column:
    """Digit ``position`` (0: least significant) of a signed key in base 2^bits."""
    return F.shiftrightunsigned(key.bitwiseXOR(F.lit(MIN_LONG)), position * bits).bitwiseAND(F.lit((1 << bits) - 1))


def mask(level: int, bits: int = 8) -> int:
    """The bits that the first ``level`` digits hold, as a signed number."""
    return -1 << max(0, 64 - bits * level)


def floor_key(key: Column, level: int, bits: int = 8) -> Column:
    """The least key with the same first ``level`` digits: names a bin of that level."""
    return key.bitwiseAND(F.lit(mask(level, bits)))


@F.pandas_udf(T.LongType())
def double_order(values: pd.Series) -> pd.Series:
    """Doubles as longs in the same order; -0.0 equals 0.0, NaN is one value above all."""
    v = values.to_numpy(dtype="float64", na_value=np.nan) + 0.0
    v[np.isnan(v)] = np.nan
    b = np.where(v == 0, 0.0, v).view(np.int64)
    return pd.Series(np.where(b >= 0, b, b ^ np.int64(0x7FFFFFFFFFFFFFFF)))


def first_bytes(value: Column) -> Column:
    """The first eight bytes of a binary value, zero padded, as an order key."""
    return F.conv(F.rpad(F.hex(F.substring(value, 1, KEY_BYTES)), 2 * KEY_BYTES, "0"), 16, -10).cast("long").bitwiseXOR(F.lit(MIN_LONG))


def value_key(kind: T.DataType, c: Column) -> Column:
    """Order key of a value by its type; nulls stay null.  Of strings and binaries: their first eight bytes."""
    epoch = F.lit("1970-01-01 00:00:00").cast("timestamp_ntz")
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.BooleanType)):
        return c.cast("long")
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        return F.when(c.isNotNull(), double_order(c.cast("double")))
    if isinstance(kind, T.DecimalType) and kind.precision <= 18:
        return (c * F.lit(10**kind.scale).cast(T.DecimalType(19, 0))).cast("long")
    if isinstance(kind, T.TimestampNTZType):
        return F.timestamp_diff("MICROSECOND", epoch, c)
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(c)
    if isinstance(kind, T.DateType):
        return F.unix_date(c).cast("long")
    if isinstance(kind, T.DayTimeIntervalType):
        return F.timestamp_diff("MICROSECOND", epoch, epoch + c)
    if isinstance(kind, (T.StringType, T.BinaryType)):
        return first_bytes(c.cast("binary"))
    raise TypeError(f"{kind.simpleString()} has no order-preserving encoding")


def whole(kind: T.DataType) -> bool:
    """Whether equal order keys mean equal values."""
    return not isinstance(kind, (T.StringType, T.BinaryType, T.ArrayType))


def item_key(kind: T.ArrayType, c: Column, k: int) -> Column:
    """Order key of an array's item; what isn't there, and null items, come before all values."""
    return F.coalesce(value_key(kind.elementType, F.get(c, F.lit(k))), F.lit(MIN_LONG))


def order_key(df: DataFrame, name: str, ascending: bool = True) -> Column:
    """Order key of a column by its type; nulls stay null."""
    kind, c = df.schema[name].dataType, F.col(f"`{name}`")
    k = F.when(c.isNotNull(), item_key(kind, c, 0)) if isinstance(kind, T.ArrayType) else value_key(kind, c)
    return k if ascending else F.bitwise_not(k)


def common_bytes(low: bytes | None, high: bytes | None) -> int:
    """Bytes that all values between two share at their start."""
    if low is None:
        return 0
    return next((k for k, (x, y) in enumerate(zip(low, high, strict=False)) if x != y), min(len(low), len(high)))


def leading(df: DataFrame, name: str, ascending: bool = True, skip: bool = True) -> Column:
    """Order key of a column; with ``skip``, that of strings passes over the bytes that all of them start with."""
    kind = df.schema[name].dataType
    if skip and isinstance(kind, (T.StringType, T.BinaryType)):
        value = F.col(name).cast("binary")
        return _turned(first_bytes(F.substring(value, common_bytes(*df.agg(F.min(value), F.max(value)).first()) + 1, KEY_BYTES)), ascending)
    return order_key(df, name, ascending)


def following(df: DataFrame, rows: DataFrame, name: str, ascending: bool = True) -> Column | None:
    """What orders ``rows`` of ``df``, equal in ``leading``, further: the bytes or items after those that all of them share; null if they're equal."""
    kind, c = df.schema[name].dataType, F.col(name)
    if isinstance(kind, (T.StringType, T.BinaryType)):
        value = c.cast("binary")
        low, high = rows.agg(F.min(value), F.max(value)).first()
        if low == high:
            return None
        return _turned(first_bytes(F.substring(value, common_bytes(bytes(low), bytes(high)) + 1, KEY_BYTES)), ascending)
    if isinstance(kind, T.ArrayType):
        low, high = rows.agg(F.min(c), F.max(c)).first()
        if low == high:
            return None
        return _turned(item_key(kind, c, next((k for k, (x, y) in enumerate(zip(low, high, strict=False)) if x != y), min(len(low), len(high)))), ascending)
    return None


def _turned(key: Column, ascending: bool) -> Column:
    return key if ascending else F.bitwise_not(key)


def encode(df: DataFrame, columns: list[str], ascending: list[bool] | None = None, nulls_first: bool = True) -> Column:
    """Binary key of several fixed-length columns: a null byte and eight bytes for each."""
    parts = []
    for k, c in enumerate(columns):
        up = ascending is None or ascending[k]
        bits = order_key(df, c, up).bitwiseXOR(F.lit(MIN_LONG))
        body = F.unhex(F.lpad(F.hex(bits), 16, "0"))
        null = F.unhex(F.lit("00" if nulls_first else "FF"))
        parts.append(F.when(F.col(c).isNull(), F.concat(null, F.unhex(F.lit("00" * 8)))).otherwise(F.concat(F.unhex(F.lit("01" if nulls_first else "00")), body)))
    return F.concat(*parts)


def mix64(seed: Column) -> Column:
    """A uniform signed 64-bit value of a string, from its MD5."""
    h = F.md5(seed)
    half = lambda at: F.conv(F.substring(h, at, 8), 16, 10).cast("long")
    return (half(1) - F.lit(1 << 31)) * F.lit(1 << 32) + half(9)


def unit32(seed: Column) -> Column:
    """A uniform number in (0, 1) of a string."""
    return (F.conv(F.substring(F.md5(seed), 1, 8), 16, 10).cast("double") + F.lit(0.5)) / F.lit(4294967296.0)


def zipf_rank(seed: Column, universe: int = 1024) -> Column:
    """Rank under Zipf's law with exponent 0.75, whose continuous inverse is a fourth power."""
    u = unit32(seed)
    return F.floor(F.lit(float(universe)) * (u * u) * (u * u)).cast("long")
