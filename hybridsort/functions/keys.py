"""Order-preserving fixed-width keys, as upper-case hex text: two characters for each byte (digit)."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

SIGN = -(1 << 63)


def unsigned(c: Column) -> Column:
    """A non-negative integer as 8 bytes."""
    return F.lpad(F.hex(c.cast("long")), 16, "0")


def signed(c: Column) -> Column:
    """Any integer as 8 bytes; the sign bit is flipped so that negatives come first."""
    return F.lpad(F.hex(c.cast("long").bitwiseXOR(F.lit(SIGN))), 16, "0")


def decimal(c: Column, scale: int, precision: int = 18) -> Column:
    """A decimal: up to 18 digits as its unscaled integer, beyond as a sign byte and 38 decimal digits, complemented below zero."""
    if precision <= 18:
        return signed(F.regexp_replace(c.cast(f"decimal(18,{scale})").cast("string"), r"\.", "").cast("long"))
    exact = c.cast(f"decimal(38,{scale})")
    digits = F.when(exact == 0, F.lit("0" * 38)).otherwise(F.lpad(F.regexp_replace(F.abs(exact).cast("string"), r"\.", ""), 38, "0"))
    return F.when(exact < 0, F.concat(F.lit("00"), F.translate(digits, "0123456789", "9876543210"))).when(exact.isNotNull(), F.concat(F.lit("01"), digits))


def timestamp(c: Column) -> Column:
    """Microseconds since the epoch."""
    return signed(F.unix_micros(c.cast("timestamp")))


def date(c: Column) -> Column:
    return signed(F.unix_date(c))


def boolean(c: Column) -> Column:
    return F.when(c, "01").otherwise("00")


def text(c: Column, width: int = 10) -> Column:
    """The first ``width`` UTF-8 bytes, padded with zero bytes; ties are left to the full value."""
    return F.rpad(F.substring(F.hex(F.encode(c, "UTF-8")), 1, 2 * width), 2 * width, "0")


@F.pandas_udf(T.StringType())
def double(values: pd.Series) -> pd.Series:
    """A double as 8 bytes: -0.0 counts as 0.0 and NaN comes last."""
    x = values.to_numpy(dtype=np.float64, na_value=np.nan) + 0.0
    bits = np.where(np.isnan(x), np.float64("nan"), x).view(np.uint64)
    bits = np.where(np.isnan(x), np.uint64(0x7FF8000000000000), bits)
    flipped = np.where(bits >> np.uint64(63) == 1, ~bits, bits | np.uint64(1 << 63))
    raw = flipped.astype(">u8").tobytes().hex().upper()
    return pd.Series([raw[i : i + 16] for i in range(0, len(raw), 16)]).where(values.notna().to_numpy() | np.isnan(x), None)


def floats(c: Column, size: int) -> Column:
    """An array of ``size`` floats or doubles, eight bytes for each: -0.0 counts as 0.0 and NaN comes last."""

    @F.pandas_udf(T.StringType())
    def encode(arrays: pd.Series) -> pd.Series:
        out = []
        for x in arrays:
            if x is None:
                out.append(None)
                continue
            x = np.asarray(x, np.float64)[:size] + 0.0
            bits = np.where(np.isnan(x), np.uint64(0x7FF8000000000000), x.view(np.uint64))
            out.append(np.where(bits >> np.uint64(63) == 1, ~bits, bits | np.uint64(1 << 63)).astype(">u8").tobytes().hex().upper())
        return pd.Series(out, dtype=object)

    return encode(c)


def descending(key: Column) -> Column:
    """Every digit complemented."""
    return F.translate(key, "0123456789ABCDEF", "FEDCBA9876543210")


def nulls(key: Column, value: Column, first: bool = True) -> Column:
    """A leading byte puts nulls before or after all values; their digits are zero."""
    return F.when(value.isNull(), "00" if first else "02").otherwise(F.concat(F.lit("01"), key))


def composite(*parts: Column) -> Column:
    return F.concat(*parts)


def digit(key: Column, i: int) -> Column:
    """Digit number i, from 0."""
    return F.substring(key, 2 * i + 1, 2)


def prefix(key: Column, depth: int) -> Column:
    return F.substring(key, 1, 2 * depth)


def normalize(c: Column, kind: T.DataType, width: int = 10) -> Column:
    """The key of a column by its type; maps and variants have no order."""
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        return signed(c)
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        return double(c.cast("double"))
    if isinstance(kind, T.DecimalType):
        return decimal(c, kind.scale, kind.precision)
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return timestamp(c)
    if isinstance(kind, T.DateType):
        return date(c)
    if isinstance(kind, T.BooleanType):
        return boolean(c)
    if isinstance(kind, T.StringType):
        return text(c, width)
    if isinstance(kind, T.BinaryType):
        return F.rpad(F.substring(F.hex(c), 1, 2 * width), 2 * width, "0")
    raise TypeError(f"{kind.simpleString()} has no order; extract a field first")


def key_pointer(df, key: Column, ptr: list[str]):
    """The pairs of key and pointer of a table; the payload stays behind, as the scan then skips it."""
    return df.select(key.alias("k"), *[F.col(f"`{p}`") for p in ptr])


#: Bytes of a text that serve to part ties.
TIE_BYTES = 64


def tie_digits(c: Column, kind: T.DataType) -> tuple[Column, int, bool]:
    """Digits in the order of a column, nulls first; how many; and whether different values have different digits."""
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        own, width, whole = signed(c), 8, True
    elif isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        own, width, whole = timestamp(c), 8, True
    elif isinstance(kind, T.DateType):
        own, width, whole = date(c), 8, True
    elif isinstance(kind, T.BooleanType):
        own, width, whole = boolean(c), 1, True
    elif isinstance(kind, T.DecimalType):
        own, width, whole = decimal(c, kind.scale, kind.precision), 8 if kind.precision <= 18 else 20, True
    elif isinstance(kind, (T.FloatType, T.DoubleType)):
        x = F.least(F.greatest(c.cast("double"), F.lit(-9.2e18)), F.lit(9.2e18))
        part = F.lpad(F.hex(((x - F.floor(x)) * F.lit(2.0**52)).cast("long")), 14, "0")
        own, width, whole = F.when(F.isnan(c), "F" * 30).otherwise(F.concat(signed(F.floor(x).cast("long")), part)), 15, False
    elif isinstance(kind, (T.StringType, T.BinaryType)):
        raw = F.encode(c, "UTF-8") if isinstance(kind, T.StringType) else c
        own, width, whole = F.rpad(F.hex(F.substring(raw, 1, TIE_BYTES)), 2 * TIE_BYTES, "0"), TIE_BYTES, False
    else:
        raise TypeError(f"{kind.simpleString()} has no order; extract a field first")
    return F.when(c.isNull(), F.lit("0" * (2 * width + 2))).otherwise(F.concat(F.lit("01"), own)), width + 1, whole


def hashed(*columns: str) -> Column:
    """md5 of the columns joined by dashes, in upper-case hex."""
    return F.upper(F.md5(F.concat_ws("-", *[F.col(c).cast("string") for c in columns])))


def uniform_binary(*columns: str) -> Column:
    return F.substring(hashed(*columns), 1, 20)


def uniform_ascii(*columns: str) -> Column:
    """Ten printable characters, in hex."""
    h = hashed(*columns)
    return F.concat(*[F.lpad(F.hex((32 + F.conv(F.substring(h, 2 * i + 1, 2), 16, 10).cast("int") % 95).cast("long")), 2, "0") for i in range(10)])


def skewed(*columns: str) -> Column:
    """Three quarters of the keys share two leading zero bytes."""
    h = hashed(*columns)
    return F.when(F.substring(h, 1, 2) < "C0", F.concat(F.lit("0000"), F.substring(h, 1, 16))).otherwise(F.substring(h, 1, 20))
