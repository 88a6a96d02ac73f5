"""Sort keys: a numeric view of any orderable type, and the slots of nulls and NaN."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Leading bytes of a string that its numeric view holds; 48 bits are exact in a double.
PREFIX_BYTES = 6


@dataclass(frozen=True)
class KeySpec:
    """A sort key and what decides between equal keys.

    ``ties`` should make rows unique where positions must be reproducible.
    ``prefix`` holds leading bytes that the strings of a column share; their
    numeric view begins after it, and strings without it still come out in order.
    """

    column: str
    ascending: bool = True
    nulls_first: bool = True
    ties: tuple[str, ...] = field(default=())
    prefix: bytes = b""

    def plain(self) -> KeySpec:
        """The same key ascending, nulls first and without ties, as models are fitted on it."""
        return replace(self, ascending=True, nulls_first=True, ties=())

    def columns(self) -> list[str]:
        return list(dict.fromkeys([self.column, *self.ties]))

    def order(self) -> list[Column]:
        """Sort expressions on the raw key, then the ties ascending."""
        c = F.col(self.column)
        if self.ascending:
            first = c.asc_nulls_first() if self.nulls_first else c.asc_nulls_last()
        else:
            first = c.desc_nulls_first() if self.nulls_first else c.desc_nulls_last()
        return [first, *(F.col(t).asc() for t in self.ties)]


def as_key(key: KeySpec | str) -> KeySpec:
    return KeySpec(key) if isinstance(key, str) else key


def numeric(df: DataFrame, key: KeySpec | str) -> Column:
    """A double that never decreases as the key grows; rounding is allowed, since local sorts use the raw key.

    Strings and binaries give six bytes after the prefix of the key, time stamps
    their seconds without any time zone, dates their days. Other types are refused.
    """
    key = as_key(key)
    kind, c = df.schema[key.column].dataType, F.col(key.column)
    if isinstance(kind, (T.DoubleType, T.FloatType, T.DecimalType, T.IntegralType)):
        return c.cast("double")
    if isinstance(kind, T.BooleanType):
        return c.cast("int").cast("double")
    if isinstance(kind, T.DateType):
        return F.unix_date(c).cast("double")
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(c).cast("double")
    if isinstance(kind, T.TimestampNTZType):
        second = F.extract(F.lit("SECOND"), c).cast("double")
        return F.unix_date(c.cast("date")) * F.lit(86400.0) + F.hour(c) * F.lit(3600.0) + F.minute(c) * F.lit(60.0) + second
    if isinstance(kind, (T.StringType, T.BinaryType)):
        return byte_prefix(c, key.prefix)
    raise TypeError(f"{key.column}: {kind.simpleString()} has no order-preserving numeric view")


def byte_prefix(c: Column, prefix: bytes = b"") -> Column:
    """Six bytes after ``prefix`` as a number, short strings filled with zero bytes.

    Strings below all with the prefix give -1, those above all of them 2**48.
    """
    raw = c.cast("binary")
    head = F.hex(F.substring(raw, len(prefix) + 1, PREFIX_BYTES))
    code = F.conv(F.rpad(head, 2 * PREFIX_BYTES, "0"), 16, 10).cast("double")
    if not prefix:
        return code
    shared = F.lit(bytearray(prefix))
    inside = F.substring(raw, 1, len(prefix)) == shared
    return F.when(c.isNotNull(), F.when(inside, code).when(raw < shared, F.lit(-1.0)).otherwise(F.lit(float(1 << 8 * PREFIX_BYTES))))


def with_prefix(df: DataFrame, key: KeySpec) -> KeySpec:
    """The key with the leading bytes that its least and its largest string share, and so all strings do."""
    if not isinstance(df.schema[key.column].dataType, (T.StringType, T.BinaryType)):
        return key
    raw = F.col(key.column).cast("binary")
    low, high = df.agg(F.min(raw), F.max(raw)).first()
    if low is None:
        return key
    same = next((i for i, (a, b) in enumerate(zip(low, high, strict=False)) if a != b), min(len(low), len(high)))
    return replace(key, prefix=bytes(low[:same]))


def order_bits_np(x: np.ndarray) -> np.ndarray:
    """Signed 64-bit integers in the order of the doubles; -0.0 equals 0.0, NaN is largest."""
    x = np.where(np.isnan(x), np.nan, x + 0.0)
    bits = x.view(np.int64)
    return np.where(bits < 0, bits ^ np.int64(0x7FFFFFFFFFFFFFFF), bits)


def order_bits(c: Column) -> Column:
    """Order-preserving integer of a double, built from its exponent and mantissa on the JVM.

    Powers of two and quotients by them are exact in doubles, so the result has
    the very bits.
    NaN gives null here, as it has no place among the numbers.
    """
    x = c.cast("double")
    a = F.abs(x)
    exponent = F.greatest(F.lit(-1022.0), F.least(F.lit(1023.0), F.floor(F.log2(a)).cast("double")))
    ratio = a / F.pow(F.lit(2.0), exponent)
    # The logarithm may be one off at powers of two; then the ratio is under 1 or from 2 on.
    above = F.when(ratio < 1, 2 * ratio - 2).when(ratio < 2, ratio - 1).otherwise(ratio / 2)
    normal = (exponent + 1023).cast("long") * F.lit(1 << 52) + (above * F.lit(float(1 << 52))).cast("long")
    small = (a * F.lit(2.0**537) * F.lit(2.0**537)).cast("long")  # below 2**-1022 the value itself counts units of 2**-1074
    size = F.when(a == float("inf"), F.lit(0x7FF << 52)).when(a < 2.0**-1022, small).otherwise(normal)
    return F.when(F.isnan(x), F.lit(None).cast("long")).when(x < 0, -size - 1).otherwise(size)


def valid(x: Column) -> Column:
    """Whether a model can place the value: neither null nor NaN."""
    return x.isNotNull() & ~F.isnan(x)


def slotted(bucket: Column, x: Column, buckets: int, key: KeySpec) -> Column:
    """Final bucket in output order: nulls at their end, NaN above every number, mirrored if descending."""
    slot = F.when(F.isnan(x), F.lit(buckets + 1)).otherwise(bucket + 1)
    if not key.ascending:
        slot = F.lit(buckets + 2) - slot
    return F.when(x.isNull(), F.lit(0 if key.nulls_first else buckets + 2)).otherwise(slot).cast("int")
