"""Canonical encoding of any key columns to bytes, injective under zero padding.

Every encoding ends in a non-zero terminator, so that no key is a zero-padded form of another. Integers are
eight bytes, most significant first; strings are their UTF-8 bytes; doubles and decimals their shortest
decimal text (-0.0 as 0.0); timestamps microseconds; arrays and structs their parts with lengths before them.
A null anywhere makes the key null, and null keys are no members of a set. Maps, intervals and variants are
refused, because equal values may have unequal forms."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

TERMINATOR = b"\x01"
#: Longer keys are digested first.
MAX_BYTES = 65


def encoded_string(raw: bytes, max_bytes: int = MAX_BYTES) -> bytes:
    """What `encode_key` makes of one string or binary column, for functions that get keys as bytes."""
    key = raw + TERMINATOR
    return hashlib.sha256(key).digest() + b"\x02" if len(key) > max_bytes else key


def long_bytes(c: Column) -> Column:
    """Eight bytes, most significant first."""
    return F.unhex(F.lpad(F.hex(c.cast("long")), 16, "0"))


def _measured(c: Column) -> Column:
    return F.concat(F.unhex(F.lpad(F.hex(F.octet_length(c).cast("long")), 8, "0")), c)


def value_bytes(c: Column, kind: T.DataType) -> Column:
    if isinstance(kind, T.StringType):
        return F.encode(c, "UTF-8")
    if isinstance(kind, T.BinaryType):
        return c
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        return long_bytes(c)
    if isinstance(kind, T.BooleanType):
        return long_bytes(c.cast("int"))
    if isinstance(kind, T.DateType):
        return long_bytes(F.unix_date(c))
    if isinstance(kind, T.TimestampType):
        return long_bytes(F.unix_micros(c))
    if isinstance(kind, T.TimestampNTZType):
        return F.encode(F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS"), "UTF-8")
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        return F.encode(F.when(c == 0, F.lit(0.0).cast(kind)).otherwise(c).cast("string"), "UTF-8")
    if isinstance(kind, T.DecimalType):
        return F.encode(c.cast("string"), "UTF-8")
    if isinstance(kind, T.ArrayType):
        parts = F.transform(c, lambda x: F.hex(_measured(value_bytes(x, kind.elementType))))
        whole = F.concat(long_bytes(F.size(c)), F.unhex(F.concat_ws("", parts)))
        return F.when(~F.exists(c, lambda x: x.isNull()), whole)
    if isinstance(kind, T.StructType):
        return F.concat(*(_measured(value_bytes(c.getField(f.name), f.dataType)) for f in kind.fields))
    raise TypeError(f"keys of type {kind.simpleString()} have no canonical encoding")


def encode_key(df: DataFrame, cols: list[str], max_bytes: int = MAX_BYTES) -> Column:
    """The key of one or more columns; more than `max_bytes` bytes are replaced by their SHA-256."""
    kinds = {f.name: f.dataType for f in df.schema.fields}
    if len(cols) == 1:
        body = value_bytes(F.col(f"`{cols[0]}`"), kinds[cols[0]])
    else:
        body = F.concat(*(_measured(value_bytes(F.col(f"`{c}`"), kinds[c])) for c in cols))
    key = F.concat(body, F.lit(TERMINATOR))
    digest = F.concat(F.unhex(F.sha2(key, 256)), F.lit(b"\x02"))
    return F.when(F.octet_length(key) > max_bytes, digest).otherwise(key)
