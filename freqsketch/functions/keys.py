"""Item keys: any column type as a BIGINT that the hash functions take."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

NULL_KEY = -1


def fingerprint(text: Column, bits: int = 32) -> Column:
    """Leading hex digits of md5: 8 of them, or 15 for 64-bit keys."""
    return F.conv(F.substring(F.md5(text), 1, 8 if bits == 32 else 15), 16, 10).cast("long")


def item_key(df: DataFrame, name: str, bits: int = 32, nulls: str = "skip") -> Column:
    """The key of a column by its type. Integers as they are, dates as days, timestamps as
    microseconds, short decimals unscaled, all else by fingerprint of its text. ``nulls``:
    'skip' leaves null (builders drop it), 'item' makes nulls one reserved item."""
    kind = df.schema[name].dataType
    c = F.col(f"`{name}`")
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        key = c.cast("long")
    elif isinstance(kind, T.BooleanType):
        key = c.cast("int").cast("long")
    elif isinstance(kind, T.DateType):
        key = F.unix_date(c).cast("long")
    elif isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        key = F.unix_micros(c.cast("timestamp"))
    elif isinstance(kind, T.DecimalType) and kind.precision <= 18:
        key = (c * F.lit(10**kind.scale)).cast("long")
    elif isinstance(kind, (T.DoubleType, T.FloatType)):
        plain = F.when(c == 0, F.lit(0.0)).otherwise(c.cast("double"))  # one zero; NaN prints alike
        key = fingerprint(plain.cast("string"), bits)
    elif isinstance(kind, (T.StringType, T.BinaryType)):
        key = fingerprint(c, bits)
    elif isinstance(kind, T.StructType):
        parts = [F.coalesce(c[f].cast("string"), F.lit("\0")) for f in kind.fieldNames()]
        key = fingerprint(F.concat(*[F.concat(F.length(p).cast("string"), F.lit(":"), p) for p in parts]), bits)
    else:
        raise TypeError(f"explode or convert {kind.simpleString()} first")
    return F.coalesce(key, F.lit(NULL_KEY).cast("long")) if nulls == "item" else key


def byte_columns(key: Column, chars: int) -> list[Column]:
    """The key's bytes, the lowest first; negative keys in two's complement."""
    return [F.shiftright(key, 8 * i).bitwiseAND(F.lit(255)).cast("int") for i in range(chars)]


def words(text: Column) -> Column:
    """Runs of a-z in lower-cased text."""
    return F.filter(F.split(F.lower(text), "[^a-z]+"), lambda w: w != "")


def url_host(url: Column) -> Column:
    return F.regexp_extract(url, r"^[a-z]+://([^/:]+)", 1)
