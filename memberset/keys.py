"""Keys of any type as 64-bit longs: one expression for builds, lookups and streams."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import (
    BinaryType, BooleanType, ByteType, CharType, DataType, DateType, DecimalType, IntegerType, LongType, ShortType, StringType, TimestampNTZType, TimestampType, VarcharType,
)


def quoted(name: str) -> str:
    return "`" + name.replace("`", "``") + "`"


def columns_of(df: DataFrame) -> list[Column]:
    return [F.col(quoted(c)) for c in df.columns]


def free_names(df: DataFrame, *wanted: str) -> list[str]:
    """The names, each behind as many underscores as it takes to be no column of df."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in wanted:
        while name.lower() in taken:
            name = f"_{name}"
        taken.add(name.lower())
        out.append(name)
    return out


def as_key(c: Column, kind: DataType) -> Column:
    """Integers, booleans, dates (days) and times (microseconds) by value, strings and binaries by their hash; null stays null.

    Other types are refused: a fraction or a wide decimal would lose what tells it from its neighbours.
    """
    if isinstance(kind, (ByteType, ShortType, IntegerType, LongType)):
        return c.cast("long")
    if isinstance(kind, BooleanType):
        return c.cast("int").cast("long")
    if isinstance(kind, (StringType, CharType, VarcharType, BinaryType)):
        return F.when(c.isNotNull(), F.xxhash64(c))
    if isinstance(kind, DateType):
        return F.unix_date(c).cast("long")
    if isinstance(kind, (TimestampType, TimestampNTZType)):
        return F.unix_micros(c.cast("timestamp"))
    if isinstance(kind, DecimalType) and kind.scale == 0 and kind.precision <= 18:
        return c.cast("long")
    raise TypeError(f"no filter key of type {kind.simpleString()}")


def key64(df: DataFrame, key: str | Column) -> Column:
    """The key of df's rows, a column's name or an expression, as a long."""
    c = F.col(quoted(key)) if isinstance(key, str) and key in df.columns else F.col(key) if isinstance(key, str) else key
    return as_key(c, df.select(c.alias("k")).schema["k"].dataType)
