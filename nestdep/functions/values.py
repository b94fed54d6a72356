"""Value identity: two values are equal iff their keys are.

A key is one letter for the domain and a canonical text: n numbers, s strings,
b booleans, t dates and timestamps.  Whole doubles print like integers, -0.0
like 0; NaN is no value.  A decimal prints like the double that equals it, if
there is one, else by its own digits, so that decimals of equal doubles stay
apart.  Strings, numbers and booleans never meet.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

_WHOLE = float(1 << 63)  # whole doubles below it are exact as long integers


def _double_text(x: Column) -> Column:
    return F.when((x == F.floor(x)) & (F.abs(x) < _WHOLE), x.cast("long").cast("string")).otherwise(x.cast("string"))


def value_key(value: Column, kind: T.DataType) -> Column:
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        return F.concat(F.lit("n"), value.cast("string"))
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        x = value.cast("double")
        return F.when(~F.isnan(x), F.concat(F.lit("n"), _double_text(x)))
    if isinstance(kind, T.DecimalType):
        x = value.cast("double")
        plain = value.cast("string")
        digits = F.when(plain.contains("."), F.regexp_replace(plain, r"\.?0+$", "")).otherwise(plain)
        same = F.coalesce(x.try_cast(f"decimal(38,{kind.scale})") == value, F.lit(False))
        return F.concat(F.lit("n"), F.when(same, _double_text(x)).otherwise(digits))
    if isinstance(kind, (T.StringType, T.VarcharType, T.CharType)):
        return F.concat(F.lit("s"), value)
    if isinstance(kind, T.BooleanType):
        return F.concat(F.lit("b"), value.cast("string"))
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType, T.DateType)):
        return F.concat(F.lit("t"), F.unix_micros(value.cast("timestamp")).cast("string"))
    if isinstance(kind, T.NullType):
        return F.lit(None).cast("string")
    raise TypeError(f"values of type {kind.simpleString()} have no identity here")


def keys_of(values: Column, kind: T.DataType) -> Column:
    """Keys of an array of values, without missing ones."""
    return F.filter(F.transform(values, lambda v: value_key(v, kind)), lambda k: k.isNotNull())


def where_type(cells: DataFrame, tag: str) -> DataFrame:
    return cells.where(F.substring("value", 1, 1) == tag)
