"""The column of values that all methods work on, and literals of its type."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

FLOATING = (T.DoubleType, T.FloatType)
NUMERIC = (*FLOATING, T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.DecimalType)
TEMPORAL = (T.DateType, T.TimestampType, T.TimestampNTZType, T.DayTimeIntervalType)
NAN_POLICIES = ("last", "drop", "error")


def value_column(df: DataFrame, col: str | Column, nan_policy: str = "last") -> DataFrame:
    """``df`` as one column ``v`` without nulls, the bare column, so that filters on it reach the
    scan. -0.0 equals 0.0 throughout and is given back as 0.0. NaN is a value above all
    others (``last``), left out (``drop``) or refused by the first count (``error``)."""
    if nan_policy not in NAN_POLICIES:
        raise ValueError(f"no NaN policy {nan_policy!r}")
    out = df.select((F.col(col) if isinstance(col, str) else col).alias("v"))
    kind = out.schema["v"].dataType
    if isinstance(kind, (T.BooleanType, T.ArrayType, T.MapType, T.VariantType, T.BinaryType)):
        raise TypeError(f"quantiles need ordered scalars or structs of them, not {kind.simpleString()}")
    out = out.where("v IS NOT NULL")
    if isinstance(kind, FLOATING) and nan_policy == "drop":
        out = out.where(~F.isnan("v"))
    return out


def kind_of(values: DataFrame) -> T.DataType:
    return values.schema["v"].dataType


def literal(value, kind: T.DataType) -> Column:
    """``value`` as a literal of exactly that type, so that comparisons push down."""
    if isinstance(kind, T.StructType):
        return F.struct(*[literal(value[f.name], f.dataType).alias(f.name) for f in kind.fields])
    if isinstance(kind, T.TimestampNTZType):
        return F.expr(f"TIMESTAMP_NTZ'{value.isoformat(sep=' ')}'")
    return F.lit(value).cast(kind)
