"""Explicit schemas of the relations that the operators exchange, and checks at the API's entry."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

VERTICES = T.StructType([T.StructField("id", T.LongType(), False)])
EDGES = T.StructType([T.StructField("src", T.LongType(), False), T.StructField("dst", T.LongType(), False)])
WEDGES = T.StructType([*EDGES.fields, T.StructField("w", T.DoubleType(), False)])
ROUND_STATS = T.StructType(
    [
        T.StructField("run", T.StringType()),
        T.StructField("round", T.IntegerType()),
        T.StructField("phase", T.StringType()),
        T.StructField("messages_emitted", T.LongType()),
        T.StructField("state_rows", T.LongType()),
        T.StructField("changed", T.BooleanType()),
        T.StructField("seconds", T.DoubleType()),
    ]
)


class SchemaError(ValueError):
    """A frame lacks a column, or has it in another type."""


def require(df: DataFrame, *columns: str) -> DataFrame:
    """``df`` cut down to ``columns``; SchemaError names what is missing."""
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise SchemaError(f"missing {missing}; the frame has {df.columns}")
    return df.select(*columns)
