"""Schemas of the engine's tables and a guard for public entries."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

EDGES = T.StructType([T.StructField("scene_id", T.LongType()), T.StructField("u", T.LongType()), T.StructField("v", T.LongType()), T.StructField("aff", T.DoubleType())])
LABELS = T.StructType([T.StructField("scene_id", T.LongType()), T.StructField("node", T.LongType()), T.StructField("label", T.LongType())])
PIXELS = T.StructType([T.StructField("scene_id", T.LongType()), T.StructField("y", T.IntegerType()), T.StructField("x", T.IntegerType()), T.StructField("pixel", T.LongType())])


def assert_schema(df: DataFrame, want: T.StructType) -> DataFrame:
    """df, if it has the wanted columns with these types; extra ones are fine."""
    have = {f.name: f.dataType for f in df.schema.fields}
    for f in want.fields:
        if f.name not in have:
            raise ValueError(f"column {f.name} is missing; there are {sorted(have)}")
        if have[f.name] != f.dataType:
            raise ValueError(f"column {f.name} is {have[f.name].simpleString()}, not {f.dataType.simpleString()}")
    return df
