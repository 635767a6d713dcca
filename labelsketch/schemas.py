"""Contracts of the tables that flow between operators."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Both directions present, no nulls, weight > 0, one row per (src, dst).
EDGE_SCHEMA = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()), T.StructField("weight", T.DoubleType())])
LABEL_SCHEMA = T.StructType([T.StructField("id", T.LongType()), T.StructField("label", T.LongType())])
#: Sketch input: ord is the neighbour's position by ascending id, chunk the subset that it belongs to.
PAIR_SCHEMA = T.StructType([T.StructField("dst", T.LongType()), T.StructField("chunk", T.IntegerType()), T.StructField("ord", T.IntegerType()), T.StructField("label", T.LongType()), T.StructField("weight", T.DoubleType())])
SLOTS = T.ArrayType(T.StructType([T.StructField("label", T.LongType()), T.StructField("weight", T.DoubleType())]))
SKETCH_SCHEMA = T.StructType([T.StructField("dst", T.LongType()), T.StructField("chunk", T.IntegerType()), T.StructField("slots", SLOTS)])
METRIC_SCHEMA = T.StructType([T.StructField("method", T.StringType()), T.StructField("graph", T.StringType()), T.StructField("metric", T.StringType()), T.StructField("value", T.DoubleType())])


@dataclass(frozen=True)
class EdgeSpec:
    """The user's column names."""

    src: str = "src"
    dst: str = "dst"
    weight: str | None = "weight"


def conform(df: DataFrame, spec: EdgeSpec = EdgeSpec()) -> DataFrame:
    """The three columns of the contract, renamed and cast; unit weights where there are none."""
    weight = F.col(spec.weight).cast("double") if spec.weight else F.lit(1.0)
    return df.select(F.col(spec.src).cast("long").alias("src"), F.col(spec.dst).cast("long").alias("dst"), weight.alias("weight"))


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """df, if it has the schema's columns with its types."""
    for field in schema:
        if field.name not in df.columns or df.schema[field.name].dataType != field.dataType:
            raise ValueError(f"column {field.name} of type {field.dataType.simpleString()} is missing; got {df.schema.simpleString()}")
    return df
