"""Reading tables and edge lists, writing labels."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schemas import EdgeSpec, conform


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_tables(spark: SparkSession, sf_dir: str, names: list[str]) -> dict[str, DataFrame]:
    """The tables, also as temporary views for SQL."""
    found = {n: table(spark, sf_dir, n) for n in names}
    for n, df in found.items():
        df.createOrReplaceTempView(n)
    return found


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", spec: EdgeSpec = EdgeSpec(), schema: str | None = None, **options) -> DataFrame:
    """An edge list of any Spark format (csv, json, orc, parquet, avro if present); text formats need a schema."""
    reader = spark.read.format(fmt).options(**options)
    if schema or fmt in ("csv", "json"):
        reader = reader.schema(schema or f"{spec.src} long, {spec.dst} long" + (f", {spec.weight} double" if spec.weight else ""))
    return conform(reader.load(path), spec)


def read_matrix_market(spark: SparkSession, path: str) -> DataFrame:
    """Directed edges of a coordinate file: comment lines and the size line (the first other line) are skipped.

    A pattern file has no third column; its weights are 1.
    """
    lines = spark.read.text(path).select(F.trim("value").alias("line"), F.monotonically_increasing_id().alias("n")).filter("line <> '' and not startswith(line, '%')")
    first = lines.agg(F.min("n")).first()[0]
    part = F.split("line", r"\s+")
    return lines.filter(F.col("n") != F.lit(first)).select(part[0].cast("long").alias("src"), part[1].cast("long").alias("dst"), F.coalesce(F.get(part, 2).cast("double"), F.lit(1.0)).alias("weight"))


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """Lines of a vertex and its neighbours, blank-separated."""
    part = spark.read.text(path).select(F.split(F.trim("value"), r"\s+").alias("p")).filter(F.size("p") > 1)
    return part.select(F.col("p")[0].cast("long").alias("src"), F.explode(F.slice("p", 2, F.size("p") - 1).cast("array<long>")).alias("dst"), F.lit(1.0).alias("weight"))


def write_labels(labels: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None) -> None:
    writer = labels.write.format(fmt).mode("overwrite")
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
