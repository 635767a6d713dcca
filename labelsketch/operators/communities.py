"""Operators around communities, and the unweighted summaries that the sketches come from."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import sketch as S
from .graph import dense_ids
from .metrics import community_sizes


def top_communities(labels: DataFrame, n: int) -> DataFrame:
    """The n largest communities; the number is the report's feature."""
    return community_sizes(labels).orderBy(F.desc("members"), "label").limit(n)


def relabel_dense(labels: DataFrame) -> DataFrame:
    """id and a label from 0 without gaps, in the order of the labels' decimal strings."""
    ids = dense_ids(labels.select(F.col("label").cast("string").alias("name")), "name", "dense")
    return labels.join(ids, F.col("label").cast("string") == F.col("name")).select("id", F.col("dense").alias("label"))


def profile(labels: DataFrame, attributes: DataFrame, by: str) -> DataFrame:
    """label, value of the attribute, members, for attributes(id, by)."""
    return labels.join(attributes, "id").groupBy("label", by).agg(F.count("*").alias("members"))


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: vertices of either table, those in both, those with equal labels."""
    j = a.select("id", F.col("label").alias("x")).join(b.select("id", F.col("label").alias("y")), "id", "full_outer")
    return j.agg(F.count("*").alias("vertices"), F.count_if(F.col("x").isNotNull() & F.col("y").isNotNull()).alias("both"), F.count_if(F.col("x") == F.col("y")).alias("equal"))


def in_parts(df: DataFrame, item: str, order: str, part_rows: int) -> DataFrame:
    """The stream in bounded parts by its order column, each as an array in that order."""
    part = F.floor(F.col(order) / part_rows).cast("long")
    return df.select(part.alias("part"), F.col(order).alias("ord"), F.col(item).cast("long").alias("label"), F.lit(1.0).alias("weight")).groupBy("part").agg(F.array_sort(F.collect_list(F.struct("ord", "label", "weight"))).alias("pairs"))


def mg_frequent(df: DataFrame, item: str, order: str, k: int, part_rows: int = 4096) -> DataFrame:
    """item, n: what occurs more than rows/(k+1) times. Sketches of bounded parts are merged by subtraction (the bound
    holds for any merge), and the survivors are counted exactly, which is the verification."""
    from .selectors import subtracted

    parts = in_parts(df, item, order, part_rows).select(F.lit(0).alias("dst"), F.col("part").alias("chunk"), S.mg_fold(F.col("pairs"), k).alias("slots"))
    survivors = subtracted(parts, k).select(F.explode("slots.label").alias(item))
    counts = df.join(F.broadcast(survivors), item, "left_semi").groupBy(item).agg(F.count("*").alias("n"))
    total = df.agg(F.count("*").alias("t"))
    return counts.join(F.broadcast(total)).filter(F.col("n") * (k + 1) > F.col("t")).select(F.col(item).alias("item"), "n")


def majority_item(df: DataFrame, item: str, order: str) -> DataFrame:
    """item, n if one item has more than half of the rows, else nothing: the sketch with one slot, verified."""
    return mg_frequent(df, item, order, 1)


def recommend(stats: DataFrame) -> DataFrame:
    """Adds the method that the findings favour: exact label propagation on graphs of degree about 2, else the sketch."""
    return stats.withColumn("method", F.when(F.col("d_avg") < 3, F.lit("exact")).otherwise(F.lit("mg8")))


#: Family of graphs -> what is recommended for quality, and where speed comes first.
RECOMMENDED = {"web": ("mg8", "vote"), "social": ("mg8", "mg8"), "road": ("baseline_b", "baseline_b"), "kmer": ("baseline_a", "baseline_a")}


def recommended(family: str, speed_first: bool = False) -> str:
    return RECOMMENDED[family][speed_first]
